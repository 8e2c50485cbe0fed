"""The training sample where one text is a large part of a language."""

import numpy as np

from private_traces.llm import language


def test_copies_of_one_text_are_drawn_apart(spark, monkeypatch):
    taken = []
    plain = language._count

    for text in ("copied words of one text", "another copied line", "third of them", "a fourth one"):
        data = [(i, text if i < 3000 else f"own words {i} again", "xx") for i in range(6000)]
        docs = spark.createDataFrame(data, "doc_id long, text string, lang string")
        seen, copies = (spark.sparkContext.accumulator(0) for _ in range(2))

        def watched(batches, bits, text=text, seen=seen, copies=copies):
            for b in batches:
                texts = b.column("text").to_pylist()
                seen.add(len(texts))
                copies.add(texts.count(text))
                yield from plain(iter([b]), bits)

        monkeypatch.setattr(language, "_count", watched)
        names, logs = language.fit(docs, per_language=1000, bits=10)
        taken.append((seen.value, copies.value))
        assert names == ["xx"] and np.isfinite(logs).all()
    assert all(850 < n < 1150 and 400 < k < 600 for n, k in taken), taken
