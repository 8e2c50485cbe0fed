"""The stages of the pipeline on nulls, empty and long texts, ties, repeated rows, no rows, and names of their own."""

import corpus_pipeline as c

PROSE = [" ".join(f"w{(7 * i + k * k) % 911}" for k in range(60)) for i in range(12)]


def table(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, score string, n_lines int, leaks string, text_key int, gone_id int, __lines string")


def test_every_stage_has_a_result_for_odd_rows(spark, sf):
    extra = ("kept as it is", 9, "mine", 3, 4, "five")
    rows = [(i, t, "en", "s", len(t), *extra) for i, t in enumerate(PROSE)]
    rows += [(100, None, None, None, None, *extra), (101, "", "en", "s", 0, *extra), (102, " \n\t", "en", "s", 3, *extra), (None, "no id " + PROSE[3][::-1], "en", "s", 10, *extra)]
    rows += [(103, PROSE[0], "en", "s", 1, *extra), (5, "another text under the id five, not a copy of any", "en", "s", 2, *extra), (5, "another text under the id five, not a copy of any", "en", "s", 2, *extra)]
    rows += [(104, " ".join(f"v{k % 7919}" for k in range(60_000)), "en", "s", 4, *extra)]
    docs, names = table(spark, rows), None
    names = docs.columns
    for name, stage in c.STAGES:
        done = c.written(stage(spark, docs, sf), name)
        if name == "byte_bpe":
            assert done.count() == docs.count() and done.where("not round_trip").count() == 0
            break
        assert done.columns == names
        assert all((r.score, r.n_lines, r.leaks, r.text_key, r.gone_id, r["__lines"]) == extra for r in done.collect())
        docs = done
    ids = [r.doc_id for r in docs.collect()]
    assert {100, 101, 102, 104, None} <= set(ids) and 103 not in ids and set(range(12)) <= set(ids)
    texts = {r.text for r in docs.where("doc_id = 5").collect()}
    assert PROSE[5] in texts and len(texts) == 2


def test_every_stage_takes_an_empty_table(spark, sf):
    docs = table(spark, [])
    for name, stage in c.STAGES:
        done = stage(spark, docs, sf)
        assert done.count() == 0
        if name != "byte_bpe":
            assert done.columns == docs.columns
