"""Benchmark items far longer than a window are found, whole or paraphrased."""

import random

import pytest

from private_traces.llm import decontaminate


@pytest.mark.parametrize("others", [0, 200])
def test_long_items_are_found(spark, others):
    r = random.Random(8)
    words = ["".join(r.choice("abcdefgh") for _ in range(7)) for _ in range(4000)]
    items = [(7, words[:400])] + [(100 + i, r.sample(words[1000:], 40)) for i in range(others)]
    changed = [w if k % 4 != 1 else "other" for k, w in enumerate(words[:400])]
    rows = [(1, words[500:600] + words[:400] + words[600:700]), (2, words[500:700] + changed), (3, words[500:1000]), (4, words[:120] + words[500:900])]
    docs = spark.createDataFrame([(i, " ".join(w)) for i, w in rows], "doc_id long, text string")
    bench = spark.createDataFrame([(i, " ".join(w)) for i, w in items], "item_id long, text string")
    got = {x.doc_id: x for x in decontaminate.flags(docs, bench).collect()}
    assert [i for i in got if got[i].contaminated and 7 in got[i].item_ids] == [1, 2] and got[1].share == 1.0
    assert not got[3].contaminated and not got[4].contaminated
