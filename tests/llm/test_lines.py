"""Line dedup against all pairs of lines."""

import random

import pytest

from private_traces.llm import lines


def distance_one(a, b):
    if a == b or abs(len(a) - len(b)) > 1:
        return False
    if len(a) > len(b):
        a, b = b, a
    p = next((i for i, (x, y) in enumerate(zip(a, b)) if x != y), len(a))
    return a[p + 1 :] == b[p + 1 :] if len(a) == len(b) else a[p:] == b[p + 1 :]


def plain(rows, least=16):
    first = {}
    for doc, text in sorted((r for r in rows if r[1] is not None), key=lambda r: (r[0] is not None, r[0] or 0)):
        for n, raw in enumerate(text.split("\n")):
            line = raw.strip(" \t\n\x0b\x0c\r")
            if line and line not in first:
                first[line] = ((doc is not None, doc or 0), n)
    gone = {a for a in first for b in first if min(len(a), len(b)) >= least and first[b] < first[a] and distance_one(a, b)}
    out = {}
    for doc, text in rows:
        if text is None:
            out[doc] = None
            continue
        keep = []
        for n, raw in enumerate(text.split("\n")):
            line = raw.strip(" \t\n\x0b\x0c\r")
            if not line or (line not in gone and first[line] == ((doc is not None, doc or 0), n)):
                keep.append(raw)
        out[doc] = "\n".join(keep)
    return out


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_planted_edits(spark, seed):
    r = random.Random(seed)
    base = ["".join(r.choice("aab é") for _ in range(r.randint(14, 60))) for _ in range(12)]

    def edit(s):
        p = r.randrange(len(s))
        return {0: s[:p] + r.choice("abxé") + s[p + 1 :], 1: s[:p] + r.choice("abxé") + s[p:], 2: s[:p] + s[p + 1 :], 3: s}[r.randrange(4)]

    rows = [(i, "\n".join(edit(edit(r.choice(base))) if r.random() < 0.3 else edit(r.choice(base)) for _ in range(r.randint(0, 8)))) for i in range(60)] + [(100, None), (101, ""), (102, "\n\n x \n"), (103, " x"), (None, "null id line, quite long")]
    got = {x.doc_id: x.text for x in lines.dedup(spark.createDataFrame(rows, "doc_id long, text string").repartition(4)).collect()}
    assert got == plain(rows)


def test_substitution_next_to_a_run(spark):
    rows = [(1, "xaab" * 6 + "q"), (2, "xaab" * 5 + "xacb" + "q"), (3, "aaaaaaaaaaaaaaaaaaaaaa"), (4, "aaaaaaaaaaaaaaaaaaaaa"), (5, "aaaaaaaaaabaaaaaaaaaaa")]
    got = {x.doc_id: x.text for x in lines.dedup(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == plain(rows) and got[2] == "" and got[4] == "" and got[5] == ""


def test_repeats_clashing_names_and_empty_tables(spark):
    t = "one long line that repeats itself\nanother line\n}\n}"
    df = spark.createDataFrame([(1, t, "a", 5), (1, t, "b", 6), (2, t, "c", 7), (1, "another text\none long line that repeats itself", "d", 8)], "doc_id long, text string, n_lines string, kept int")
    got = lines.dedup(df).collect()
    assert len(got) == 4 and {c for r in got for c in r.asDict()} == {"doc_id", "text", "n_lines", "n_removed", "kept"}
    by = {r.kept: r for r in got}
    assert by[5].text == by[6].text and by[5].text.startswith("one long") and by[7].text == "" and by[7].n_removed == 4
    assert lines.dedup(df.limit(0)).count() == 0
