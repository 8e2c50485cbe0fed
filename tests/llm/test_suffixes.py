"""Passage removal against a plain window index."""

import hashlib
import random

import numpy as np
import pytest

from private_traces.llm import suffixes


def plain(rows):
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256) by remembering every window."""
    seen, out = set(), []
    for doc_id, text in rows:
        raw = (text or "").encode()
        gone = np.zeros(len(raw) + 1, bool)
        for i in range(len(raw) - suffixes.WINDOW + 1):
            w = raw[i : i + suffixes.WINDOW]
            if w in seen:
                gone[i : i + suffixes.WINDOW] = True
            seen.add(w)
        g = gone[:-1]
        spans = int((g & ~np.r_[False, g[:-1]]).sum()) if len(g) else 0
        out.append((doc_id, len(raw), int(g.sum()), spans, hashlib.sha256(bytes(b for b, x in zip(raw, g) if not x)).hexdigest()))
    return out


def got(spark, rows, parts=5):
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(parts)
    return sorted(map(tuple, suffixes.digests(df).collect()))


def test_given_documents(spark):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").orderBy("doc_id").collect()]
    assert got(spark, rows) == sorted(plain(rows))


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_planted_repeats(spark, seed):
    r = random.Random(seed)
    word = lambda: "".join(r.choice("abcdé") for _ in range(r.randint(1, 6)))
    text = lambda n: " ".join(word() for _ in range(n))
    passages = [text(n) for n in (18, 22, 24, 25, 30, 60)]
    rows = [(i, None if i == 3 else "") for i in (3, 4)]
    for i in range(10, 90):
        t = text(r.randint(0, 60))
        for _ in range(r.randint(0, 3)):
            p = r.choice(passages)
            a = r.randint(0, 20)
            t += " " + (p[a:] if r.random() < 0.5 else p) + " " + text(r.randint(0, 9))
        rows.append((i, t))
    rows += [(100, "a" * 500), (101, "ab" * 300), (102, "a" * 99), (103, rows[20][1]), (104, rows[20][1] + "x"), (105, "b" * 100), (106, "b" * 101)]
    assert got(spark, rows) == sorted(plain(rows))


def test_long_texts_cross_segments(spark, monkeypatch):
    r = random.Random(5)
    t = "".join(r.choice("abcdefgh ") for _ in range(5000))
    rows = [(1, t), (2, t[100:3000] + "zz" + t[2000:2500]), (3, t[4000:] + t[:1200])]
    monkeypatch.setattr(suffixes, "SEGMENT", 700)
    raw = [x[1].encode() for x in rows]
    whole = list(suffixes._segments(raw, [1, 2, 3]))
    assert len(whole) > 10
    assert got(spark, rows, 2) == sorted(plain(rows))


def test_repeated_and_null_ids_and_clashing_names(spark):
    t = "word " * 40 + "tail one two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen"
    rows = [(None, t), (1, t), (1, t), (1, "short")]
    out = sorted(map(tuple, suffixes.digests(spark.createDataFrame(rows, "doc_id long, text string")).collect()), key=str)
    first = plain([(None, t)])[0]
    assert sum(x[1:] == first[1:] for x in out) == 1 and len(out) == 4 and sum(x[2] == len(t) for x in out) == 2
    df = spark.createDataFrame([(1, t, 5, "x"), (2, t, 6, "y")], "doc_id long, text string, key int, removed string")
    cut = {r.doc_id: r for r in suffixes.dedup(df).collect()}
    assert cut[2].text == "" and cut[2].removed[0].end == len(t) and cut[1].text != ""
    assert suffixes.digests(df.limit(0)).count() == 0


def test_lpf_of_one_text():
    r = random.Random(2)
    for _ in range(30):
        t = bytes(r.choice(b"ab") for _ in range(r.randint(0, 40)))
        want = [max([0] + [k for q in range(p) for k in range(1, len(t) - p + 1) if t[q : q + k] == t[p : p + k]]) for p in range(len(t))]
        assert suffixes.longest_previous_factor(t).tolist() == want
