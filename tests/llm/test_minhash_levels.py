"""Large nodes, last levels, null and repeated ids, against brute force."""

import random

from private_traces.llm import minhash

from .test_learned import plain_classes


def family(seed: int, members: int, words: int) -> list[str]:
    r = random.Random(seed)
    base = [f"w{r.randrange(3000)}" for _ in range(words)]
    out = []
    for _ in range(members):
        t = list(base)
        for _ in range(r.choice((0, 1, 2, 4, 6, 8, 10))):
            t[r.randrange(len(t))] = f"n{r.randrange(10**6)}"
        out.append(" ".join(t))
    return out


def test_large_nodes_and_the_last_level(spark):
    """Nodes over 40 sets are dealt in parts and branch; at level 3 all that are left meet in blocks."""
    rows = list(enumerate(family(3, 260, 110) + family(4, 60, 100)))
    want = plain_classes(rows, 2, 80)
    got = {x.doc_id: (x.n_shingles, x.component_id) for x in minhash.classes(spark.createDataFrame(rows, "doc_id long, text string"), limit=40, deepest=3).collect()}
    assert got == want and len({c for _, c in want.values()}) > 2


def test_null_ids_take_part_but_name_no_class(spark):
    texts = ["a b c d e f g h i j", "a b c d e f g h i j", "a b c d e f g h i j k", "x y z", "x y z", "lone text here"]
    ids = [None, 7, None, None, None, 9]
    df = spark.createDataFrame(list(zip(ids, texts)), "doc_id long, text string")
    got = sorted(((r.doc_id, r.n_shingles, r.component_id) for r in minhash.classes(df).collect()), key=str)
    assert got == sorted([(None, 9, 7), (7, 9, 7), (None, 10, 7), (None, 2, None), (None, 2, None), (9, 2, 9)], key=str)


def test_repeated_ids_keep_the_set_of_each_row(spark):
    df = spark.createDataFrame([(5, "a b c d"), (5, "p q r s"), (6, "a b c d"), (4, "p q r s"), (8, "one two three")], "doc_id long, text string")
    got = sorted((r.doc_id, r.component_id) for r in minhash.classes(df).collect())
    assert got == [(4, 4), (5, 4), (5, 5), (6, 5), (8, 8)]


def test_hashed_sets_are_the_sets(spark):
    """Word hashes are made of blocks of eight bytes: every length around a block, other white space, other letters."""
    r = random.Random(5)
    texts = ["", " ", "one", "\u00a0 x\u2003y  A\u00c4\t\x0bB\x1cC\r\n", *(" ".join("".join(r.choice("ab\u00e9\u6c34\U0001F642") for _ in range(r.randrange(1, 30))) for _ in range(r.randrange(40))) for _ in range(200))]
    texts += ["q" * 100_000 + " " + "q" * 99_999, "abcdefgh", "abcdefgh\0", "abcdefg", "abcdefgh abcdefgh"]
    for width in (1, 2, 5):
        plain, names = [minhash.shingles(t, width) for t in texts], {}
        for s, h in zip(plain, minhash.hashed_sets(texts, width)):
            assert len(s) == len(h) and (h[1:] > h[:-1]).all()
            names.setdefault(frozenset(s), h.tobytes())
            assert names[frozenset(s)] == h.tobytes()
        assert len({h for h in names.values()}) == len(names)


def test_drop_later_tells_rows_of_one_id_apart(spark):
    rows = [(5, "a b c d e f g", 1), (3, "a b c d e f g", 2), (5, "only here is this text", 3), (None, "a b c d e f g", 4), (None, "p q r s t u", 5), (None, None, 6), (6, "", 7)]
    df = spark.createDataFrame(rows, "doc_id long, text string, gone_key int")
    kept = minhash.drop_later(df)
    assert kept.columns == df.columns and sorted(r.gone_key for r in kept.collect()) == [2, 3, 5, 6, 7]
    assert minhash.drop_later(df.limit(0)).count() == 0
