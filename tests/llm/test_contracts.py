"""Where a contract is easily missed: letters beyond the basic plane, numbers at the edge of a window, added tokens,
windows with equal hashes, columns with the names of our own."""

import random
import zlib
from collections import Counter

import numpy as np
import public_tokenizers as P
from pyspark.sql import functions as F

from private_traces.llm import language, lines, quality, secrets, suffixes, token_files
from private_traces.llm.common import aside


def plain_grams(text: str, bits: int) -> Counter:
    """Buckets of all 1- to 3-grams of letters (others as spaces) of a text between two spaces on either side."""
    padded = "  " + "".join(c.lower()[0] if c.isalpha() else " " for c in text) + "  "
    out = Counter()
    for i in range(len(padded) - 2):
        h = 0
        for n in (1, 2, 3):
            if i + n <= len(padded):
                h = (h * 0x01000193 + ord(padded[i + n - 1]) + 1) % 2**32
                out[((h ^ n) * 0x9E3779B1 % 2**32) >> (32 - bits)] += 1
    return out


def test_grams_are_those_of_a_plain_loop():
    r = random.Random(3)
    letters = "abcXYZ äÖ ß水\U00010400\U0001F642\U0001D7D8 .1"
    for _ in range(50):
        text = "".join(r.choice(letters) for _ in range(r.randrange(60)))
        found = language.grams([text], 15)[0].ravel()
        assert Counter(found.tolist()) == plain_grams(text, 15)


def test_only_letters_make_a_language(spark):
    train = spark.createDataFrame([(i, t, x) for i, (t, x) in enumerate([("the cat and the dog", "en"), ("der hund und die katze", "de")] * 20)], "doc_id long, text string, lang string")
    texts = ["\U0001F642\U0001F642 !", "\U0001D7D8\U0001D7D9", "12 -- 3", None, "", "der hund", "\U00010400\U00010401"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").withColumn("lang", F.lit(None).cast("string"))
    got = {r.doc_id: r.lang_pred for r in language.identify(docs, train).collect()}
    assert [got[i] for i in range(5)] == ["und"] * 5 and got[5] == "de" and got[6] in ("en", "de")


def test_numbers_are_read_to_their_end():
    assert secrets.spans("card" + " " * 31 + "4111111111111111") == [(35, 51, "card")]
    assert secrets.spans("card" + " " * 31 + "4111111111111111999") == []
    iban = "DE89370400440532013000"
    for gap in (0, 16, 40):
        assert secrets.spans("iban" + " " * gap + iban) == [(4 + gap, 26 + gap, "iban")]
    assert secrets.spans("iban" + "x" * (secrets.NEAR + 5) + " " + iban) == []
    assert secrets.spans("visa 1234 4111 1111 1111 1111") == [] and secrets.spans("visa: 4111 1111 1111 1111.") == [(6, 25, "card")]


def test_added_tokens_are_the_library_s(spark):
    from tokenizers import Tokenizer

    path = P.path("word_bpe_49k.json")
    tok = Tokenizer.from_file(path)
    texts = ["hello <|startoftext|> there", "a<|endoftext|>b c", "<|STARTOFTEXT|> x", "<|EndOfText|>", "plain", None, "<|endoftext|><|endoftext|>"]
    got = token_files.round_trip(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), path).collect()
    want = [np.array(tok.encode(t or "", add_special_tokens=False).ids + [1], "<u4") for t in texts]
    assert {r.doc_id: (r.n_tokens, r.ids_crc32) for r in got} == {i: (len(x), zlib.crc32(x)) for i, x in enumerate(want)}


def test_repeated_windows_are_those_of_equal_words(spark):
    r = random.Random(4)
    texts = [" ".join(r.choice("abcdefghij") for _ in range(r.randrange(200))) for _ in range(60)] + ["", None, "a a a a", "a b c a b c", "x y z"]

    def plain(text):
        w = (text or "").split()
        seen = Counter(zip(w, w[1:], w[2:]))
        return len({j for i, x in enumerate(zip(w, w[1:], w[2:])) if seen[x] > 1 for j in (i, i + 1, i + 2)})

    got = {x.doc_id: x.n_repeat_words for x in quality.base(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert got == {i: plain(t) for i, t in enumerate(texts)}


def test_windows_of_one_hash_are_compared_by_their_words(spark, monkeypatch):
    """All windows get one hash: only the words tell them apart."""
    monkeypatch.setattr(F, "xxhash64", lambda *c: F.lit(5).cast("bigint"))
    texts = ["a b c d e f g", "a b c x a b c y", "p q r s q r s t", "a a a a"]
    got = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").select("doc_id", quality.repeated_words(F.split("text", " ")).alias("n")).collect()
    assert {r.doc_id: r.n for r in got} == {0: 0, 1: 6, 2: 6, 3: 4}


def test_columns_with_names_of_our_own_pass_through(spark):
    names = ["__row", "__kept", "__lines", "__flags", "__out", "__key", "__hash", "__ranges", "kept", "row", "leaks 1", "a`b"]
    df = spark.createDataFrame([(1, "one line\none line", *[f"v{i}" for i in range(len(names))]), (None, None, *names)], ["doc_id", "text", *names])
    for done, own in ((lines.dedup(df), ["n_lines", "n_removed"]), (suffixes.dedup(df), ["removed"])):
        assert done.columns == [*df.columns, *own]
        assert sorted(str(tuple(r)[2 : 2 + len(names)]) for r in done.collect()) == sorted(str(tuple(r)[2:]) for r in df.collect())
    moved, back = aside(df, ["doc_id", "text"])
    assert not set(names) & set(moved.columns) and back(moved).columns == df.columns
