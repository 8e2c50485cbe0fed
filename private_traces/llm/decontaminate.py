"""Benchmark decontamination: latent semantic retrieval, then longest-common-subsequence and answer checks.

Words are lower-cased runs of letters and digits. (1) Passage frequencies of the benchmark's words are counted over
all passages of all documents; those of more than ``COMMON`` of them are left to step 4. (2) The TF-IDF matrix of the benchmark's passages has its leading right singular
vectors found by a randomised SVD: every pass is a distributed product A'(A X) over the passages, summed from one
partial matrix per task. (3) Each window of ``SPAN`` words of every whole document is projected (as a sum of blocks of
``STRIDE`` words) and compared with every item by cosine in that space, and by the share of the item it
carries; no cap on candidates. An item of more than ``PART`` words is cut into parts that are retrieved apart and judged
together, so a window can carry its share of a part however long the item is. (4) Neighbouring candidate windows of one item form a region, which is checked by the longest common
subsequence with the item. A region that holds ``COPY`` of the item's words in order is a copy; one that holds
``PARAPHRASE`` of them must also hold most of the item's ``answer``: its rarest words.

A benchmark above ``BLOCK`` items is searched block by block, which bounds what is broadcast and collected.

Defined results: null and empty texts are clean; items without words match nothing; of a repeated item id each row is
an item; an empty benchmark leaves all documents clean. Rows are never joined: repeated ids and further columns pass.
"""

from __future__ import annotations

import re
from collections import Counter
from itertools import chain, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import aside, pieces, widened, written

CHUNK = 2_000_000
BLOCK = 2_000
SPAN = 36
STRIDE = 12
RANK = 96
PART = 60  # words of an item that are retrieved as one
PASSAGE = 128
COMMON = 0.1
PRIOR = 100  # passages without the word that every share counts besides
LEAST_COSINE = 0.45
LEAST_SHARE = 0.2
COPY = 0.7
PARAPHRASE = 0.5
ANSWER_WORDS = 5
_words = re.compile(r"[^\W_]+").findall


def words_of(text: str) -> list[str]:
    return _words(text.lower())


def common_subsequence(item: list[str], region: list[str]) -> int:
    """Length of the longest common subsequence, one word of the region at a time over bits of the item."""
    masks: dict[str, int] = {}
    for i, w in enumerate(item):
        masks[w] = masks.get(w, 0) | 1 << i
    full = (1 << len(item)) - 1
    free = full
    for w in region:
        m = masks.get(w)
        if m:
            u = free & m
            free = ((free + u) | (free - u)) & full
    return len(item) - free.bit_count()


def _frequencies(batches, vocabulary: frozenset):
    seen, passages = Counter(), 0
    for _, texts in pieces(batches, "text", CHUNK):
        for text in texts:
            ws = words_of(text)
            for a in range(0, len(ws), PASSAGE):
                passages += 1
                seen.update(vocabulary.intersection(ws[a : a + PASSAGE]))
    names = list(seen)
    yield pa.RecordBatch.from_pydict({"word": pa.array([*names, None], pa.string()), "n": pa.array([*(seen[w] for w in names), passages], pa.int64())})


class Space:
    """The words of a block of items, their IDF, the projection, and the parts of the items in it."""

    def __init__(self, items: list[tuple[int, str]], counts: dict):
        self.ids = [i for i, _ in items]
        self.texts = [words_of(t or "") for _, t in items]
        cuts = [np.linspace(0, len(t), max(1, -(-len(t) // PART)) + 1).astype(int).tolist() for t in self.texts]
        self.parts = [t[a:b] for t, c in zip(self.texts, cuts) for a, b in zip(c, c[1:])]
        self.owner = np.array([i for i, c in enumerate(cuts) for _ in c[1:]], np.int64)
        total = counts.get(None, 0)
        rare = lambda w: (counts.get(w, 0), w)
        self.answers = [set(sorted(set(t), key=rare)[:ANSWER_WORDS]) for t in self.texts]
        # words of more than COMMON of the passages tell nothing, but where they are all an item has
        telling = {w for t in self.texts for w in t if counts.get(w, 0) <= COMMON * (total + PRIOR)}.union(*self.answers)
        self.at = {w: k for k, w in enumerate(sorted(telling))}
        n = np.array([counts.get(w, 0) for w in self.at], float)
        self.idf = np.log((1 + total) / (1 + n)) + 0.1

    def rows(self, texts: list[list[str]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """TF-IDF entries (row, word, weight) of texts, each of length one."""
        row = np.array([r for r, t in enumerate(texts) for w in t if w in self.at], np.int64)
        col = np.array([self.at[w] for t in texts for w in t if w in self.at], np.int64)
        pair, n = np.unique(row * max(1, len(self.at)) + col, return_counts=True)
        row, col = pair // max(1, len(self.at)), pair % max(1, len(self.at))
        w = n * self.idf[col]
        norm = np.sqrt(np.bincount(row, w * w, minlength=len(texts)))
        return row, col, w / norm[row]

    def project(self, basis: np.ndarray) -> None:
        """Fix the basis (words x rank); the projected words and parts follow."""
        self.word = (self.idf[:, None] * basis).astype(np.float32)
        item = np.zeros((len(self.parts), basis.shape[1]), np.float32)
        for i, t in enumerate(self.parts):
            if t:
                item[i] = self.word[[self.at[w] for w in t if w in self.at]].sum(axis=0)
        size = np.linalg.norm(item, axis=1, keepdims=True)
        self.item = item / np.where(size > 0, size, 1)
        self.size = np.where(size > 0, size, np.inf).ravel()


def _product(batches, shared, basis):
    """A'(A X) of the passages of this task."""
    space, x = shared.value, basis.value
    total = np.zeros_like(x)
    for batch in batches:
        texts = [words_of(t or "") for t in batch.column("text").to_pylist()]
        row, col, w = space.rows(texts)
        if len(row):
            y = np.zeros((len(texts), x.shape[1]))
            np.add.at(y, row, w[:, None] * x[col])
            np.add.at(total, col, w[:, None] * y[row])
    yield pa.RecordBatch.from_pydict({"part": pa.array([total.tobytes()], pa.binary())})


def randomised_svd(passages: DataFrame, space: Space, rank: int = RANK, rounds: int = 2, seed: int = 5) -> np.ndarray:
    """Leading right singular vectors of the TF-IDF matrix of ``passages(text)``; at most 8 partial matrices at a time
    reach the driver."""
    spark = passages.sparkSession
    size = len(space.at)
    width = min(size, rank + 10)
    shared = spark.sparkContext.broadcast(space)
    rows = written(passages.select("text").repartition(8), "passages").coalesce(8)

    def times(x: np.ndarray) -> np.ndarray:
        basis = spark.sparkContext.broadcast(x)
        parts = rows.mapInArrow(lambda b: _product(b, shared, basis), "part binary").collect()
        return sum((np.frombuffer(p.part).reshape(x.shape) for p in parts), np.zeros_like(x))

    x = np.linalg.qr(times(np.random.default_rng(seed).normal(size=(size, width))))[0]
    for _ in range(rounds):
        x = np.linalg.qr(times(x))[0]
    small = x.T @ times(x)
    value, vector = np.linalg.eigh((small + small.T) / 2)
    lead = np.argsort(-value)[: min(rank, width)]
    lead = lead[value[lead] > 1e-9 * max(value.max(), 1e-30)]
    return x @ vector[:, lead]


def candidates(space: Space, texts: list[list[str]]):
    """(text, item, first word, last word, cosine) of every region of neighbouring candidate windows."""
    flat = np.fromiter(map(space.at.get, chain.from_iterable(texts), repeat(-1)), np.int32, sum(map(len, texts)))
    bounds = np.cumsum([0, *map(len, texts)])
    if not len(flat) or not len(space.item) or not space.word.shape[1]:
        return
    known = np.flatnonzero(flat >= 0)
    if not len(known):
        return
    # sums per block of STRIDE words; a window is SPAN / STRIDE blocks in a row
    blocks = -(-np.diff(bounds) // STRIDE)
    base = np.cumsum([0, *blocks])
    text = np.searchsorted(bounds, known, side="right") - 1
    block = base[text] + (known - bounds[text]) // STRIDE
    starts = np.flatnonzero(np.r_[True, block[1:] != block[:-1]])
    ids, sums = block[starts], np.add.reduceat(space.word[flat[known]], starts, axis=0)
    wide = SPAN // STRIDE
    owner = np.searchsorted(base, ids, side="right") - 1
    begin = np.concatenate([np.clip(ids - k, base[owner], np.maximum(base[owner], base[owner + 1] - wide)) for k in range(wide)])
    begin = np.unique(begin)
    text = np.searchsorted(base, begin, side="right") - 1
    first = bounds[text] + (begin - base[text]) * STRIDE
    last = np.minimum(first + SPAN, bounds[1:][text])
    for a in range(0, len(first), 20_000):
        f, e = first[a : a + 20_000], last[a : a + 20_000]
        window = np.zeros((len(f), sums.shape[1]), np.float32)
        for k in range(wide):
            want = begin[a : a + 20_000] + k
            at = np.minimum(np.searchsorted(ids, want), len(ids) - 1)
            here = (ids[at] == want) & (want < base[text[a : a + 20_000] + 1])
            window[here] += sums[at[here]]
        size = np.linalg.norm(window, axis=1)
        along = window @ space.item.T
        w, item = np.nonzero((along >= LEAST_SHARE * space.size) & (along >= LEAST_COSINE * np.maximum(size, 1e-6)[:, None]))
        c = along[w, item] / np.maximum(size, 1e-6)[w]
        t, item = text[a : a + 20_000][w], space.owner[item]
        order = np.lexsort((f[w], item, t))
        t, item, lo, hi, c = t[order], item[order], f[w][order], e[w][order], c[order]
        cut = np.flatnonzero(np.r_[True, (t[1:] != t[:-1]) | (item[1:] != item[:-1]) | (lo[1:] > hi[:-1])][: len(t)])
        for s, z in zip(cut.tolist(), np.r_[cut[1:], len(t)].tolist()):
            zero = bounds[t[s]]
            yield int(t[s]), int(item[s]), int(lo[s] - zero), int(hi[z - 1] - zero), float(c[s:z].max())


def judge(item: list[str], answer: set[str], region: list[str]) -> tuple[bool, float]:
    """Whether the region holds the item, and the share of the item's words it holds in order."""
    if not item:
        return False, 0.0
    share = common_subsequence(item, region) / len(item)
    if len(item) < 8:
        return share == 1.0 and " ".join(item) in " ".join(region), share
    if share >= COPY:
        return True, share
    return share >= PARAPHRASE and 3 * len(answer.intersection(region)) >= 2 * len(answer), share


def matches(space: Space, texts: list[str]) -> list[list[tuple[int, float, float]]]:
    """(item id, share, cosine) of the items found in each text."""
    cut = [words_of(t) for t in texts]
    found: list[dict] = [{} for _ in texts]
    for t, item, lo, hi, cosine in candidates(space, cut):
        own = space.texts[item]
        margin = max(0, len(own) - SPAN // 2)
        region = cut[t][max(0, lo - margin) : hi + margin]
        hit, share = judge(own, space.answers[item], region)
        if hit and share > found[t].get(item, (0, 0))[0]:
            found[t][item] = (share, cosine)
    return [[(space.ids[i], s, c) for i, (s, c) in sorted(f.items(), key=lambda x: (-x[1][0], space.ids[x[0]]))] for f in found]


HIT = "array<struct<item_id:bigint,share:double,cosine:double>>"


def _search(batches, shared, columns: list[str]):
    kind = pa.list_(pa.struct([("item_id", pa.int64()), ("share", pa.float64()), ("cosine", pa.float64())]))
    space = shared.value
    for batch, texts in pieces(batches, "text", CHUNK):
        hits = [[{"item_id": i, "share": s, "cosine": c} for i, s, c in f] for f in matches(space, texts)]
        yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in columns), pa.array(hits, kind)], [*columns, "leaks"])


def spaces(docs: DataFrame, benchmark: DataFrame) -> list[Space]:
    """A fitted space for each block of benchmark items."""
    items = benchmark.where("text is not null").select("item_id", "text")
    blocks = max(1, -(-items.count() // BLOCK))
    out = []
    for i in range(blocks):
        block = items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == i)
        rows = sorted((r.item_id, r.text) for r in block.collect())
        if not rows:
            continue
        vocabulary = frozenset(w for _, t in rows for w in words_of(t))
        counted = docs.select("text").mapInArrow(lambda b, v=vocabulary: _frequencies(b, v), "word string, n long").groupBy("word").agg(F.sum("n").alias("n")).collect()
        space = Space(rows, {r.word: r.n for r in counted})
        space.project(randomised_svd(block, space) if vocabulary else np.zeros((0, 0)))
        out.append(space)
    return out


def find(docs: DataFrame, benchmark: DataFrame, columns: list[str] | None = None) -> DataFrame:
    """``docs`` (or its ``columns``) with ``leaks``: item id, share of its words found in order, and cosine, in place of any
    column of that name."""
    if columns is None:
        moved, back = aside(docs.drop("leaks"), ["doc_id", "text"])
        return back(find(moved, benchmark, moved.columns), "leaks")
    kept, names = docs, columns
    found = spaces(kept, benchmark)
    if not found:
        return kept.select(*names).withColumn("leaks", F.array().cast(HIT))
    done = None
    for space in found:
        shared = docs.sparkSession.sparkContext.broadcast(space)
        given = kept if done is None else done
        carried = [*names, *(["text"] if "text" not in names and space is not found[-1] else [])]
        name = f"leaks {len(carried)} {id(space)}"
        schema = widened(given.select(*[c for c in given.columns if c in carried or c.startswith("leaks ")]), f"leaks {HIT}")
        done = given.mapInArrow(lambda b, s=shared, c=schema.names[:-1]: _search(b, s, c), schema).withColumnRenamed("leaks", name)
    parts = [c for c in done.columns if c.startswith("leaks ")]
    return done.select(*names, F.concat(*parts).alias("leaks"))


def flags(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """``doc_id, contaminated, item_ids, share`` of every row (``share``: of the best match, 0 without one)."""
    found = find(docs.select("doc_id", "text"), benchmark, ["doc_id"])
    best = F.coalesce(F.get("leaks", F.lit(0))["share"], F.lit(0.0))
    return found.select("doc_id", (F.size("leaks") > 0).alias("contaminated"), F.array_sort(F.array_distinct("leaks.item_id")).alias("item_ids"), F.round(best, 6).alias("share"))
