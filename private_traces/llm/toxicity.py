"""Toxicity: nearest labelled examples by exact TF-IDF cosine over block-max inverted indexes.

Terms are words and their beginnings of four to eight letters. From at most about ``most_examples`` labelled rows
(a documented bound) the ``most_terms`` terms that tell the labels apart best by chi-squared are kept; their
document frequencies are counted over all whole texts of ``docs``. Each example becomes a normalised TF-IDF
vector; examples are laid out by their strongest term in blocks of ``BLOCK``, and each block keeps the largest
weight of every term. A query bounds each block's best cosine by those maxima and opens blocks in falling order
of the bound until no bound can reach its k-th neighbour, so the k neighbours are exact (ties: smaller id).

Votes are weighted by cosine; the raw share is mapped to a probability by a monotone fit over the examples
themselves, each scored without itself. ``evidence`` names the nearest examples.

Defined results: null and empty texts, and texts without any kept term, get the smoothed rate of the examples
without one; without labelled rows every score is 0. Rows are never joined: repeated ids and further columns
pass through. Null labels and held-out rows are never learned from; of rows repeated for one id the larger counts.
"""

from __future__ import annotations

import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drawn_labels, held_out, pieces, widened

BLOCK = 64
CHUNK = 2_000_000
NEIGHBOURS = 15
SHOWN = 3
CUT = 0.3
LEAST_CHI = 30.0  # a chance term among a million stays below this
_words = re.compile(r"[^\W_]+").findall


def terms_of(word: str) -> list[str]:
    """The word and, with a star, its beginnings of four to eight letters."""
    return [word, *(f"{word[:n]}*" for n in range(4, min(9, len(word))))]


def _tally(batches):
    seen, toxic = Counter(), Counter()

    def flush():
        names = list(seen)
        found = pa.RecordBatch.from_pydict({"term": names, "n": pa.array([seen[t] for t in names], pa.int64()), "p": pa.array([toxic[t] for t in names], pa.int64())})
        seen.clear(), toxic.clear()
        return found

    for batch, texts in pieces(batches, "text", CHUNK):
        for text, y in zip(texts, batch.column("toxic").to_pylist()):
            own = {t for w in set(_words(text.lower())) for t in terms_of(w)}
            seen.update(own)
            if y:
                toxic.update(own)
            if len(seen) > 200_000:
                yield flush()
    if seen:
        yield flush()


def choose_terms(examples: DataFrame, most_terms: int, least: int = 3) -> list[str]:
    """The terms commoner under label 1 in ``examples(text, toxic)``, by chi-squared, ties by name."""
    total = examples.agg(F.count("*").alias("n"), F.sum("toxic").alias("p")).first()
    if not total.n or not total.p or total.p == total.n:
        return []
    n, p = float(total.n), float(total.p)
    each = examples.select("text", "toxic").mapInArrow(_tally, "term string, n long, p long").groupBy("term").agg(F.sum("n").alias("n"), F.sum("p").alias("p"))
    a, b = F.col("p"), F.col("n") - F.col("p")
    chi = n * F.pow(a * (n - p - b) - b * (p - a), 2) / (F.col("n") * (n - F.col("n")) * p * (n - p))
    best = each.where((F.col("n") >= least) & (F.col("n") < n)).select("term", "n", "p", chi.alias("chi")).where((F.col("chi") >= LEAST_CHI) & (F.col("p") * total.n > F.col("n") * total.p)).orderBy(F.desc("chi"), "term").limit(most_terms)
    return [r.term for r in best.collect()]


class Features:
    """Counts of the kept terms of a text."""

    def __init__(self, terms: list[str]):
        self.at = {t: i for i, t in enumerate(terms)}
        self.memo: dict[str, list[int]] = {}

    def counts(self, text: str) -> dict[int, int]:
        found: dict[int, int] = {}
        if len(self.memo) > 100_000:
            self.memo.clear()
        memo, at = self.memo, self.at
        for w, n in Counter(_words(text.lower())).items():
            own = memo.get(w)
            if own is None:
                own = memo[w] = [at[t] for t in terms_of(w) if t in at]
            for i in own:
                found[i] = found.get(i, 0) + n
        return found


def _frequencies(batches, terms: list[str]):
    features, n = Features(terms), np.zeros(len(terms) + 1, np.int64)
    for _, texts in pieces(batches, "text", CHUNK):
        n[-1] += len(texts)
        for t in texts:
            n[list(features.counts(t))] += 1
    yield pa.RecordBatch.from_pydict({"i": pa.array(range(len(n)), pa.int32()), "n": pa.array(n)})


def weigh(features: Features, idf: np.ndarray, texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Normalised TF-IDF rows as (row, term, weight)."""
    row, col, val = [], [], []
    for r, t in enumerate(texts):
        c = features.counts(t)
        row += [r] * len(c)
        col += c.keys()
        val += c.values()
    row, col = np.array(row, np.int64), np.array(col, np.int64)
    w = (1 + np.log(np.array(val, float))) * idf[col] if len(col) else np.zeros(0)
    norm = np.sqrt(np.bincount(row, w * w, minlength=len(texts)))
    return row, col, w / norm[row] if len(row) else w


class BlockMax:
    """An inverted index of sparse unit vectors in blocks; each block has the largest weight of every term."""

    def __init__(self, row, col, val, ids: np.ndarray, labels: np.ndarray, width: int):
        self.width = width
        some = np.unique(row)
        top = np.zeros(len(ids), np.int64)
        order = np.lexsort((val, row))
        if len(order):
            ends = np.flatnonzero(np.r_[row[order][1:] != row[order][:-1], True])
            top[row[order][ends]] = col[order][ends]
        laid = some[np.lexsort((ids[some], top[some]))]
        place = np.full(len(ids), -1)
        place[laid] = np.arange(len(laid))
        self.ids, self.labels = ids[laid], labels[laid]
        n = -(-len(laid) // BLOCK)
        self.most = np.zeros((n, width), np.float32)
        self.postings = []
        at = place[row]
        for b in range(n):
            mine = (at >= b * BLOCK) & (at < (b + 1) * BLOCK)
            o = np.argsort(col[mine], kind="stable")
            c, d, w = col[mine][o], at[mine][o] - b * BLOCK, val[mine][o]
            np.maximum.at(self.most[b], c, w.astype(np.float32))
            self.postings.append((c.astype(np.int32), d.astype(np.int16), w))
        self.most *= np.float32(1.000001)  # rounding never lowers a bound

    def search(self, row, col, val, n: int, k: int, exclude: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Position and cosine of the k nearest of each of n queries (-1 and 0 where there are fewer); ties by id."""
        best_at, best = np.full((n, k), -1), np.zeros((n, k))
        if not len(row) or not len(self.most):
            return best_at, best
        q = np.zeros((n, self.width), np.float32)
        q[row, col] = val
        exact = np.zeros((n, self.width))
        exact[row, col] = val
        bound = q @ self.most.T
        order = np.argsort(-bound, axis=1, kind="stable")
        falling = np.take_along_axis(bound, order, axis=1)
        live = np.flatnonzero(falling[:, 0] > 0)
        opened = 0
        while len(live) and opened < order.shape[1]:
            block = order[live, opened]
            for b in np.unique(block):
                who = live[block == b]
                c, d, w = self.postings[b]
                size = min(BLOCK, len(self.ids) - b * BLOCK)
                dense = np.zeros((self.width, size))
                dense[c, d] = w
                used = np.unique(c)
                cos = exact[np.ix_(who, used)] @ dense[used]
                at = np.broadcast_to(np.arange(b * BLOCK, b * BLOCK + size), cos.shape)
                if exclude is not None:
                    cos = np.where(at == exclude[who][:, None], 0.0, cos)
                both, where = np.concatenate([best[who], cos], axis=1), np.concatenate([best_at[who], at], axis=1)
                both = np.round(both, 12)
                where = np.where(both > 0, where, -1)
                rank = np.lexsort((np.where(where >= 0, self.ids[where], np.iinfo(np.int64).max), -both), axis=1)[:, :k]
                best[who], best_at[who] = np.take_along_axis(both, rank, axis=1), np.take_along_axis(where, rank, axis=1)
            opened += 1
            if opened < order.shape[1]:
                ahead = falling[live, opened]
                live = live[(ahead > 0) & (ahead * 1.000001 + 1e-9 >= best[live, k - 1])]
        return best_at, best


def monotone(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pooled adjacent violators: knots and levels of the non-decreasing least-squares fit."""
    xs, inverse = np.unique(np.round(x, 6), return_inverse=True)
    n = np.bincount(inverse).astype(float)
    level = np.bincount(inverse, y) / n
    pools: list[list[float]] = []
    for i, (m, v) in enumerate(zip(n, level)):
        pools.append([m, v, i, i])
        while len(pools) > 1 and pools[-2][1] >= pools[-1][1]:
            m2, v2, _, last = pools.pop()
            m1, v1, first, _ = pools.pop()
            pools.append([m1 + m2, (m1 * v1 + m2 * v2) / (m1 + m2), first, last])
    fit = np.concatenate([[v] * int(b - a + 1) for _, v, a, b in pools])
    return xs, fit


class Model:
    """Kept terms, their IDF, the index, and the map from a raw vote to a probability."""

    def __init__(self, terms: list[str], idf: np.ndarray, ids, texts: list[str], labels, k: int = NEIGHBOURS):
        self.terms, self.idf, self.k = terms, idf, k
        row, col, val = weigh(Features(terms), idf, texts)
        self.index = BlockMax(row, col, val, ids, labels, max(1, len(terms)))
        self.rate = float(labels.mean()) if len(labels) else 0.0
        bare = np.setdiff1d(np.arange(len(ids)), row)
        self.bare = float((labels[bare].sum() + self.rate) / (len(bare) + 1)) if len(labels) else 0.0
        self.knots, self.levels = np.array([0.0, 1.0]), np.array([0.0, 1.0])
        have = np.unique(row)
        if len(have):
            place = {i: p for p, i in enumerate(self.index.ids.tolist())}
            alone = np.array([place[i] for i in ids.tolist()] if len(have) == len(ids) else [place.get(i, -1) for i in ids.tolist()])
            raw = np.concatenate([self.raw(*self._part(row, col, val, a, min(a + 512, len(ids))), exclude=alone[a : a + 512])[0] for a in range(0, len(ids), 512)])
            keep = np.isin(np.arange(len(ids)), have)
            self.knots, self.levels = monotone(raw[keep], labels[keep].astype(float))

    @staticmethod
    def _part(row, col, val, a: int, b: int):
        mine = (row >= a) & (row < b)
        return row[mine] - a, col[mine], val[mine], b - a

    def raw(self, row, col, val, n: int, exclude=None):
        """Cosine-weighted share of label 1 among the neighbours, drawn slightly to the overall rate."""
        at, cos = self.index.search(row, col, val, n, self.k, exclude)
        y = self.index.labels[at] * (at >= 0) if len(self.index.ids) else np.zeros(cos.shape)
        return ((cos * y).sum(axis=1) + 0.5 * self.rate) / (cos.sum(axis=1) + 0.5), at, cos

    def score(self, features: Features, texts: list[str]):
        row, col, val = weigh(features, self.idf, texts)
        raw, at, cos = self.raw(row, col, val, len(texts))
        scored = np.interp(raw, self.knots, self.levels)
        none = np.bincount(row, minlength=len(texts)) == 0
        return np.clip(np.where(none, self.bare, scored), 0.0, 1.0), at, cos


def fit(docs: DataFrame, labels: DataFrame, most_examples: int = 12_000, most_terms: int = 512) -> Model:
    """The model of ``docs(doc_id, text)`` and ``labels(doc_id, toxic)``. The drawn labels number at most about
    ``most_examples``, which bounds what is broadcast and collected here."""
    drawn = F.broadcast(drawn_labels(labels, "toxic", most_examples))
    examples = docs.select("doc_id", "text").join(drawn, "doc_id")
    terms = choose_terms(examples, most_terms)
    if not terms:
        rows = examples.agg(F.count("*").alias("n"), F.sum("toxic").alias("p")).first()
        model = Model([], np.zeros(0), np.zeros(0, np.int64), [], np.zeros(0, np.int64))
        model.rate = model.bare = (rows.p or 0) / rows.n if rows.n else 0.0
        return model
    counted = docs.select("text").mapInArrow(lambda b: _frequencies(b, terms), "i int, n long").groupBy("i").agg(F.sum("n").alias("n")).collect()
    n = np.zeros(len(terms) + 1)
    for r in counted:
        n[r.i] = r.n
    idf = np.log((1 + n[-1]) / (1 + n[:-1])) + 1
    features = examples.mapInArrow(lambda b: _sparse(b, terms), "doc_id long, toxic int, t array<string>").toPandas().sort_values("doc_id", kind="stable")
    features = features.drop_duplicates("doc_id")
    return Model(terms, idf, features["doc_id"].to_numpy(np.int64), [" ".join(t) for t in features["t"]], features["toxic"].to_numpy(np.int64))


def _sparse(batches, terms: list[str]):
    """The words of each example that carry a kept term: all that its vector needs."""
    kept = set(terms)
    for batch, texts in pieces(batches, "text", CHUNK):
        words = [[w for w in _words(t.lower()) if not kept.isdisjoint(terms_of(w))] for t in texts]
        yield pa.RecordBatch.from_pydict({"doc_id": batch.column("doc_id"), "toxic": batch.column("toxic"), "t": pa.array(words, pa.list_(pa.string()))})


def _scored(batches, shared, columns: list[str]):
    model = shared.value
    features = Features(model.terms)
    kind = pa.list_(pa.struct([("doc_id", pa.int64()), ("cosine", pa.float64()), ("toxic", pa.int32())]))
    for batch, texts in pieces(batches, "text", CHUNK):
        parts = [model.score(features, texts[a : a + 1024]) for a in range(0, len(texts), 1024)]
        score = np.concatenate([p[0] for p in parts])
        shown = [
            [{"doc_id": int(model.index.ids[i]), "cosine": float(c), "toxic": int(model.index.labels[i])} for i, c in zip(at[:SHOWN], cos[:SHOWN]) if i >= 0]
            for p in parts for at, cos in zip(p[1], p[2])
        ]
        yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in columns), pa.array(score), pa.array(shown, kind)], [*columns, "score", "evidence"])


def score(docs: DataFrame, model: Model) -> DataFrame:
    """``docs`` with ``score`` and ``evidence`` in place of any columns of those names."""
    kept = docs.drop("score", "evidence")
    names = kept.columns
    shared = docs.sparkSession.sparkContext.broadcast(model)
    return kept.mapInArrow(lambda b: _scored(b, shared, names), widened(kept, "score double, evidence array<struct<doc_id:bigint,cosine:double,toxic:int>>"))


def classify(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """``doc_id, held_out, score, predicted, evidence`` of every row."""
    scored = _without_text(docs.select("doc_id", "text"), fit(docs, labels))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= CUT).cast("int").alias("predicted"), F.col("evidence.doc_id").alias("evidence"))


def _without_text(docs: DataFrame, model: Model) -> DataFrame:
    shared = docs.sparkSession.sparkContext.broadcast(model)
    return docs.mapInArrow(lambda b: _scored(b, shared, ["doc_id"]), "doc_id long, score double, evidence array<struct<doc_id:bigint,cosine:double,toxic:int>>")
