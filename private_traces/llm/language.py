"""Language identification: multinomial naive Bayes over hashed character n-grams.

Training counts are summed by Spark from a stratified sample of at most about ``per_language`` documents of
each language (a documented bound; scoring covers every whole text), drawn by document, so that copies of one
text are drawn apart. The log-probability matrix
(buckets x languages) is broadcast; scoring is batched numpy over code points.

Defined results: a null text, or one without a letter, is ``und`` with score 0; rows are never joined, so
repeated ids and further columns pass through; without any labelled row everything is ``und``.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import held_out, pieces

CHUNK = 1_000_000
ORDERS = (1, 2, 3)
UNKNOWN = "und"


@lru_cache(maxsize=1)
def _letters() -> np.ndarray:
    """Lower-case code point of each letter; other characters become a space."""
    table = np.full(0x110000, 32, np.uint32)
    for i in range(len(table)):
        c = chr(i)
        if c.isalpha():
            table[i] = ord(c.lower()[0])
    return table


def grams(texts: list[str], bits: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bucket of every n-gram (one row per order), where each text starts, and which texts have a letter."""
    joined = "  ".join(["", *texts, ""])  # two spaces between texts: no n-gram spans two of them
    points = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)
    low = _letters()[points]
    lengths = np.array([len(t) + 2 for t in texts], np.int64)
    starts = np.concatenate([[0], np.cumsum(lengths)[:-1]])
    total = int(lengths.sum())
    found = np.empty((len(ORDERS), total), np.uint32)
    mixed = np.zeros(len(low), np.uint32)
    for n in ORDERS:
        mixed = mixed * np.uint32(0x01000193)
        mixed[: len(low) - n + 1] += low[n - 1 :] + np.uint32(1)
        found[n - 1] = ((mixed[:total] ^ np.uint32(n)) * np.uint32(0x9E3779B1)) >> np.uint32(32 - bits)
    lettered = np.add.reduceat((low[:total] != 32).astype(np.int64), starts) > 0
    return found, starts, lettered


def _count(batches, bits: int):
    for batch, texts in pieces(batches, "text", CHUNK):
        langs = np.array(batch.column("lang").to_pylist(), dtype=object)
        for lang in sorted(set(langs)):
            own = [t for t, x in zip(texts, langs) if x == lang]
            n = np.bincount(grams(own, bits)[0].ravel(), minlength=1 << bits)
            at = np.flatnonzero(n)
            yield pa.RecordBatch.from_pydict({"lang": [lang] * len(at), "bucket": at.astype(np.int32), "n": n[at].astype(np.int64)})


def fit(labelled: DataFrame, per_language: int = 4_000, bits: int = 15) -> tuple[list[str], np.ndarray]:
    """Languages and the matrix of log-probabilities, from ``labelled(doc_id, text, lang)`` with at most about
    ``per_language`` rows of each language (all rows where there are fewer)."""
    labelled = labelled.where("text is not null and lang is not null")
    sizes = {r.lang: r["count"] for r in labelled.groupBy("lang").count().collect()}
    if not sizes:
        return [], np.zeros((1 << bits, 0), np.float32)
    rates = F.create_map(*[F.lit(x) for k, n in sizes.items() for x in (k, min(1.0, per_language / n))])
    draw = F.pmod(F.xxhash64("doc_id", "text"), F.lit(1 << 20)) / (1 << 20)
    sample = labelled.where(draw < rates[F.col("lang")]).select("text", "lang")
    summed = (
        sample.mapInArrow(lambda b: _count(b, bits), "lang string, bucket int, n long")
        .groupBy("lang", "bucket").agg(F.sum("n").alias("n")).toPandas()
    )
    names = sorted(sizes)
    counts = np.full((1 << bits, len(names)), 0.5)
    counts[summed["bucket"].to_numpy(), [names.index(x) for x in summed["lang"]]] += summed["n"].to_numpy()
    return names, np.log(counts / counts.sum(axis=0)).astype(np.float32)


def _score(batches, model, bits: int):
    names, logs = model.value
    for batch, texts in pieces(batches, "text", CHUNK):
        pred, score = [UNKNOWN] * len(texts), np.zeros(len(texts))
        if names:
            found, starts, lettered = grams(texts, bits)
            sums = np.zeros((len(texts), len(names)))
            for row in found:
                sums += np.add.reduceat(logs[row], starts, axis=0, dtype=np.float64)
            best = sums.argmax(axis=1)
            chance = 1 / np.exp(sums - sums.max(axis=1, keepdims=True)).sum(axis=1)
            pred = [names[b] if ok else UNKNOWN for b, ok in zip(best, lettered)]
            score = np.where(lettered, chance, 0.0)
        columns = {n: batch.column(n) for n in batch.schema.names if n != "text"}
        yield pa.RecordBatch.from_pydict(columns | {"lang_pred": pa.array(pred, pa.string()), "score": pa.array(score, pa.float64())})


def identify(docs: DataFrame, labelled: DataFrame, per_language: int = 4_000, bits: int = 15) -> DataFrame:
    """``doc_id, held_out, lang_pred, score`` of every row of ``docs``."""
    model = docs.sparkSession.sparkContext.broadcast(fit(labelled, per_language, bits))
    given = docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "text")
    return given.mapInArrow(lambda b: _score(b, model, bits), "doc_id long, held_out boolean, lang_pred string, score double")


def learnable(docs: DataFrame) -> DataFrame:
    """The rows a language model may learn from: a language is given and the row is not held out."""
    return docs.where(F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
