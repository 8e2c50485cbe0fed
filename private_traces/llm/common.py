"""What the training-data operators share: shared storage, column helpers and Arrow iteration."""

from __future__ import annotations

import atexit
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

WORD = r"[^\x20\x09-\x0D]+"

_OWN: dict[int, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; on a local master, one of our own where none is set."""
    where = spark.conf.get("spark.checkpoint.dir", None)
    if where:
        return where.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir: executors of a cluster share no local folder")
    key = id(spark.sparkContext)
    if key not in _OWN:
        _OWN[key] = "file://" + tempfile.mkdtemp(prefix="shared-")
    return _OWN[key]


def fresh_path(spark: SparkSession, tag: str) -> str:
    """A new folder name under the shared folder, removed when the driver ends."""
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    atexit.register(remove, spark, path)
    return path


def remove(spark: SparkSession, path: str) -> None:
    try:
        hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
        hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).delete(hadoop, True)
    except Exception:  # the gateway is gone when the session ended first
        return


def written(df: DataFrame, tag: str) -> DataFrame:
    """Cut the lineage: write to the shared folder and read back, so a lost executor costs no recomputation."""
    spark = df.sparkSession
    path = fresh_path(spark, tag)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def let(value: Column, body) -> Column:
    """Evaluate ``value`` once and use it many times inside lambdas (no re-evaluation per element)."""
    return F.transform(F.array(value), body)[0]


def held_out(doc_id: Column) -> Column:
    """True for the quarter of documents that no classifier may learn from; false for a null id."""
    return F.coalesce(F.crc32(doc_id.cast("string")) % 4 == 2, F.lit(False))


def drawn_labels(labels: DataFrame, column: str, most: int) -> DataFrame:
    """``doc_id`` and ``column`` (int; the larger of repeated rows) of at most about ``most`` labelled rows, drawn by a
    hash of the id. Rows with a null id or label and held-out rows are left out."""
    given = labels.where(F.col(column).isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max(column).cast("int").alias(column))
    n = given.count()
    return given.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) < (1 << 20) * min(1.0, most / max(1, n)))


def aside(docs: DataFrame, own: list[str]) -> tuple[DataFrame, Callable]:
    """``docs`` with all columns but ``own`` under names that no operator uses, and what gives the names back to a result that
    still has those columns, with any further columns after them."""
    names = {c: c if c in own else f"aside {i}" for i, c in enumerate(docs.columns)}
    quoted = lambda c: F.col("`" + c.replace("`", "``") + "`")
    moved = docs.select(*[quoted(c).alias(n) for c, n in names.items()])
    return moved, lambda done, *more: done.select(*[quoted(n).alias(c) for c, n in names.items()], *more)


def widened(df: DataFrame, ddl: str) -> T.StructType:
    """The schema of ``df`` with the columns of ``ddl`` after it."""
    return T.StructType([*df.schema.fields, *T.StructType.fromDDL(ddl).fields])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def give_back() -> None:
    """Return freed memory to the system, so that an idle Python worker stays small beside the next stage."""
    import ctypes
    import gc

    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        return


def pieces(batches: Iterator[pa.RecordBatch], column: str, most_chars: int) -> Iterator[tuple[pa.RecordBatch, list[str]]]:
    """Slices of the batches whose texts (null: empty) hold about ``most_chars`` characters at most, or one long text."""
    for batch in batches:
        texts = [x or "" for x in batch.column(column).to_pylist()]
        start = size = 0
        for i, text in enumerate(texts):
            if i > start and size + len(text) > most_chars:
                yield batch.slice(start, i - start), texts[start:i]
                start, size = i, 0
            size += len(text)
        if len(texts) > start:
            yield batch.slice(start), texts[start:]
    give_back()


def aligned(batches: Iterator[pa.RecordBatch], keys: list[str], rows: int = 50_000) -> Iterator[pa.Table]:
    """Tables of about ``rows`` rows from sorted batches, cut where ``keys`` change.

    A run of equal keys longer than ``rows`` is yielded whole with what is already buffered; callers keep
    such runs bounded (columns of fixed width, pre-aggregated keys).
    """
    held: list[pa.RecordBatch] = []
    count = 0
    for batch in batches:
        if not batch.num_rows:
            continue
        held.append(batch)
        count += batch.num_rows
        if count < rows:
            continue
        whole = pa.Table.from_batches(held)
        change = np.zeros(whole.num_rows - 1, bool)
        for k in keys:
            v = whole.column(k).to_numpy()
            change |= v[1:] != v[:-1]
        cut = np.flatnonzero(change)
        if not len(cut):
            continue
        at = int(cut[-1]) + 1
        yield whole.slice(0, at).combine_chunks()
        rest = whole.slice(at).combine_chunks()
        held, count = rest.to_batches(), rest.num_rows
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def runs(batches: Iterator[pa.RecordBatch], keys: list[str], rows: int, most: int) -> Iterator[tuple[pa.Table, np.ndarray]]:
    """Tables of about ``rows`` rows from sorted batches, with a flag for each run of equal keys in them. Runs are whole but for
    those over ``most`` rows, which come in pieces of so many, alone and flagged; no more than ``rows`` and a batch are held."""
    held: list[pa.RecordBatch] = []
    count, cut = 0, None

    def parts(whole: pa.Table, open_end: bool):
        nonlocal cut
        values = [whole.column(k).to_numpy() for k in keys]
        starts = starts_of(*values)
        ends = np.r_[starts[1:], whole.num_rows]
        long_run = ends - starts > most
        long_run[0] |= cut == [v[0] for v in values]
        if open_end:
            long_run[-1] = True
        cut = [v[-1] for v in values] if open_end else None
        at = 0
        for k in np.flatnonzero(long_run):
            if starts[k] > starts[at]:
                yield whole.slice(starts[at], starts[k] - starts[at]).combine_chunks(), np.zeros(k - at, bool)
            for a in range(starts[k], ends[k], most):
                yield whole.slice(a, min(most, ends[k] - a)).combine_chunks(), np.ones(1, bool)
            at = k + 1
        if at < len(starts):
            yield whole.slice(starts[at]).combine_chunks(), np.zeros(len(starts) - at, bool)

    for batch in batches:
        if not batch.num_rows:
            continue
        held.append(batch)
        count += batch.num_rows
        if count < max(rows, most + 1):
            continue
        whole = pa.Table.from_batches(held)
        change = np.flatnonzero(np.any([v[1:] != v[:-1] for v in (whole.column(k).to_numpy() for k in keys)], axis=0))
        at = int(change[-1]) + 1 if len(change) else whole.num_rows
        yield from parts(whole.slice(0, at), not len(change))
        rest = whole.slice(at).combine_chunks()
        held, count = rest.to_batches(), rest.num_rows
    if held and count:
        yield from parts(pa.Table.from_batches(held), False)


def starts_of(*columns: np.ndarray) -> np.ndarray:
    """Where runs of equal values start in sorted columns."""
    n = len(columns[0])
    if not n:
        return np.zeros(0, np.int64)
    change = np.zeros(n, bool)
    change[0] = True
    for v in columns:
        change[1:] |= v[1:] != v[:-1]
    return np.flatnonzero(change)
