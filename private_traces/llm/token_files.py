"""Token ids in Arrow files of equal-length sequences.

A shard is two Arrow IPC files. ``ids-N.arrow`` holds record batches of ``BATCH`` rows, each row a fixed-size
list of ``seq_len`` ids and one of mask bits (true: a token, false: padding of the shard's last row); a memory
map gives any sequence without copying, and sequence i is row ``i % BATCH`` of batch ``i // BATCH``.
``docs-N.arrow`` has the documents of the shard (doc_id, start within the shard, n_tokens). Shards hold
consecutive ranges of doc_id in ascending order, so the global order is shard by shard.

Each distinct word of a slice of texts is encoded once and kept in a bounded memo. A
shard is written under another name and then renamed, so a retried task leaves the same file.

Defined results: a null text is empty (only the end id); rows with a null id come first; equal ids keep all
their rows, ordered by text; an empty table writes no shard and gives no rows.
"""

from __future__ import annotations

import json
import uuid
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import fresh_path, pieces, written

CHUNK = 4_000_000
BATCH = 64
KEPT = 1_000_000


class Encoder:
    """The tokenizers library behind a bounded memo of words (runs without ASCII white space).

    Where the file's pre-split never crosses white space, a word's ids do not depend on its neighbours. New words are
    then encoded in one call, set apart by a control character whose id marks the borders; words that hold that
    character are encoded alone.
    """

    MARK = "\x01"

    def __init__(self, path: str):
        import os
        import re

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        with open(path) as f:
            spec = json.load(f)
        self.dtype = np.dtype("<u2") if self.tok.get_vocab_size() <= 1 << 16 else np.dtype("<u4")
        first = ((spec.get("pre_tokenizer") or {}).get("pretokenizers") or [{}])[0]
        apart = first.get("type") == "Split" and first.get("invert") and first.get("behavior") == "Removed" and spec["model"]["type"] == "BPE"
        mark = self.tok.encode(self.MARK, add_special_tokens=False).ids
        self.mark = mark[0] if apart and len(mark) == 1 else None
        self.runs = re.compile(r"[^\x20\x09-\x0D]+").findall
        self.odd = re.compile("[\x1c-\x1f\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]").search
        self.lowers = any(n.get("type") == "Lowercase" for n in (spec.get("normalizer") or {}).get("normalizers", []))
        added = [t["content"] for t in spec.get("added_tokens") or []]
        self.added = [t.lower() if self.lowers else t for t in added]  # lowered as the texts are that may hold them
        self.words: dict[str, bytes] = {}

    def _raw(self, texts: list[str]) -> list[bytes]:
        return [np.array(e.ids, self.dtype).tobytes() for e in self.tok.encode_batch_fast(texts, add_special_tokens=False)]

    def _learn(self, new: list[str]) -> None:
        plain = [w for w in new if self.MARK not in w and len(w) < 1000]
        alone = [w for w in new if self.MARK in w or len(w) >= 1000]
        for a in range(0, len(plain), 20_000):
            part = plain[a : a + 20_000]
            ids = np.array(self.tok.encode_batch_fast([f" {self.MARK} ".join(part)], add_special_tokens=False)[0].ids, self.dtype)
            cuts = np.flatnonzero(ids == self.mark)
            if len(cuts) != len(part) - 1:
                alone += part
                continue
            raw, size = ids.tobytes(), self.dtype.itemsize
            begins, ends = [0, *((cuts + 1) * size).tolist()], [*(cuts * size).tolist(), len(raw)]
            self.words.update(zip(part, [raw[x:y] for x, y in zip(begins, ends)]))
        self.words.update(zip(alone, self._raw(alone)))

    def split(self, text: str) -> list[str] | None:
        """Runs without ASCII white space; A-Z lowered where the tokenizer lowers anyway, so that fewer words differ. None for a
        text that may hold an added token of the vocabulary, which the library looks for in the text as it is."""
        if self.lowers and not text.islower():
            text = text.encode("utf-8", "surrogatepass").lower().decode("utf-8", "surrogatepass")
        if any(t in text for t in self.added):
            return None
        return self.runs(text) if self.odd(text) else text.split()

    def texts(self, texts: list[str]) -> list[bytes]:
        """Ids of each text as little-endian integers of ``dtype``."""
        if self.mark is None:
            return self._raw(texts)
        cut = list(map(self.split, texts))
        need = set().union(*(ws for ws in cut if ws is not None))
        self._learn(list(need - self.words.keys()))
        get = self.words.__getitem__
        out = [self._raw([t])[0] if ws is None else b"".join(map(get, ws)) for t, ws in zip(texts, cut)]
        if len(self.words) > KEPT:  # the words of this slice are the likeliest to come again
            self.words = {w: self.words[w] for w in need}
        return out


@lru_cache(maxsize=1)
def encoder(path: str) -> Encoder:
    return Encoder(path)


def _encode(batches, path: str, end_id: int, edges: np.ndarray):
    own = encoder(path)
    end = np.array([end_id], own.dtype).tobytes()
    for batch, texts in pieces(batches, "text", CHUNK):
        ids = batch.column("doc_id")
        keys = ids.fill_null(-(1 << 63)).to_numpy(zero_copy_only=False)
        yield pa.RecordBatch.from_pydict({
            "doc_id": ids, "shard": pa.array(np.searchsorted(edges, keys, side="left").astype(np.int32)),
            "raw": pa.array([r + end for r in own.texts(texts)], pa.binary()),
        })


def _fs(uri: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(uri if "://" in uri else uri.replace("file:", "file://", 1) if uri.startswith("file:") else f"file://{uri}")


def _write(batches, folder: str, seq_len: int, dtype: np.dtype):
    """Write the rows of one shard, which come in order; a manifest row for the shard."""
    fs, root = _fs(folder)
    value = pa.from_numpy_dtype(dtype)
    schema = pa.schema([("ids", pa.list_(value, seq_len)), ("mask", pa.list_(pa.bool_(), seq_len))])
    docs_schema = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64())])
    mark, shard, total, n_docs = uuid.uuid4().hex, None, 0, 0
    held: list[bytes] = []
    size = 0

    def full(raw: bytes, n: int):
        ids = np.zeros(-(-n // seq_len) * seq_len, dtype)
        ids[:n] = np.frombuffer(raw, dtype)
        mask = np.arange(len(ids)) < n
        out.write_batch(pa.RecordBatch.from_arrays([pa.FixedSizeListArray.from_arrays(pa.array(ids), seq_len), pa.FixedSizeListArray.from_arrays(pa.array(mask), seq_len)], schema=schema))

    step = BATCH * seq_len * dtype.itemsize
    for batch in batches:
        if not batch.num_rows:
            continue
        if shard is None:
            shard = batch.column("shard")[0].as_py()
            fs.create_dir(root)
            temps = [f"{root}/.{k}-{shard:06d}-{mark}" for k in ("ids", "docs")]
            sinks = [fs.open_output_stream(t) for t in temps]
            out, side = pa.ipc.new_file(sinks[0], schema), pa.ipc.new_file(sinks[1], docs_schema)
        raws = batch.column("raw").to_pylist()
        n = np.array([len(r) // dtype.itemsize for r in raws], np.int64)
        start = total + np.concatenate([[0], np.cumsum(n)[:-1]])
        side.write_batch(pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(start), pa.array(n)], schema=docs_schema))
        total, n_docs = total + int(n.sum()), n_docs + len(raws)
        for r in raws:
            held.append(r)
            size += len(r)
            if size >= step:
                whole = b"".join(held)
                for at in range(0, size - step + 1, step):
                    full(whole[at : at + step], BATCH * seq_len)
                held = [whole[size - size % step :]]
                size %= step
    if shard is not None:
        if size:
            full(b"".join(held), size // dtype.itemsize)
        out.close(), side.close()
        names = [f"{root}/{k}-{shard:06d}.arrow" for k in ("ids", "docs")]
        for sink, temp, name in zip(sinks, temps, names):
            sink.close()
            fs.move(temp, name)
        yield pa.RecordBatch.from_pydict({"shard": pa.array([shard], pa.int32()), "n_docs": pa.array([n_docs], pa.int64()), "n_tokens": pa.array([total], pa.int64())})


def write(docs: DataFrame, tokenizer: str, folder: str, end_id: int = 1, seq_len: int = 2048, shard_docs: int = 8192) -> DataFrame:
    """Encode and write ``docs`` under ``folder``; the manifest ``shard, n_docs, n_tokens, first`` (``first``: tokens before the shard)."""
    given = docs.select("doc_id", "text")
    rows = given.select("doc_id").count()
    shards = max(1, -(-rows // shard_docs))
    edges = np.zeros(0, np.int64)
    if shards > 1:
        cuts = given.select(F.percentile_approx("doc_id", [i / shards for i in range(1, shards)], max(10_000, 20 * shards)).alias("c")).first().c
        edges = np.array(sorted(set(cuts or [])), np.int64)
    dtype = encoder(tokenizer).dtype
    packed = given.mapInArrow(lambda b: _encode(b, tokenizer, end_id, edges), "doc_id long, shard int, raw binary")
    dealt = packed.repartitionById(len(edges) + 1, F.col("shard")).sortWithinPartitions("doc_id", "raw")
    manifest = written(dealt.mapInArrow(lambda b: _write(b, folder, seq_len, dtype), "shard int, n_docs long, n_tokens long"), "manifest")
    before = F.sum("n_tokens").over(Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1))
    return manifest.withColumn("first", F.coalesce(before, F.lit(0)).cast("long"))


class Reader:
    """Random access to one shard; sequences and masks are views of the mapped file where it is local."""

    def __init__(self, folder: str, shard: int):
        fs, root = _fs(folder)
        local = isinstance(fs, pafs.LocalFileSystem)
        opened = lambda kind: pa.memory_map(f"{root}/{kind}-{shard:06d}.arrow") if local else fs.open_input_file(f"{root}/{kind}-{shard:06d}.arrow")
        self.ids, self.docs = pa.ipc.open_file(opened("ids")), pa.ipc.open_file(opened("docs"))
        self.seq_len = self.ids.schema.field("ids").type.list_size
        self.at = -1

    def _batch(self, i: int) -> np.ndarray:
        if i != self.at:
            self.at, self.flat = i, self.ids.get_batch(i).column("ids").values.to_numpy(zero_copy_only=True)
        return self.flat

    def sequence(self, i: int) -> tuple[np.ndarray, pa.Array]:
        """Ids (a view) and mask of sequence ``i``."""
        batch = self.ids.get_batch(i // BATCH)
        row = i % BATCH
        return batch.column("ids").values.to_numpy(zero_copy_only=True)[row * self.seq_len : (row + 1) * self.seq_len], batch.column("mask")[row].values

    def tokens(self, start: int, n: int) -> np.ndarray:
        """``n`` ids from ``start``; a view where they lie in one batch."""
        width = BATCH * self.seq_len
        parts = []
        while n > 0:
            flat = self._batch(start // width)
            part = flat[start % width : start % width + n]
            parts.append(part)
            start, n = start + len(part), n - len(part)
        return parts[0] if len(parts) == 1 else np.concatenate(parts) if parts else np.zeros(0, np.uint16)


def _read(batches, folder: str):
    for batch in batches:
        for shard, first in zip(batch.column("shard").to_pylist(), batch.column("first").to_pylist()):
            reader = Reader(folder, shard)
            for i in range(reader.docs.num_record_batches):
                docs = reader.docs.get_batch(i)
                start, n = docs.column("start").to_numpy(), docs.column("n_tokens").to_numpy()
                crc = [zlib.crc32(reader.tokens(a, k).astype("<u4")) for a, k in zip(start.tolist(), n.tolist())]
                yield pa.RecordBatch.from_pydict({"doc_id": docs.column("doc_id"), "start": pa.array(start + first), "n_tokens": docs.column("n_tokens"), "ids_crc32": pa.array(crc, pa.int64())})


def read(manifest: DataFrame, folder: str) -> DataFrame:
    """``doc_id, start, n_tokens, ids_crc32`` of every document, read from the files."""
    return manifest.select("shard", "first").repartition(F.col("shard")).mapInArrow(lambda b: _read(b, folder), "doc_id long, start long, n_tokens long, ids_crc32 long")


def round_trip(docs: DataFrame, tokenizer: str, end_id: int = 1, seq_len: int = 2048, shard_docs: int = 8192) -> DataFrame:
    folder = fresh_path(docs.sparkSession, "tokens")
    return read(write(docs, tokenizer, folder, end_id, seq_len, shard_docs), folder)
