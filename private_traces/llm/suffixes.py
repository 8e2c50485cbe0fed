"""Removal of repeated passages by longest-previous-factor arrays, over the whole corpus.

A position's longest previous factor (LPF) is the longest string that starts there and also starts at an earlier
position (smaller doc_id, or earlier in the same document). In suffix order the longest earlier match of a
position is with its previous or its next entry of smaller position. Bytes under a string of ``WINDOW`` bytes whose
LPF reaches ``WINDOW`` are removed; the first copy stays. Matches never cross documents.

No corpus-wide suffix array is built; windows are brought together by content, without loss:

1. In each window the least hash of its ``ANCHOR``-byte substrings names an anchor. Equal windows have equal
   anchors at equal offsets. Consecutive windows of one anchor are one row: anchor hash, hash of all their bytes
   (the span), place. Copies inside one batch of documents leave here, so a hot passage costs a row per batch.
2. Rows meet by anchor. A span equal to an earlier one is removed whole. A first span whose anchor has no other span
   holds no repeated window. What is left are first spans that share an anchor but not all bytes: edges of
   repeated passages, and short common strings.
3. Those are cut into four ranges of windows; each range has a core of 83 bytes or more that all its windows
   contain, and meets others of equal core. There windows with the same offset are put in suffix order by the bytes
   beside the core; runs with a common prefix of ``WINDOW`` are found, and every position in a run with a previous
   or next smaller position (that is, all but its least) has LPF >= ``WINDOW``.
4. Ranges return to their documents, which are digested or cut.

Hashes are 64 bits twice (anchor and span are independent); what is compared in step 3 are the bytes themselves.

Defined results: a null text is empty; texts under ``WINDOW`` bytes lose nothing; rows that repeat an id, or have
none, are ordered by (doc_id, hash of the text), null first, and judged one by one; further columns pass through.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import aside, starts_of, widened, written

WINDOW = 100
ANCHOR = 32
REACH = WINDOW - ANCHOR  # bytes of a window beside its anchor
STEP = 17  # windows of one range differ by fewer than this in offset
RANGES = 4
PLACE_BITS = 24
SEGMENT = 1 << 20
_rng = np.random.default_rng(11)
_codes = _rng.integers(1, 1 << 63, (2, 256), dtype=np.uint64)
_base = np.uint64(0xD6E8FEB86659FD93)
_inverse = np.uint64(pow(int(_base), -1, 1 << 64))


def _mixed(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xA0761D6478BD642F)
    return x ^ (x >> np.uint64(29))


_powers: list[np.ndarray] = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _power(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers[0]) < n:
        for i, by in enumerate((_base, _inverse)):
            grown = np.full(n, by, np.uint64)
            grown[0] = 1
            _powers[i] = np.cumprod(grown)
    return _powers[0][:n], _powers[1][:n]


def _sums(data: np.ndarray, which: int) -> np.ndarray:
    """Prefix sums from which the hash of any substring follows."""
    up, _ = _power(len(data) + 1)
    out = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(_codes[which][data] * up[:-1], out=out[1:])
    return out


def _substring(sums: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    _, down = _power(len(sums))
    return _mixed((sums[end] - sums[start]) * down[start] + (end - start).astype(np.uint64))


def anchored(data: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, ...]:
    """Spans of the windows of texts that lie one after another in ``data`` (text i from bounds[i] to bounds[i+1]):
    anchor hash, span hash, first window, number of windows, offset of the anchor in the first window."""
    none = np.zeros(0, np.int64)
    if len(data) < WINDOW:
        return none.view(np.uint64), none.view(np.uint64), none, none, none
    sums = _sums(data, 0)
    count = len(data) - ANCHOR + 1
    at = np.arange(count)
    grams = _substring(sums, at, at + ANCHOR)
    low = (grams >> np.uint64(PLACE_BITS) << np.uint64(PLACE_BITS)) | at.astype(np.uint64)
    width, size = 1, REACH + 1
    while width * 2 <= size:
        low = np.minimum(low[:-width], low[width:])
        width *= 2
    if width < size:
        low = np.minimum(low[: len(low) - (size - width)], low[size - width :])
    owner = (low & np.uint64((1 << PLACE_BITS) - 1)).astype(np.int64)
    text = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))[: len(owner)]
    whole = np.arange(len(owner)) + WINDOW <= bounds[1:][text]
    change = np.ones(len(owner), bool)
    change[1:] = (owner[1:] != owner[:-1]) | (text[1:] != text[:-1]) | ~whole[:-1]
    first = np.flatnonzero(change & whole)
    ends = np.flatnonzero(whole & np.r_[change[1:] | ~whole[1:], True])
    n = ends - first + 1
    return grams[owner[first]], _substring(_sums(data, 1), first, ends + WINDOW), first, n, owner[first] - first


def _packed(lo: np.ndarray, n: np.ndarray, off: np.ndarray) -> np.ndarray:
    return lo << 16 | n << 8 | off


def _texts(batch, column: str = "text") -> list[bytes]:
    return [b"" if x is None else x for x in batch.column(column).cast(pa.binary()).to_pylist()]


def _segments(raw: list[bytes], keys: list[int]):
    """(bytes, bounds, keys, shift of each text): short texts together, a long one in overlapping parts."""
    held, own, size = [], [], 0
    for r, k in zip(raw, keys):
        if len(r) > SEGMENT:
            for a in range(0, len(r) - WINDOW + 1, SEGMENT):
                part = r[a : a + SEGMENT + WINDOW - 1]
                yield np.frombuffer(part, np.uint8), np.array([0, len(part)]), np.array([k]), np.array([a])
            continue
        if size + len(r) > SEGMENT and held:
            yield np.frombuffer(b"".join(held), np.uint8), np.cumsum([0, *map(len, held)]), np.array(own), np.zeros(len(own), np.int64)
            held, own, size = [], [], 0
        if len(r) >= WINDOW:
            held.append(r)
            own.append(k)
            size += len(r)
    if held:
        yield np.frombuffer(b"".join(held), np.uint8), np.cumsum([0, *map(len, held)]), np.array(own), np.zeros(len(own), np.int64)


DIRECT = 255  # in place of an anchor's offset: the span is a copy already, known inside its batch


def _spans(batches):
    for batch in batches:
        found = []
        for data, bounds, keys, shift in _segments(_texts(batch), batch.column("key").to_pylist()):
            h, c, first, n, off = anchored(data, bounds)
            text = np.searchsorted(bounds, first, side="right") - 1
            found.append((h.view(np.int64), c.view(np.int64), keys[text], _packed(first - bounds[text] + shift[text], n, off)))
        if not found:
            continue
        h, c, key, v = (np.concatenate([f[i] for f in found]) for i in range(4))
        order = np.lexsort((v, key, c, h))
        h, c, key, v = h[order], c[order], key[order], v[order]
        copy = np.zeros(len(h), bool)
        copy[1:] = (h[1:] == h[:-1]) & (c[1:] == c[:-1])
        v[copy] |= DIRECT
        h[copy] = _mixed((key[copy] ^ v[copy]).astype(np.uint64)).view(np.int64)
        yield pa.RecordBatch.from_pydict({"h": h, "c": c, "key": key, "v": v})


def _met(batches):
    """Rows in order of (h, c, key, v): spans with an earlier equal one (``h`` null), and first spans that share
    their anchor with another first span."""
    last_h = last_c = None
    held = None  # the last first span, whose successor is not known yet
    held_shared = False

    def out(h, key, v):
        return pa.RecordBatch.from_arrays([h, pa.array(key, pa.int64()), pa.array(v, pa.int64())], ["h", "key", "v"])

    for batch in batches:
        if not batch.num_rows:
            continue
        h, c, key, v = (batch.column(x).to_numpy() for x in ("h", "c", "key", "v"))
        direct = (v & 255) == DIRECT
        yield out(pa.nulls(int(direct.sum()), pa.int64()), key[direct], v[direct])
        h, c, key, v = h[~direct], c[~direct], key[~direct], v[~direct]
        if not len(h):
            continue
        same = np.zeros(len(h), bool)
        same[1:] = (h[1:] == h[:-1]) & (c[1:] == c[:-1])
        same[0] = last_h == h[0] and last_c == c[0]
        yield out(pa.nulls(int(same.sum()), pa.int64()), key[same], v[same])
        last_h, last_c = h[-1], c[-1]
        h, key, v = h[~same], key[~same], v[~same]
        if not len(h):
            continue
        if held is not None:
            h, key, v = np.r_[held[0], h], np.r_[held[1], key], np.r_[held[2], v]
        shared = np.zeros(len(h), bool)
        shared[1:] |= h[1:] == h[:-1]
        shared[:-1] |= h[1:] == h[:-1]
        shared[0] |= held is not None and held_shared
        held, held_shared = (h[-1], key[-1], v[-1]), bool(shared[-1])
        go = shared[:-1]
        yield out(pa.array(h[:-1][go], pa.int64()), key[:-1][go], v[:-1][go])
    if held is not None and held_shared:
        yield out(pa.array([held[0]], pa.int64()), [held[1]], [held[2]])


def _zipped_rows(batches):
    """The rows with their text packed into ``z``, so that a shuffle carries a third of it."""
    import zstandard

    press = zstandard.ZstdCompressor(level=1)
    for batch in batches:
        names = [n for n in batch.schema.names if n != "text"]
        yield pa.RecordBatch.from_arrays([*(batch.column(n) for n in names), pa.array([press.compress(r) for r in _texts(batch)], pa.binary())], [*names, "z"])


def _unzip():
    import zstandard

    return zstandard.ZstdDecompressor().decompress


PIECE = "core long, key long, place long, data binary"


def _pieces(batches):
    """The ranges of windows of first spans that share an anchor: core hash, place, bytes. A piece equal to one
    before it in the batch is a copy (``data`` null)."""
    unzip = _unzip()
    for batch in batches:
        rows: list[tuple] = []
        for key, z, spans in zip(*(batch.column(c).to_pylist() for c in ("key", "z", "spans"))):
            raw = unzip(z)
            for v in spans:
                lo, n, off = v >> 16, v >> 8 & 255, v & 255
                for r in range(RANGES):
                    most = min(off, STEP * (r + 1) - 1 if r < RANGES - 1 else REACH)
                    least = max(off - n + 1, STEP * r)
                    if most < least:
                        continue
                    anchor = lo + off
                    core = raw[anchor - STEP * r : anchor + ANCHOR + (max(0, REACH - STEP * (r + 1) + 1) if r < RANGES - 1 else 0)]
                    tag = int.from_bytes(hashlib.blake2b(core, digest_size=8, salt=bytes([r])).digest(), "little", signed=True)
                    rows.append((tag, key, (anchor - most) << 16 | (most - least + 1) << 8 | most, raw[anchor - most : anchor - least + WINDOW]))
        rows.sort(key=lambda x: x[1:3])
        seen: set[tuple] = set()
        data = []
        for tag, key, place, piece in rows:
            mark = (tag, place & 0xFFFF, piece)
            data.append(None if mark in seen else piece)
            seen.add(mark)
        for a in range(0, len(rows), 20_000):
            part = rows[a : a + 20_000]
            yield pa.RecordBatch.from_pydict({"core": pa.array([p[0] for p in part], pa.int64()), "key": pa.array([p[1] for p in part], pa.int64()), "place": pa.array([p[2] for p in part], pa.int64()), "data": pa.array(data[a : a + 20_000], pa.binary())})


def repeated(group: np.ndarray, order_key: np.ndarray, beside: np.ndarray, position: tuple[np.ndarray, ...]) -> np.ndarray:
    """Which windows have LPF >= WINDOW. Windows of one ``group`` and ``order_key`` (offset) share their core; ``beside`` (two
    integers) are the bytes on either side in order, so sorting by them is suffix order and equal values are a common
    prefix of WINDOW. In each such run a previous or next smaller position exists for all but the least."""
    order = np.lexsort((*position[::-1], beside[1], beside[0], order_key, group))
    starts = starts_of(group[order], order_key[order], beside[0][order], beside[1][order])
    out = np.ones(len(group), bool)
    out[order[starts]] = False
    return out


def _judged(batches):
    """Repeated windows of the pieces of each core, as packed ranges of their document."""
    carry = None  # (core, windows already met) of a core that goes on in the next batch: least windows only
    for batch in batches:
        if not batch.num_rows:
            continue
        yield from _copies(batch)
        batch = batch.filter(batch.column("data").is_valid())
        core, key, place = (batch.column(c).to_numpy() for c in ("core", "key", "place"))
        alone = np.ones(len(core), bool)
        if len(core) > 1:
            alone[1:] &= core[1:] != core[:-1]
            alone[:-1] &= core[1:] != core[:-1]
        if len(core):
            alone[0] &= carry is None or carry["core"][0] != core[0]
            alone[-1] = False  # it may go on
        some = np.flatnonzero(~alone)
        if not len(some):
            continue
        core, key, place = core[some], key[some], place[some]
        data = batch.column("data").take(pa.array(some)).to_pylist()
        now = _windows(core, key, place, data)
        if carry is not None and carry["core"][0] == core[0]:
            now = {k: np.concatenate([carry[k], now[k]]) for k in now}
        gone = repeated(now["core"], now["left"], (now["b0"], now["b1"]), (now["key"], now["start"]))
        fresh = gone & ~now["old"]
        if fresh.any():
            yield _ranges(now["key"][fresh], now["start"][fresh])
        stay = (now["core"] == core[-1]) & ~gone
        carry = {k: x[stay] for k, x in now.items()}
        carry["old"] = np.ones(int(stay.sum()), bool)
        if not stay.any():
            carry = None


def _windows(core, key, place, data) -> dict[str, np.ndarray]:
    """Every window of the pieces: core, offset, position, and the bytes beside the core as two big-endian integers."""
    n = (place >> 8) & 255
    most = place & 255
    first = place >> 16
    piece = np.repeat(np.arange(len(core)), n)
    step = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
    left = most[piece] - step
    r = np.minimum(left // STEP, RANGES - 1)
    flat = np.frombuffer(b"".join(data) + b"\0" * WINDOW, np.uint8)
    base = np.cumsum([0, *map(len, data)])[:-1][piece] + step
    before = left - STEP * r  # bytes of the window left of the core
    core_size = np.where(r < RANGES - 1, STEP * r + ANCHOR + REACH - STEP * (r + 1) + 1, STEP * r + ANCHOR)
    slot = np.arange(STEP + 1)
    beside = base[:, None] + slot + np.where(slot[None, :] < before[:, None], 0, core_size[:, None])
    used = slot[None, :] < (WINDOW - core_size)[:, None]
    raw = np.where(used, flat[np.minimum(beside, len(flat) - 1)], 0).astype(np.uint8)
    b0 = np.ascontiguousarray(raw[:, :8]).view(">u8").ravel().astype(np.uint64)
    b1 = np.ascontiguousarray(raw[:, 8:16]).view(">u8").ravel().astype(np.uint64)
    rest = raw[:, 16:].astype(np.int64) @ np.array([256, 1])
    return {"core": core[piece], "left": left * 65536 + rest, "key": key[piece], "start": first[piece] + step, "b0": b0, "b1": b1, "old": np.zeros(len(piece), bool)}


def _ranges(key: np.ndarray, start: np.ndarray) -> pa.RecordBatch:
    """Runs of consecutive windows of a document, at most 200 in a row of output."""
    order = np.lexsort((start, key))
    key, start = key[order], start[order]
    at = np.arange(len(key))
    runs = starts_of(key, start - at)
    inside = at - np.repeat(runs, np.diff(np.r_[runs, len(key)]))
    cut = np.flatnonzero(inside % 200 == 0)
    return pa.RecordBatch.from_pydict({"key": key[cut], "v": _packed(start[cut], np.diff(np.r_[cut, len(key)]), np.zeros(len(cut), np.int64))})


def _copies(batch):
    copy = batch.filter(batch.column("data").is_null())
    if copy.num_rows:
        yield pa.RecordBatch.from_arrays([copy.column("key"), copy.column("place")], ["key", "v"])


def removed_ranges(keyed: DataFrame) -> DataFrame:
    """``key, v`` (packed first window and number of windows) of every repeated run of windows. ``keyed``: key, text."""
    spans = keyed.select("key", "text").mapInArrow(_spans, "h long, c long, key long, v long")
    dealt = spans.repartition(F.col("h")).sortWithinPartitions("h", "c", "key", "v")
    marks = written(dealt.mapInArrow(_met, "h long, key long, v long"), "marks")
    edges = marks.where("h is not null").groupBy("key").agg(F.collect_list("v").alias("spans"))
    zipped = keyed.select("key", "text").mapInArrow(_zipped_rows, "key long, z binary")
    cores = zipped.join(edges, "key").mapInArrow(_pieces, PIECE)
    judged = cores.repartition(F.col("core")).sortWithinPartitions("core", "key", "place").mapInArrow(_judged, "key long, v long")
    return marks.where("h is null").select("key", "v").unionByName(judged)


def _keyed(docs: DataFrame) -> DataFrame:
    """``docs`` with ``__key``: doc_id where ids are unique, otherwise numbers in the order of (doc_id, hash of the text)."""
    ids = docs.agg(F.count("*").alias("n"), F.count_distinct("doc_id").alias("d")).first()
    if ids.n == ids.d:
        return docs.withColumn("__key", F.col("doc_id"))
    ordered = docs.withColumn("__hash", F.xxhash64("text")).repartitionByRange(64, "doc_id", "__hash").sortWithinPartitions("doc_id", "__hash")
    return written(ordered.drop("__hash").withColumn("__key", F.monotonically_increasing_id()), "keyed")


def _ranges_of(keyed: DataFrame) -> DataFrame:
    """``__key, __ranges``: all repeated ranges of each document."""
    found = removed_ranges(keyed.select(F.col("__key").alias("key"), "text"))
    return found.groupBy(F.col("key").alias("__key")).agg(F.collect_list("v").alias("__ranges"))


def covered(size: int, ranges: list[int]) -> list[tuple[int, int]]:
    """Maximal removed runs of bytes."""
    out: list[list[int]] = []
    for v in sorted(ranges):
        a, b = v >> 16, (v >> 16) + (v >> 8 & 255) + WINDOW - 1
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, min(b, size)) for a, b in out]


def _kept(raw: bytes, gone: list[tuple[int, int]]) -> bytes:
    at, parts = 0, []
    for a, b in gone:
        parts.append(raw[at:a])
        at = b
    return b"".join([*parts, raw[at:]])


def _digest(batches):
    unzip = _unzip()
    for batch in batches:
        rows = []
        for z, ranges in zip(batch.column("z").to_pylist(), batch.column("ranges").to_pylist()):
            raw = unzip(z)
            gone = covered(len(raw), ranges or [])
            rows.append((len(raw), sum(b - a for a, b in gone), len(gone), hashlib.sha256(_kept(raw, gone)).hexdigest()))
        columns = list(zip(*rows)) or [[]] * 4
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(c, pa.int64()) for c in columns[:3]), pa.array(columns[3], pa.string())], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])


def digests(docs: DataFrame) -> DataFrame:
    """``doc_id, n_bytes, n_removed, n_spans, kept_sha256`` of every row."""
    keyed = _keyed(docs.select("doc_id", "text"))
    packed = keyed.select("__key", "doc_id", "text").mapInArrow(_zipped_rows, "__key long, doc_id long, z binary")
    joined = packed.join(_ranges_of(keyed), "__key", "left").select("doc_id", "z", F.col("__ranges").alias("ranges"))
    return joined.mapInArrow(_digest, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def _cut(batches, names: list[str]):
    for batch in batches:
        raws = _texts(batch)
        texts, spans = [], []
        for raw, ranges, given in zip(raws, batch.column("__ranges").to_pylist(), batch.column("text").is_null().to_pylist()):
            gone = covered(len(raw), ranges or [])
            texts.append(None if given else _kept(raw, gone).decode("utf-8", "replace"))
            spans.append([{"start": a, "end": b} for a, b in gone])
        kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
        columns = [pa.array(texts, pa.string()) if n == "text" else batch.column(n) for n in names]
        yield pa.RecordBatch.from_arrays([*columns, pa.array(spans, kind)], [*names, "removed"])


def dedup(docs: DataFrame) -> DataFrame:
    """``docs`` with repeated passages cut from ``text`` and ``removed``: the runs of bytes that went (in place of any column
    of that name). A cut inside a character leaves a replacement mark."""
    own, back = aside(docs.drop("removed"), ["doc_id", "text"])
    names = own.columns
    keyed = _keyed(own)
    schema = widened(own, "removed array<struct<start:bigint,end:bigint>>")
    return back(keyed.join(_ranges_of(keyed), "__key", "left").drop("__key").mapInArrow(lambda b: _cut(b, names), schema), "removed")


def longest_previous_factor(text: bytes) -> np.ndarray:
    """LPF of every position of one text: a suffix array by doubling, then previous and next smaller positions."""
    n = len(text)
    rank = np.frombuffer(text, np.uint8).astype(np.int64)
    order, width = np.argsort(rank, kind="stable"), 1
    while n and width < 2 * n:
        second = np.full(n, -1, np.int64)
        second[: max(0, n - width)] = rank[width:] if width < n else rank[:0]
        order = np.lexsort((second, rank))
        rank2 = np.zeros(n, np.int64)
        rank2[order[1:]] = np.cumsum((rank[order[1:]] != rank[order[:-1]]) | (second[order[1:]] != second[order[:-1]]))
        rank = rank2
        if n and rank.max() == n - 1:
            break
        width *= 2
    smaller = [[-1] * n, [-1] * n]  # nearest entries of smaller position before and after in suffix order
    for side, walk in ((0, order.tolist()), (1, order.tolist()[::-1])):
        stack: list[int] = []
        for p in walk:
            while stack and stack[-1] > p:
                stack.pop()
            smaller[side][p] = stack[-1] if stack else -1
            stack.append(p)
    out = np.zeros(n, np.int64)
    reach = [0, 0]
    for p in range(n):
        for side in (0, 1):
            q, k = smaller[side][p], max(0, reach[side] - 1)
            if q < 0:
                reach[side] = 0
                continue
            k = 0 if text[q : q + k] != text[p : p + k] else k
            while p + k < n and text[p + k] == text[q + k]:
                k += 1
            reach[side] = k
            out[p] = max(out[p], k)
    return out
