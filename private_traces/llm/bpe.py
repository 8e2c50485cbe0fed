"""Byte-level BPE encoding and decoding against a fixed rank file.

Each text is cut by the public pre-split pattern; the distinct words of a slice of texts are folded
together: every round looks up the rank of each adjacent pair and joins the lowest-ranked, leftmost pair of
every word at once in numpy, until no pair has a rank. Words above ``LONG`` bytes are folded with a heap, so
one long run costs n log n. Decoding concatenates the binary pieces of the ids.

Style: Arrow batches and numpy. Folding with Spark's higher-order functions is in ``fold_words`` (used on
distinct words); README gives the figures that keep it off the main path.

Defined results: a null text is encoded as the empty text (no ids, empty bytes); rows are never joined, so
repeated ids and further columns do no harm.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from array import array
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import pieces, widened

CHUNK = 4_000_000
LONG = 64
KEPT_WORDS = 400_000
KEPT_WITH_IDS = 150_000  # beside the heap of a pipeline's other stages
SLOT_BITS = 21
NO_RANK = (1 << 31) - 1
_NONE = np.int64(1) << 62


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


class Folder:
    """Folds words by the ranks of one file; keeps a bounded memo of words met before."""

    def __init__(self, path: str, pattern: str, ids: bool = False):
        import regex

        self.ids, self.kept = ids, KEPT_WITH_IDS if ids else KEPT_WORDS

        self.ranks = read_ranks(path)
        self.words = regex.compile(pattern).findall
        self.piece = {i: b for b, i in self.ranks.items()}
        self.shown = {i: str(i) for i in self.piece}
        self.byte = np.array([self.ranks[bytes([i])] for i in range(256)], np.int64)
        pairs = {}
        for token, rank in self.ranks.items():
            for cut in range(1, len(token)):
                left, right = self.ranks.get(token[:cut]), self.ranks.get(token[cut:])
                if left is not None and right is not None:
                    pairs[left << 20 | right] = rank
        self._table(np.array(list(pairs), np.int64), np.array(list(pairs.values()), np.int64))
        self.memo: dict[str, tuple] = {}  # (ids as text, number, bytes), or (ids as 32-bit integers, bytes)

    @staticmethod
    def _slot(pair: np.ndarray) -> np.ndarray:
        return ((pair.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - SLOT_BITS)).astype(np.int64)

    def _table(self, pairs: np.ndarray, ranks: np.ndarray) -> None:
        """An open-addressed table of the pairs; ``probes`` slots from the home slot find any of them."""
        self.keys, self.joined = np.full((1 << SLOT_BITS) + 64, -1), np.full((1 << SLOT_BITS) + 64, _NONE)
        self.probes = 0
        while len(pairs):
            slot = self._slot(pairs) + self.probes
            free = self.keys[slot] == -1
            _, first = np.unique(slot[free], return_index=True)
            put = np.flatnonzero(free)[first]
            self.keys[slot[put]], self.joined[slot[put]] = pairs[put], ranks[put]
            left = np.ones(len(pairs), bool)
            left[put] = False
            pairs, ranks = pairs[left], ranks[left]
            self.probes += 1

    def _rank(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        want = left << 20 | right
        slot = self._slot(want)
        found = np.where(self.keys[slot] == want, self.joined[slot], _NONE)
        for i in range(1, self.probes):
            open_ = np.flatnonzero((found == _NONE) & (self.keys[slot + i - 1] != -1))
            if not len(open_):
                break
            at = slot[open_] + i
            found[open_] = np.where(self.keys[at] == want[open_], self.joined[at], _NONE)
        return found

    def fold_long(self, word: bytes) -> list[int]:
        """One word by a heap of ranked neighbours over a linked list."""
        ids = self.byte[np.frombuffer(word, np.uint8)].tolist()
        n = len(ids)
        parts = [bytes([b]) for b in word]
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(r, i, parts[i] + parts[i + 1]) for i in range(n - 1) if (r := self.ranks.get(parts[i] + parts[i + 1])) is not None]
        heapq.heapify(heap)
        alive = [True] * n
        while heap:
            rank, i, whole = heapq.heappop(heap)
            j = after[i] if alive[i] else n
            if j >= n or parts[i] + parts[j] != whole:
                continue
            parts[i], ids[i], alive[j] = whole, rank, False
            after[i] = after[j]
            if after[i] < n:
                before[after[i]] = i
            for a, b in ((before[i], i), (i, after[i])):
                if a >= 0 and b < n and (r := self.ranks.get(parts[a] + parts[b])) is not None:
                    heapq.heappush(heap, (r, a, parts[a] + parts[b]))
        return [x for x, ok in zip(ids, alive) if ok]

    def fold(self, words: list[bytes]) -> list[list[int]]:
        """Ids of each word (none above LONG bytes), all folded side by side."""
        lengths = np.array([len(w) for w in words], np.int64)
        ids = self.byte[np.frombuffer(b"".join(words), np.uint8)]
        word = np.repeat(np.arange(len(words)), lengths)
        done: list[tuple[np.ndarray, np.ndarray]] = []
        while len(ids):
            rank = np.full(len(ids), _NONE)
            if len(ids) > 1:
                same = word[1:] == word[:-1]
                rank[:-1] = np.where(same, self._rank(ids[:-1], ids[1:]), _NONE)
            starts = np.flatnonzero(np.r_[True, word[1:] != word[:-1]])
            at = np.arange(len(ids))
            best = np.minimum.reduceat(np.where(rank < _NONE, rank << 32 | at, _NONE), starts)
            live = best < _NONE
            if not live.all():
                row_live = np.repeat(live, np.diff(np.r_[starts, len(ids)]))
                done.append((word[~row_live], ids[~row_live]))
            else:
                row_live = np.ones(len(ids), bool)
            place = best[live] & 0xFFFFFFFF
            ids[place] = best[live] >> 32
            row_live[place + 1] = False
            ids, word = ids[row_live], word[row_live]
        owner = np.concatenate([d[0] for d in done]) if done else np.zeros(0, np.int64)
        flat = np.concatenate([d[1] for d in done]) if done else np.zeros(0, np.int64)
        order = np.argsort(owner, kind="stable")
        owner, flat = owner[order], flat[order].tolist()
        cuts = np.searchsorted(owner, np.arange(len(words) + 1)).tolist()
        return [flat[a:b] for a, b in zip(cuts, cuts[1:])]

    def learn(self, words: set[str]) -> None:
        """Put every word into the memo."""
        new = [w for w in words if w not in self.memo]
        raw = [w.encode("utf-8", "surrogatepass") for w in new]
        short = [i for i, r in enumerate(raw) if len(r) <= LONG]
        ids: list = [None] * len(new)
        for i, found in zip(short, self.fold([raw[i] for i in short])):
            ids[i] = found
        for i, r in enumerate(raw):
            if ids[i] is None:
                ids[i] = self.fold_long(r)
        shown, piece = self.shown.__getitem__, self.piece.__getitem__
        for w, found in zip(new, ids):
            raw = b"".join(map(piece, found))
            self.memo[w] = (array("i", found).tobytes(), raw) if self.ids else (" ".join(map(shown, found)), len(found), raw)

    def texts(self, texts: list[str]):
        """The memo entries of the words of each text, in order."""
        cut = [self.words(t) for t in texts]
        need = set().union(*cut) if cut else set()
        self.learn(need)
        get = self.memo.__getitem__
        for words in cut:
            yield list(map(get, words))
        if len(self.memo) > self.kept:  # the words of this slice are the likeliest to come again
            self.memo = {w: self.memo[w] for w in need}


@lru_cache(maxsize=2)
def folder(path: str, pattern: str, ids: bool = False) -> Folder:
    return Folder(path, pattern, ids)


def _digest(batches, path: str, pattern: str):
    own = folder(path, pattern)
    for batch, texts in pieces(batches, "text", CHUNK):
        n, ids, back = [], [], []
        for entries in own.texts(texts):
            shown, counts, raw = zip(*entries) if entries else ((), (), ())
            n.append(sum(counts))
            ids.append(hashlib.sha256(" ".join(shown).encode()).hexdigest())
            back.append(hashlib.sha256(b"".join(raw)).hexdigest())
        yield pa.RecordBatch.from_pydict({"doc_id": batch.column("doc_id"), "n_tokens": pa.array(n, pa.int64()), "ids_sha256": pa.array(ids, pa.string()), "decoded_sha256": pa.array(back, pa.string())})


def digests(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """``doc_id, n_tokens, ids_sha256, decoded_sha256``: encoded, decoded again, and both digested."""
    return docs.select("doc_id", "text").mapInArrow(lambda b: _digest(b, path, pattern), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def _encode(batches, path: str, pattern: str):
    own = folder(path, pattern, True)
    for batch, texts in pieces(batches, "text", CHUNK // 4):
        raw = [b"".join([e[0] for e in entries]) for entries in own.texts(texts)]
        ends = np.cumsum([0, *(len(r) // 4 for r in raw)])
        ids = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.frombuffer(b"".join(raw), np.int32)))
        yield pa.RecordBatch.from_arrays([*batch.columns, ids], [*batch.schema.names, "token_ids"])


def encode(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """``docs`` with ``token_ids`` (array of int) in place of any column of that name."""
    kept = docs.drop("token_ids")
    return kept.mapInArrow(lambda b: _encode(b, path, pattern), widened(kept, "token_ids array<int>"))


def _decode(batches, path: str, pattern: str):
    piece = folder(path, pattern).piece.__getitem__
    for batch in batches:
        given = batch.column("token_ids")
        values, ends = given.flatten().to_numpy(), np.cumsum([0, *(n or 0 for n in given.value_lengths().to_pylist())])
        raw = [b"".join(map(piece, values[a:b].tolist())) for a, b in zip(ends, ends[1:])]
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(raw, pa.binary())], [*batch.schema.names, "decoded"])


def decode(encoded: DataFrame, path: str, pattern: str) -> DataFrame:
    """``encoded`` with ``decoded`` (binary): the pieces of ``token_ids`` concatenated; null ids give no bytes."""
    kept = encoded.drop("decoded")
    return kept.mapInArrow(lambda b: _decode(b, path, pattern), widened(kept, "decoded binary"))


def _round_trip(batches, path: str, pattern: str):
    own = folder(path, pattern, True)
    for batch, texts in pieces(batches, "text", CHUNK // 4):
        ids, back = [], []
        for entries in own.texts(texts):
            ids.append(b"".join([e[0] for e in entries]))
            back.append(b"".join([e[1] for e in entries]))
        same = pa.array([b == t.encode("utf-8", "surrogatepass") for b, t in zip(back, texts)])
        ends = np.cumsum([0, *(len(r) // 4 for r in ids)])
        tokens = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.frombuffer(b"".join(ids), np.int32)))
        names = [n for n in batch.schema.names if n != "text"]
        yield pa.RecordBatch.from_arrays([*(batch.column(n) for n in names), tokens, same], [*names, "token_ids", "round_trip"])


def round_trip(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """``docs`` without its text but with ``token_ids`` and ``round_trip``: whether decoding gives the text's bytes. One pass
    (and one Python worker a task) for both directions."""
    kept = docs.drop("token_ids", "round_trip")
    return kept.mapInArrow(lambda b: _round_trip(b, path, pattern), widened(kept.drop("text"), "token_ids array<int>, round_trip boolean"))


def rank_literal(path: str, cells: int = 4096) -> Column:
    """The rank file as one constant array of small maps, by crc32 of the piece's hexadecimal text."""
    import json
    import zlib

    maps: list[dict[str, int]] = [{} for _ in range(cells)]
    for piece, rank in read_ranks(path).items():
        key = piece.hex().upper()
        maps[zlib.crc32(key.encode()) % cells][key] = rank
    return F.from_json(F.lit(json.dumps(maps)), "array<map<string,int>>")


def fold_words(words: DataFrame, path: str, cells: int = 4096) -> DataFrame:
    """``word, ids`` of distinct words by Spark's higher-order functions alone.

    State: the word's pieces as hexadecimal texts. Each step finds the lowest-ranked adjacent pair, the leftmost
    among equals, and joins it; a word of n bytes takes n steps at most.
    """
    table = rank_literal(path, cells)

    def rank(piece: Column) -> Column:
        return table[(F.crc32(piece.cast("binary")) % cells).cast("int")][piece]

    def step(parts: Column, _: Column) -> Column:
        pairs = F.transform(F.sequence(F.lit(0), F.size(parts) - 2), lambda i: F.struct(F.coalesce(rank(F.concat(F.get(parts, i), F.get(parts, i + 1))), F.lit(NO_RANK)).alias("rank"), i.alias("at")))
        best = F.array_min(pairs)

        def join(b: Column) -> Column:
            whole = F.concat(F.get(parts, b["at"]), F.get(parts, b["at"] + 1))
            return F.when(b["rank"] == NO_RANK, parts).otherwise(F.concat(F.slice(parts, F.lit(1), b["at"]), F.array(whole), F.slice(parts, b["at"] + 3, F.size(parts))))

        return F.when(F.size(parts) < 2, parts).otherwise(F.transform(F.array(best), join)[0])

    raw = F.hex(F.encode("word", "UTF-8"))
    n = F.octet_length("word").cast("int")
    first = F.transform(F.sequence(F.lit(0), n - 1), lambda i: F.substring(raw, i * 2 + 1, F.lit(2)))
    one = F.when(n > 0, first).otherwise(F.array().cast("array<string>"))
    folded = F.aggregate(F.sequence(F.lit(1), F.greatest(n, F.lit(1))), one, step)
    return words.where("word is not null").select("word").distinct().select("word", F.transform(folded, rank).alias("ids"))
