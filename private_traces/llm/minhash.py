"""Near-duplicate documents by a chosen-path set similarity join.

A document's set is its distinct word shingles (``width`` words, A-Z lower-cased; a text of fewer words is one shingle).
Documents with equal sets are joined first by two sums of shingle hashes, so a group of copies is one set from there on.
Each set has ``COORDS`` minwise tokens of its own in each of ``trees`` trees. In a tree a node picks, by a hash of its path,
on average 1/threshold of the coordinates; a set goes to one child per picked coordinate, named by its minwise token there.
Two sets that agree with probability at or above the threshold share a child at every level with a probability that falls only
slowly with depth, and trees raise the recall: no two share a coordinate. ``recall`` counts that all picks of one tree come
from the same ``COORDS`` tokens and that its sketch may fall below the cut; ``trees_for`` takes as many trees as miss a pair at
the threshold with a chance of at most ``MISS`` at the last level.

Nodes of up to ``LIMIT`` sets are compared exhaustively by their tokens; larger ones are dealt out in parts, which are compared
in themselves, and branch again. Then two rounds on full sets settle what the sketches suggest:

1. Every set is confirmed against the two sets that look nearest to it over all its nodes. That joins nearly all of a group of
   near copies, by two rows a set.
2. What still looks near and is not in one class is compared in full. Pairs of thin nodes are confirmed one by one. Sets of
   dense nodes are dealt to blocks of about ``BLOCK`` sets of one home, which is the largest class found beside them in a node; a set is
   sent once to each block of a home with a set it looks near to, compared there with the whole block on hashed
   sets, and only links that join two classes leave the block. So the rows grow with sets times blocks and not with pairs.

At ``DEEPEST`` large nodes branch no more: every set outside the node's largest class goes to every block of the node. Every
link is confirmed on the words themselves in the end.

Defined results: null, empty and word-less texts have an empty set and link with nothing; repeated rows of one id count as one
document with the set of each row; a null id takes part, but names a class only where no other id is in it. Rows are returned
once each.
"""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import pieces, runs, starts_of, written

CHUNK = 2_000_000
COORDS = 32  # minwise tokens of each tree
LIMIT = 4096  # sets of a node that are compared exhaustively
TINY = 48  # nodes up to here are compared side by side
FIRST_DEPTH = 2
DEEPEST = 9
ROUNDS = 64  # throws of a whole set before the tokens still missing are drawn one by one
BLOCK = 512
MISS = 1e-4  # the chance that a pair at the threshold is not found
NEAREST = 2  # sets that are confirmed for each set first
SAMPLE = 16  # one set in so many tells which nodes are large
SMALL = 500_000
Texts = Callable[[DataFrame], DataFrame]
EMPTY = np.uint64(0xFFFFFFFFFFFFFFFF)


def mixed(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser."""
    x = x.astype(np.uint64, copy=True)
    for shift, by in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x ^= x >> np.uint64(shift)
        x *= np.uint64(by)
    return x ^ (x >> np.uint64(31))


def recall(threshold: float, trees: int, depth: int) -> float:
    """The chance that a pair at the threshold meets in some tree at ``depth`` and passes the cut there. Within a tree both
    hang on how many of its ``COORDS`` tokens agree."""
    extra, one_tree = 1 / threshold - 1, 0.0
    for agree in range(COORDS + 1):
        if agree < loose(threshold) * COORDS:
            continue
        q = 1.0
        for _ in range(depth):
            one = agree / COORDS * q
            q = (1 - extra) * one + extra * (1 - (1 - one) ** 2)
        one_tree += math.comb(COORDS, agree) * threshold**agree * (1 - threshold) ** (COORDS - agree) * q
    return 1 - (1 - one_tree) ** trees


def trees_for(threshold: float) -> int:
    """The least number of trees that miss a pair at the threshold with a chance of at most ``MISS`` at ``DEEPEST``."""
    return math.ceil(math.log(MISS) / math.log(1 - recall(threshold, 1, DEEPEST)))


def loose(threshold: float, coords: int = COORDS) -> float:
    """Agreement of so many tokens from which a pair looks near: 3.5 deviations below the threshold."""
    return threshold - 3.5 * (threshold * (1 - threshold) / coords) ** 0.5


def words_of(text: str) -> list[bytes]:
    """The words as UTF-8: bytes lower-case A-Z alone and split at the six white-space characters of the definition."""
    return text.encode().lower().split()


def shingles(text: str, width: int) -> set[tuple[bytes, ...]]:
    """The set itself, as tuples of words."""
    w = words_of(text)
    if not w:
        return set()
    return set(zip(*(w[i:] for i in range(width)))) if len(w) >= width else {tuple(w)}


_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True


def _word_hashes(joined: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Where each word of the lower-cased bytes starts, and its 64-bit hash, by blocks of eight bytes."""
    buffer = np.frombuffer(joined + b"        ", np.uint8)
    edge = np.flatnonzero(np.diff(_SPACE[buffer[:-7]], prepend=True))
    start, size = edge[::2], edge[1::2] - edge[::2]
    eight = np.ndarray(len(buffer) - 7, "<u8", buffer.data, strides=(1,))
    h, some = mixed(size.astype(np.uint64) + np.uint64(0x9E3779B97F4A7C15)), np.arange(len(start))
    at = 0
    while len(some):
        left = size[some] - at
        block = eight[start[some] + at]
        block &= np.uint64(0xFFFFFFFFFFFFFFFF) >> (np.uint64(64) - np.uint64(8) * np.minimum(left, 8).astype(np.uint64))
        h[some] = mixed(h[some] ^ block) + np.uint64(0x51ED2701)
        at += 8
        some = some[left > 8]
    return start, h


def hashed_sets(texts: list[str], width: int) -> list[np.ndarray]:
    """Each text's set as sorted 64-bit hashes of its shingles."""
    raw = [t.encode().lower() for t in texts]
    begin = np.cumsum([0, *(len(x) + 1 for x in raw)])
    start, word = _word_hashes(b" ".join(raw))
    first = np.searchsorted(start, begin)  # the first word of each text
    whole = np.zeros(max(len(word) - width + 1, 0), np.uint64)
    for i in range(width):
        whole = mixed(whole + word[i : i + len(whole)] + np.uint64(i + 1)) * np.uint64(0x9E3779B97F4A7C15)
    out = []
    for a, b in zip(first[:-1].tolist(), first[1:].tolist()):
        if b - a >= width:
            s = np.sort(whole[a : b - width + 1])
            out.append(s[np.r_[True, s[1:] != s[:-1]]])
        else:  # all words as one shingle
            s = np.zeros(min(b - a, 1), np.uint64)
            for i in range(b - a):
                s = mixed(s + word[a + i] + np.uint64(i + 1)) * np.uint64(0x9E3779B97F4A7C15)
            out.append(s)
    return out


def _sketch(sets: list[np.ndarray], coords: int) -> np.ndarray:
    """16-bit minwise tokens, one row per non-empty set.

    Each round throws every shingle into one of the coordinates; a coordinate keeps the least hash of the first round that
    reached it, so a set costs some multiple of ``coords`` and not ``coords`` times its size. Two sets agree in a coordinate with
    the probability of their similarity. Coordinates still empty after ``ROUNDS`` take the least of their own hash.
    """
    if not sets:
        return np.zeros((0, coords), np.uint16)
    sizes = np.array([len(s) for s in sets])
    flat = np.concatenate(sets)
    owner = np.repeat(np.arange(len(sets)), sizes)
    out = np.full((len(sets), coords), EMPTY)
    cells, thrown, base = out.reshape(-1), flat, owner * coords
    for turn in range(ROUNDS):
        h = mixed(thrown + np.uint64((turn + 1) * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF))
        at = base + ((h >> np.uint64(32)) * np.uint64(coords) >> np.uint64(32)).astype(np.int64)
        np.minimum.at(cells, at, (h & np.uint64(0xFFFFFFFF)) | np.uint64(turn << 32))
        if turn % 3 == 2:
            still = (out == EMPTY).any(axis=1)
            if not still.any():
                break
            stay = still[base // coords]
            thrown, base = thrown[stay], base[stay]
    row, col = np.nonzero(out == EMPTY)
    n, begin = sizes[row], np.r_[0, np.cumsum(sizes)][:-1][row]
    step = max(1, 1_000_000 // max(1, int(n.max(initial=1))))
    for a in range(0, len(row), step):
        k, first = n[a : a + step], np.r_[0, np.cumsum(n[a : a + step])][:-1]
        from_ = np.arange(k.sum()) + np.repeat(begin[a : a + step] - first, k)
        own = mixed(flat[from_] + mixed(np.repeat(col[a : a + step], k).astype(np.uint64) + np.uint64(77)))
        out[row[a : a + step], col[a : a + step]] = np.minimum.reduceat(own, first)
    return (mixed(out) & np.uint64(0xFFFF)).astype(np.uint16)


def picked(path: np.ndarray, threshold: float) -> tuple[np.ndarray, np.ndarray]:
    """For each node one or two coordinates (1/threshold on average); the second is -1 where there is one."""
    h = mixed(path)
    one = (h % np.uint64(COORDS)).astype(np.int64)
    two = (one + 1 + ((h >> np.uint64(16)) % np.uint64(COORDS - 1)).astype(np.int64)) % COORDS
    draw = (h >> np.uint64(40)).astype(np.float64) / (1 << 24)
    return one, np.where(draw < 1 / threshold - 1, two, -1)


def children(path: np.ndarray, sketch: np.ndarray, threshold: float) -> tuple[np.ndarray, np.ndarray]:
    """The rows (indices) and paths of the children of each (node, set)."""
    rows = np.arange(len(path))
    one, two = picked(path, threshold)
    at, coord = np.concatenate([rows, rows[two >= 0]]), np.concatenate([one, two[two >= 0]])
    token = sketch[at, coord].astype(np.uint64)
    return at, mixed(mixed(path[at] + np.uint64(0x51ED2701)) ^ (token << np.uint64(8)) ^ coord.astype(np.uint64) ^ np.uint64(1 << 40))


def _sums(sets: list[np.ndarray]) -> list[pa.Array]:
    """Two sums of shingle hashes of each set, by which equal sets meet."""
    return [pa.array([int(mixed(s ^ np.uint64(by)).sum(dtype=np.uint64).astype(np.int64)) for s in sets], pa.int64()) for by in (0, 0xA5A5A5A55A5A5A5A)]


def _documents(batches, width: int, coords: int):
    for batch, texts in pieces(batches, "text", CHUNK):
        sets = hashed_sets(texts, width)
        row = dict(zip([i for i, s in enumerate(sets) if len(s)], _sketch([s for s in sets if len(s)], coords)))
        yield pa.RecordBatch.from_arrays(
            [batch.column("doc_id"), batch.column("text_key"), pa.array([len(s) for s in sets], pa.int64()), *_sums(sets), pa.array([row[i].tobytes() if i in row else b"" for i in range(len(sets))], pa.binary())],
            ["doc_id", "text_key", "n", "s1", "s2", "sketch"],
        )


def _unpack(column) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.uint16).reshape(len(column), -1)


def _packed(sketch: np.ndarray) -> pa.Array:
    """The rows as a binary column."""
    ends = np.arange(len(sketch) + 1, dtype=np.int32) * np.int32(2 * sketch.shape[1])
    return pa.Array.from_buffers(pa.binary(), len(sketch), [None, pa.py_buffer(ends), pa.py_buffer(np.ascontiguousarray(sketch))])


NODE = "path long, id long, n long, sketch binary"
FOUND = f"kind int, other long, likeness double, {NODE}"
PAIR, NEAR, OPEN, WHOLE, DEEPER = range(5)


def _rooted(batches, trees: int, threshold: float):
    """Every set under each of its nodes at the first depth, with the tokens of the node's tree."""
    for batch in batches:
        for a in range(0, batch.num_rows, 5000):
            part = batch.slice(a, 5000)
            sketch = _unpack(part.column("sketch")).reshape(part.num_rows, trees, COORDS)
            at, tree = np.tile(np.arange(part.num_rows), trees), np.repeat(np.arange(trees), part.num_rows)
            path = mixed(tree.astype(np.uint64) + np.uint64(1))
            for _ in range(FIRST_DEPTH):
                rows, path = children(path, sketch[at, tree], threshold)
                at, tree = at[rows], tree[rows]
            take = pa.array(at)
            yield pa.RecordBatch.from_arrays([pa.array(path.view(np.int64)), part.column("id").take(take), part.column("n").take(take), _packed(sketch[at, tree])], ["path", "id", "n", "sketch"])


def _tiny_pairs(path, n, sketch, member, threshold: float, apart=None):
    """Pairs (i, j, likeness) of rows of one node that look near; ``member``: the rows to take, ``apart``: labels to differ."""
    found, rows = [], np.arange(len(path))
    for off in range(1, TINY):
        i = rows[: len(rows) - off]
        i = i[member[i] & (path[i] == path[i + off])]
        if not len(i):
            break
        j = i + off
        ok = np.minimum(n[i], n[j]) >= threshold * np.maximum(n[i], n[j]) - 1e-9
        if apart is not None:
            ok &= apart[i] != apart[j]
        i, j = i[ok], j[ok]
        like = np.zeros(len(i))
        for a in range(0, len(i), 100_000):
            like[a : a + 100_000] = (sketch[i[a : a + 100_000]] == sketch[j[a : a + 100_000]]).mean(axis=1)
        close = like >= loose(threshold)
        found.append((i[close], j[close], like[close]))
    return tuple(np.concatenate([f[k] for f in found]) if found else np.zeros(0, np.int64 if k < 2 else float) for k in range(3))


def _strips(n, sketch, threshold: float, rows):
    """For strips of ``rows`` of one node: those rows and their agreeing tokens with every row of the node, 0 where a pair can't
    link."""
    tokens, m = np.ascontiguousarray(sketch.T), len(n)
    step = max(1, 1_000_000 // m)
    for a in range(0, len(rows), step):
        own = rows[a : a + step]
        like = np.zeros((len(own), m), np.uint8)
        for t in tokens:
            like += t[own, None] == t[None, :]
        like[np.minimum(n[own, None], n) < threshold * np.maximum(n[own, None], n) - 1e-9] = 0
        like[np.arange(len(own)), own] = 0
        like[like < math.ceil(loose(threshold) * COORDS)] = 0
        yield own, like


def _made(kind, other, likeness, path, ids, n, sketch=None) -> pa.RecordBatch:
    k = len(ids)
    return pa.RecordBatch.from_arrays(
        [pa.array(np.full(k, kind, np.int32)), pa.nulls(k, pa.int64()) if other is None else pa.array(other), pa.nulls(k, pa.float64()) if likeness is None else pa.array(likeness),
         pa.array(path), pa.array(ids), pa.array(n), pa.nulls(k, pa.binary()) if sketch is None else _packed(sketch)],
        ["kind", "other", "likeness", "path", "id", "n", "sketch"],
    )


def _gather(batches, threshold: float, last: bool, limit: int):
    """What each node finds: all near pairs of thin nodes (PAIR); of dense ones the nearest set of each set (NEAR) and the sets
    that have one (OPEN); of large ones the sets under their children (DEEPER) or, at the last level, all of them (WHOLE)."""
    for node, long_run in runs(batches, ["path", "part"], 20_000, limit):
        path, ids, n = (node.column(c).to_numpy() for c in ("path", "id", "n"))
        sketch = _unpack(node.column("sketch"))
        starts = starts_of(path, node.column("part").to_numpy())
        sizes = np.diff(np.r_[starts, len(path)])
        large = long_run | (node.column("part").to_numpy()[starts] > 0)
        tiny = np.repeat(sizes <= TINY, sizes)
        i, j, like = _tiny_pairs(path, n, sketch, tiny, threshold)
        run = np.repeat(np.arange(len(starts)), sizes)
        linked = np.bincount(np.unique(np.r_[i, j]) if len(i) else np.zeros(0, np.int64), minlength=len(path)) > 0
        thin = np.bincount(run[i], minlength=len(starts)) <= np.bincount(run[linked], minlength=len(starts))
        thin &= ~large
        some = thin[run[i]]
        if some.any():
            yield _made(PAIR, ids[j[some]], like[some], path[i[some]], ids[i[some]], n[i[some]])
        me, other, alike = np.r_[i[~some], j[~some]], np.r_[j[~some], i[~some]], np.r_[like[~some], like[~some]]
        order = np.lexsort((other, -alike, me))
        me, other, alike = me[order], other[order], alike[order]
        lead = starts_of(me)
        near, open_ = [(me[lead], other[lead], alike[lead])], [me[lead][~large[run[me[lead]]]]]
        for s, m, big in zip(starts[sizes > TINY], sizes[sizes > TINY], large[sizes > TINY]):
            for own, strip in _strips(n[s : s + m], sketch[s : s + m], threshold, np.arange(m)):
                best = strip.argmax(axis=1)
                top = strip[np.arange(len(strip)), best]
                has = np.flatnonzero(top)
                near.append((s + own[has], s + best[has], top[has] / COORDS))
                if not big:
                    open_.append(s + own[has])
        me, other, alike = (np.concatenate([f[k] for f in near]) for k in range(3))
        if len(me):
            yield _made(NEAR, ids[other], alike, path[me], ids[me], n[me])
        back = np.concatenate(open_).astype(np.int64)
        if len(back):
            yield _made(OPEN, None, None, path[back], ids[back], n[back], sketch[back])
        whole = np.flatnonzero(large[run])
        if len(whole) and last:
            yield _made(WHOLE, None, None, path[whole], ids[whole], n[whole])
        elif len(whole):
            at, below = children(path[whole].view(np.uint64), sketch[whole], threshold)
            at = whole[at]
            yield _made(DEEPER, None, None, below.view(np.int64), ids[at], n[at], sketch[at])


def _requests(batches, threshold: float):
    """For each set of an open node the homes of the sets it looks near to and shares no class with. Of two classes the one
    with fewer sets in the node asks."""
    for node, _ in runs(batches, ["path"], 20_000, 4 * LIMIT):
        path, ids, n, label, home = (node.column(c).to_numpy() for c in ("path", "id", "n", "class", "home"))
        sketch = _unpack(node.column("sketch"))
        starts = starts_of(path)
        sizes = np.diff(np.r_[starts, len(path)])
        run = np.repeat(np.arange(len(starts)), sizes)
        order = np.lexsort((label, run))
        first = starts_of(run[order], label[order])
        weight = np.empty(len(path), np.int64)  # sets of the class in the node
        weight[order] = np.repeat(np.diff(np.r_[first, len(path)]), np.diff(np.r_[first, len(path)]))
        i, j, _ = _tiny_pairs(path, n, sketch, np.repeat(sizes <= TINY, sizes), threshold, label)
        asks = (weight[i] < weight[j]) | (weight[i] == weight[j]) & (label[i] > label[j])
        sent = [(ids[np.where(asks, i, j)], home[np.where(asks, j, i)])]
        for s, m in zip(starts[sizes > TINY], sizes[sizes > TINY]):
            w, kind, to = weight[s : s + m], label[s : s + m], home[s : s + m]
            homes, which = np.unique(to, return_inverse=True)
            holds = np.zeros((m, len(homes)), np.float32)
            holds[np.arange(m), which] = 1
            top = kind[w == w.max()].min()  # the class that never asks
            for own, strip in _strips(n[s : s + m], sketch[s : s + m], threshold, np.flatnonzero(kind != top)):
                asks = (w[own, None] < w) | (w[own, None] == w) & (kind[own, None] > kind)
                row, at = np.nonzero((asks & (strip > 0) & (kind[own, None] != kind)).astype(np.float32) @ holds)
                sent.append((ids[s + own[row]], homes[at]))
        asker, to = (np.concatenate([x[k] for x in sent]) for k in range(2))
        order = np.lexsort((to, asker))
        asker, to = asker[order], to[order]
        lead = starts_of(asker, to)
        asker, to = asker[lead], to[lead]
        first = starts_of(asker)
        if len(first):  # a row for each set, with its homes
            yield pa.RecordBatch.from_arrays([pa.array(asker[first]), pa.ListArray.from_arrays(pa.array(np.r_[first, len(to)], pa.int32()), pa.array(to))], ["id", "homes"])


def _hashed(batches, width: int):
    """The hashed sets of ``id, text``."""
    for batch, texts in pieces(batches, "text", CHUNK):
        yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array([s.tobytes() for s in hashed_sets(texts, width)], pa.binary())], ["id", "held"])


def _met(batches, percent: int):
    """Links (a, b) between a block's sets and those sent to it, sorted by block with the block's own sets first; one link at
    most for each two classes."""
    at = None
    for batch in batches:
        for a in range(0, batch.num_rows, 64):
            part = batch.slice(a, 64)
            links = []
            for block, asks, id_, label, held in zip(*(part.column(c).to_pylist() for c in ("block", "asks", "id", "class", "held"))):
                s = np.frombuffer(held, np.uint64)
                if block != at:
                    at, own, index, known = block, [], None, {}
                if not asks:
                    own.append((id_, label, s))
                    continue
                if index is None:
                    sizes = np.array([len(x) for _, _, x in own])
                    flat = np.concatenate([x for _, _, x in own])
                    order = np.argsort(flat, kind="stable")
                    flat, holder = flat[order], np.repeat(np.arange(len(own)), sizes)[order]
                    first = starts_of(flat)
                    index = flat[first], first, np.r_[first[1:], len(flat)], holder
                    names, labels = np.array([x for x, _, _ in own]), np.array([x for _, x, _ in own])
                tokens, first, end, holder = index
                spot = np.minimum(np.searchsorted(tokens, s), len(tokens) - 1)
                spot = spot[tokens[spot] == s]
                k = end[spot] - first[spot]
                reach = np.repeat(first[spot] - np.r_[0, np.cumsum(k)][:-1], k) + np.arange(k.sum())
                both = np.bincount(holder[reach], minlength=len(own))
                hit = np.flatnonzero((100 * both >= percent * (len(s) + sizes - both)) & (labels != label))
                for h in hit[np.unique(labels[hit], return_index=True)[1]]:
                    x, y = _root(known, label), _root(known, int(labels[h]))
                    if x != y:
                        known[x] = y
                        links.append((min(id_, int(names[h])), max(id_, int(names[h]))))
            if links:
                yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in links], pa.int64()) for k in (0, 1)], ["a", "b"])


def _root(known: dict, x: int) -> int:
    while x in known:
        x = known[x]
    return x


def _confirm(batches, width: int, percent: int):
    last, held = None, set()
    for batch in batches:
        keep = []
        for at in range(0, batch.num_rows, 256):  # few texts as Python strings at a time
            part = batch.slice(at, 256)
            for i, (a, ta, tb) in enumerate(zip(*(part.column(c).to_pylist() for c in ("a", "ta", "tb"))), at):
                if a != last:
                    last, held = a, shingles(ta, width)
                other = shingles(tb, width)
                both = len(held & other)
                if 100 * both >= percent * (len(held) + len(other) - both):
                    keep.append(i)
        yield pa.RecordBatch.from_arrays([batch.column(c).take(pa.array(keep, pa.int64())) for c in ("a", "b")], ["a", "b"])


def few(df: DataFrame) -> DataFrame:
    """The rows, to be broadcast where they are few: some 16 bytes a row, a checked bound."""
    return F.broadcast(df) if df.count() <= SMALL else df


def confirmed(pairs: DataFrame, texts: Texts, width: int, percent: int) -> DataFrame:
    """The pairs (a, b) whose full sets reach the threshold."""
    sides = [pairs.select(F.col(c).alias("id")).distinct() for c in ("a", "b")]  # each side's repeats go before they meet
    own = written(texts(sides[0].union(sides[1]).distinct()), "texts")
    left, right = own.select(F.col("id").alias("a"), F.col("text").alias("ta")), own.select(F.col("id").alias("b"), F.col("text").alias("tb"))
    met = pairs.select("a", "b").join(left, "a").join(right, "b").sortWithinPartitions("a")
    return written(met.mapInArrow(lambda x: _confirm(x, width, percent), "a long, b long"), "links")


def components(links: DataFrame) -> DataFrame:
    """``id, class``: the smallest id reachable over ``links(a, b)``, for every id in them.

    Labels pass along links and then jump to the label's own label until nothing moves; each round is written to
    the shared folder.
    """
    both = links.select("a", "b").union(links.select(F.col("b"), F.col("a")))
    edges = written(both.distinct(), "links")
    labels = written(edges.groupBy(F.col("a").alias("id")).agg(F.least(F.min("b"), F.first("a")).alias("class")), "classes")
    while True:
        heard = edges.join(labels.select(F.col("id").alias("b"), "class"), "b").groupBy(F.col("a").alias("id")).agg(F.min("class").alias("heard"))
        lower = labels.join(heard, "id").select("id", F.least("class", "heard").alias("low"), F.col("class").alias("old"))
        lower = written(lower, "heard")
        jump = lower.select(F.col("id").alias("low"), F.col("low").alias("next"))
        moved = written(lower.join(jump, "low", "left").select("id", F.least("low", "next").alias("class"), "old"), "classes")
        labels = moved.select("id", "class")
        if not moved.where("class != old").limit(1).count():
            return labels


def _dealt(nodes: DataFrame, limit: int) -> DataFrame:
    """The nodes' rows, each node in one place; what a sample takes for large nodes is dealt out in parts. The sample
    only plans: a node that it misses is cut into parts where it is read."""
    seen = nodes.where(F.pmod(F.xxhash64("id"), F.lit(SAMPLE)) == 0).groupBy("path").agg((F.count("*") * SAMPLE / limit).cast("int").alias("parts")).where("parts > 1")
    seen = written(seen, "large")
    known = nodes.withColumn("part", F.lit(0))
    if seen.limit(1).count():
        known = nodes.join(few(seen), "path", "left").withColumn("part", F.when(F.col("parts") > 1, 1 + F.pmod(F.xxhash64("id"), F.col("parts"))).otherwise(0).cast("int")).drop("parts")
    return known.repartition("path", "part").sortWithinPartitions("path", "part", "id")


def _candidates(firsts: DataFrame, trees: int, threshold: float, limit: int, deepest: int) -> DataFrame:
    """What the nodes of all levels find (``FOUND``)."""
    nodes = firsts.select("id", "n", "sketch").mapInArrow(lambda b: _rooted(b, trees, threshold), NODE)
    found = None
    for depth in range(FIRST_DEPTH, deepest + 1):
        out = written(_dealt(nodes, limit).mapInArrow(lambda b, last=depth == deepest: _gather(b, threshold, last, limit), FOUND), "nodes")
        found = out if found is None else found.unionByName(out)
        nodes = out.where(F.col("kind") == DEEPER).select("path", "id", "n", "sketch")
        if depth == deepest or not nodes.limit(1).count():
            return found.where(F.col("kind") != DEEPER)


def _settled(found: DataFrame, labels: DataFrame, texts: Texts, width: int, percent: int) -> DataFrame:
    """Links between the classes of ``labels`` that dense and last nodes suggest, found on whole hashed sets. The home of a set
    is the largest class in one of its nodes, its own or another, or else a node: what lies close together shares few homes."""
    rows = found.where(F.col("kind").isin(OPEN, WHOLE))
    placed = written(rows.select("path", "id").join(few(labels), "id", "left"), "placed")
    crowd = placed.where("class is not null").groupBy("path", "class").count().groupBy("path").agg(F.max(F.struct("count", "class")).alias("top"))
    beside = placed.join(crowd, "path", "left").groupBy("id").agg(F.first("class").alias("class"), F.max("top")["class"].alias("beside"), F.min("path").alias("path"))
    homes = written(beside.select("id", F.coalesce("class", "id").alias("class"), F.coalesce("beside", "path").alias("home")), "homes")
    where = few(homes)
    known = rows.where(F.col("kind") == OPEN).select("path", "id", "n", "sketch").join(where, "id")
    asked = known.repartition("path").sortWithinPartitions("path", "id").mapInArrow(lambda b: _requests(b, percent / 100), "id long, homes array<long>")
    asked = asked.groupBy("id").agg(F.array_distinct(F.flatten(F.collect_list("homes"))).alias("homes")).select("id", F.explode("homes").alias("home"))
    whole = written(rows.where(F.col("kind") == WHOLE).select("path", "id").join(where, "id"), "whole")
    if whole.limit(1).count():
        top = whole.groupBy("path", "class").count().groupBy("path").agg(F.max_by("class", F.struct("count", "class")).alias("top"))
        outer = whole.join(top, "path").where("class != top").select("path", "id").distinct()
        asked = asked.union(outer.join(whole.select("path", "home").distinct(), "path").select("id", "home"))
    asked = written(asked.distinct(), "asked")
    if not asked.limit(1).count():
        return asked.select(F.col("id").alias("a"), F.col("id").alias("b"))
    wide = written(homes.join(few(asked.select("home").distinct()), "home", "left_semi").groupBy("home").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("parts")), "wide")
    block = F.xxhash64("home", "part").alias("block")
    members = homes.join(few(wide), "home").withColumn("part", F.pmod(F.xxhash64("id"), F.col("parts")).cast("int")).select("id", block)
    asked = asked.join(few(wide), "home").select("id", "home", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part")).select("id", block)
    held = texts(members.select("id").union(asked.select("id")).distinct()).mapInArrow(lambda b: _hashed(b, width), "id long, held binary")
    held = written(held.join(few(homes.select("id", "class")), "id"), "held")
    sent = members.withColumn("asks", F.lit(False)).union(asked.select("id", "block").withColumn("asks", F.lit(True))).join(held, "id")
    links = sent.select("block", "asks", "id", "class", "held").repartition("block").sortWithinPartitions("block", "asks", "id")
    return written(links.mapInArrow(lambda b: _met(b, percent), "a long, b long").distinct(), "pairs")


def classes(docs: DataFrame, width: int = 2, percent: int = 80, trees: int | None = None, limit: int = LIMIT, deepest: int = DEEPEST) -> DataFrame:
    """``doc_id, text_key, n_shingles, component_id, first`` of every row. ``trees``: as many as ``trees_for`` says where no number
    is given; ``limit`` and ``deepest``: sets of a node that are compared exhaustively, and the last level. ``first``: true for
    the rows of a class with its least id and, of these, the least ``text_key`` (a hash of the text), and for empty sets."""
    threshold = percent / 100
    trees = trees or trees_for(threshold)
    given = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    keyed = given.withColumn("text_key", F.xxhash64("text"))
    rows = written(keyed.mapInArrow(lambda b: _documents(b, width, trees * COORDS), "doc_id long, text_key long, n long, s1 long, s2 long, sketch binary"), "sets")
    # the sketch is a function of the set, so any row's serves; a set's number holds from here on, as it is written
    firsts = rows.where("n > 0").groupBy("s1", "s2", "n").agg(F.min(F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "text_key")).alias("least"), F.first("sketch").alias("sketch"))
    firsts = written(firsts.withColumn("id", F.monotonically_increasing_id()), "firsts")
    texts = _texts(given, rows, firsts.drop("sketch"), width)
    found = _candidates(firsts, trees, threshold, limit, deepest)
    near = found.where(F.col("kind") == NEAR).select("id", "other", "likeness")
    pairs = found.where(F.col("kind") == PAIR).select("id", "other", "likeness")
    both = near.union(pairs).union(pairs.select("other", "id", "likeness"))
    best = both.groupBy("id").agg(F.slice(F.array_sort(F.collect_set(F.struct(-F.col("likeness"), "other"))), 1, NEAREST).alias("best"))
    first = best.select("id", F.explode("best.other").alias("other")).select(F.least("id", "other").alias("a"), F.greatest("id", "other").alias("b")).distinct()
    first = written(first, "pairs")
    links = confirmed(first, texts, width, percent)
    labels = components(links)
    at = few(labels)
    left = pairs.select(F.least("id", "other").alias("a"), F.greatest("id", "other").alias("b")).distinct().join(few(first), ["a", "b"], "left_anti")
    for c in ("a", "b"):
        left = left.join(at.select(F.col("id").alias(c), F.col("class").alias(f"{c}_class")), c, "left")
    left = left.where(F.coalesce("a_class", "a") != F.coalesce("b_class", "b")).select("a", "b")
    more = written(left.union(_settled(found, labels, texts, width, percent)).distinct(), "pairs")
    if more.limit(1).count():
        labels = components(links.union(confirmed(more, texts, width, percent)))
    named = firsts.drop("sketch").join(few(labels), "id", "left").withColumn("class", F.coalesce("class", "id"))
    named = written(named, "named")
    least = named.groupBy("class").agg(F.min("least").alias("top"))
    named = named.join(least, "class").select("s1", "s2", "n", "top")
    joined = rows.drop("sketch").join(named, ["s1", "s2", "n"], "left")
    own = F.col("top").isNull()
    first = own | F.col("doc_id").eqNullSafe(F.col("top.doc_id")) & (F.col("text_key") == F.col("top.text_key"))
    return joined.select("doc_id", "text_key", F.col("n").alias("n_shingles"), F.when(own, F.col("doc_id")).otherwise(F.col("top.doc_id")).alias("component_id"), first.alias("first"))


def drop_later(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """The documents without those that are near an earlier one: of each class the rows with the least id (null last) and, of
    these, the least hash of the text stay, so rows that repeat both are one document. All columns pass through."""
    gone = classes(docs, width, percent).where(~F.col("first")).select(F.col("doc_id").alias("gone_id"), F.col("text_key").alias("gone_key")).distinct()
    gone = few(written(gone, "near"))
    return docs.join(gone, docs["doc_id"].eqNullSafe(gone["gone_id"]) & (F.xxhash64(docs["text"]) == gone["gone_key"]), "left_anti")


def _texts(given: DataFrame, rows: DataFrame, firsts: DataFrame, width: int) -> Texts:
    """What looks up ``id, text``, one text for each of the set numbers in ``id``. Where document ids repeat or are null, the
    texts are met by their sets again."""
    some = given.where("text is not null")
    unique = rows.select("doc_id").distinct().count() == rows.count() and not rows.where("doc_id is null").limit(1).count()

    def keyed(batches):
        for batch, texts in pieces(batches, "text", CHUNK):
            yield pa.RecordBatch.from_arrays([*_sums(hashed_sets(texts, width)), batch.column("text")], ["s1", "s2", "text"])

    def found(ids: DataFrame) -> DataFrame:
        want = written(firsts.join(few(written(ids, "ids")), "id", "left_semi"), "ids")
        if unique:
            return some.join(few(want.select(F.col("least.doc_id").alias("doc_id"), "id")), "doc_id").select("id", "text")
        met = some.select("text").mapInArrow(keyed, "s1 long, s2 long, text string").join(few(want.select("id", "s1", "s2")), ["s1", "s2"])
        return met.groupBy("id").agg(F.min("text").alias("text"))

    return found
