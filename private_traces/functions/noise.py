"""Keyed noise: every draw is a function of (seed, stage, key), so a recomputed partition repeats it."""

from __future__ import annotations

import hashlib
import math

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def keyed_uniform(seed: int | Column, stage: str, *key: Column | str, source: str = "md5") -> Column:
    """A number in (0, 1) from the text ``seed|stage|key``; ``xxhash64`` is the cheaper source without an oracle."""
    lead = F.lit(str(seed)) if isinstance(seed, int) else seed.cast("string")
    text = F.concat_ws("|", lead, F.lit(stage), *[(F.col(k) if isinstance(k, str) else k).cast("string") for k in key])
    if source == "xxhash64":
        return (F.shiftrightunsigned(F.xxhash64(text), 16) + 0.5) / F.lit(float(1 << 48))
    return (F.conv(F.substring(F.md5(text), 1, 12), 16, 10).cast("bigint") + 0.5) / F.lit(float(1 << 48))


SINES = [int(abs(math.sin(i + 1)) * 2**32) for i in range(64)]
TURNS = ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21))


def _md5_lead(words: np.ndarray) -> np.ndarray:
    """The first 48 bits of the MD5 digests of padded messages, a column of 32-bit words each."""
    total = [np.full(words.shape[1], v, np.uint32) for v in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)]
    for block in range(0, len(words), 16):
        a, b, c, d = total
        for i in range(64):
            lap = i // 16
            mixed, word = ((b & c) | (~b & d), i) if lap == 0 else ((d & b) | (~d & c), 5 * i + 1) if lap == 1 else (b ^ c ^ d, 3 * i + 5) if lap == 2 else (c ^ (b | ~d), 7 * i)
            mixed += a
            mixed += words[block + word % 16]
            mixed += np.uint32(SINES[i])
            turn = TURNS[lap][i % 4]
            a, d, c, b = d, c, b, b + ((mixed << np.uint32(turn)) | (mixed >> np.uint32(32 - turn)))
        total = [x + y for x, y in zip(total, (a, b, c, d))]
    return total[0].byteswap().astype(np.uint64) << np.uint64(16) | (total[1] & np.uint32(0xFFFF)).astype(np.uint16).byteswap().astype(np.uint64)


def keyed_numbers(seed: int, stage: str, first: np.ndarray, second: np.ndarray, part: int = 16_384) -> np.ndarray:
    """``keyed_uniform`` of the source ``md5`` for many keys of two whole numbers from 0 on, in arrays."""
    lead, out = np.frombuffer(f"{seed}|{stage}|".encode(), np.uint8), np.empty(len(first))
    digits = lambda v: np.searchsorted(10 ** np.arange(1, 19), v, side="right") + 1
    long = digits(first) * 32 + digits(second)
    for kind in np.unique(long):
        one, two = divmod(int(kind), 32)
        size = len(lead) + one + 1 + two
        rows = np.flatnonzero(long == kind)
        for own in np.split(rows, range(part, len(rows), part)):
            text = np.zeros((len(own), (size + 8) // 64 * 64 + 64), np.uint8)
            text[:, : len(lead)] = lead
            for v, start, many in ((first[own], len(lead), one), (second[own], len(lead) + one + 1, two)):
                for k in range(many):
                    text[:, start + k] = 48 + v // 10 ** (many - 1 - k) % 10
            text[:, len(lead) + one] = ord("|")
            text[:, size] = 0x80
            text[:, -8:] = np.frombuffer((8 * size).to_bytes(8, "little"), np.uint8)
            out[own] = (_md5_lead(np.ascontiguousarray(text.view("<u4").T)) + 0.5) / float(1 << 48)
    return out


def laplace_of(u: Column, scale: Column | float) -> Column:
    """The Laplace draw of ``u`` by its inverse distribution."""
    b = F.lit(scale) if isinstance(scale, (int, float)) else scale
    return -b * F.signum(u - 0.5) * F.log(1 - 2 * F.abs(u - 0.5))


def laplace(scale: Column | float, seed: int | Column, stage: str, *key: Column | str, source: str = "md5") -> Column:
    return laplace_of(keyed_uniform(seed, stage, *key, source=source), scale)


def geometric(epsilon: float, seed: int, stage: str, *key: Column | str, source: str = "md5") -> Column:
    """Two-sided geometric noise with parameter exp(-epsilon): the difference of two one-sided draws, in integers."""
    one = lambda side: F.floor(F.log(keyed_uniform(seed, f"{stage}{side}", *key, source=source)) / F.lit(-float(epsilon)))
    return (one("+") - one("-")).cast("bigint")


def integer_noise(mechanism: str, epsilon: float, seed: int, stage: str, *key: Column | str, source: str = "md5") -> Column:
    """Noise for counts that one trace moves by 1: ``laplace``, or ``geometric``, which keeps them integers."""
    if mechanism == "geometric":
        return geometric(epsilon, seed, stage, *key, source=source).cast("double")
    return laplace(1 / epsilon, seed, stage, *key, source=source)


def densify(stats: DataFrame, domain: DataFrame, keys: list[str], **zero) -> DataFrame:
    """Every key of ``domain``, with 0 (or the given value) where ``stats`` has no row."""
    rest = [c for c in stats.columns if c not in keys]
    joined = domain.join(stats, keys, "left")
    return joined.select(*domain.columns, *[F.coalesce(c, F.lit(zero.get(c, 0.0))).alias(c) for c in rest])


def water_level(masses: Column, total: Column) -> Column:
    """The constant that, taken from every mass, leaves positive parts that sum to ``total``."""
    start = F.struct(F.lit(0).alias("k"), F.lit(0.0).alias("s"), F.lit(0.0).alias("level"))

    def step(acc: Column, m: Column) -> Column:
        level = (acc["s"] + m - total) / (acc["k"] + 1)
        return F.struct((acc["k"] + 1).alias("k"), (acc["s"] + m).alias("s"), F.when(m > level, level).otherwise(acc["level"]).alias("level"))

    return F.aggregate(F.sort_array(masses, asc=False), start, step, lambda acc: acc["level"])


def clean_up(noisy: DataFrame, mass: str, by: list[str], mode: str = "shift", threshold: float = 0.0, total: Column | None = None) -> DataFrame:
    """Non-negative masses: ``clip``; ``shift`` (one constant per group, so that the sum stays the noisy sum); or
    ``threshold``. Post-processing only. Groups are bounded by the lattice, not by the data."""
    if mode == "clip":
        return noisy.withColumn(mass, F.greatest(F.lit(0.0), F.col(mass)))
    if mode == "threshold":
        return noisy.withColumn(mass, F.when(F.col(mass) >= threshold, F.col(mass)).otherwise(0.0))
    if mode != "shift":
        raise ValueError(f"unknown clean-up: {mode}")
    want = F.greatest(F.lit(0.0), total if total is not None else F.aggregate("m", F.lit(0.0), lambda a, x: a + x))
    # the sum is bound outside the steps of the level, which would make it again for every mass
    level = F.get(F.transform(F.array(want), lambda t: F.when(t > 0, water_level(F.col("m"), t))), F.lit(0))
    level = noisy.groupBy(*by).agg(F.sort_array(F.collect_list(mass)).alias("m")).select(*by, level.alias("level"))
    joined = noisy.join(F.broadcast(level), by, "left") if by else noisy.crossJoin(F.broadcast(level))
    return joined.withColumn(mass, F.when(F.col("level").isNull(), 0.0).otherwise(F.greatest(F.lit(0.0), F.col(mass) - F.col("level")))).drop("level")


def to_probabilities(df: DataFrame, mass: str, by: list[str], name: str = "prob") -> DataFrame:
    """``mass`` divided by its sum per group (null where the sum is 0)."""
    return df.withColumn(name, F.try_divide(F.col(mass), F.sum(mass).over(Window.partitionBy(*by))) if by else F.try_divide(F.col(mass), F.sum(mass).over(Window.partitionBy(F.lit(0)))))


def sparse_noise(stats: DataFrame, size: int, key: str, mass: str, scale: float, threshold: float, seed: int, stage: str) -> DataFrame:
    """Noise for a domain of ``size`` keys of which few occur, without listing it: noise the keys that occur, draw how many
    empty keys would pass ``threshold`` (a binomial draw) and which, and give those a draw beyond it. Same law as dense noise
    followed by the threshold, which must not be negative."""
    if threshold < 0:
        raise ValueError("the threshold must not be negative")
    occurring = stats.select(key, (F.col(mass) + laplace(scale, seed, stage, key)).alias(mass)).where(F.col(mass) >= threshold)
    p = 0.5 * math.exp(-threshold / scale)
    spark = stats.sparkSession
    empty = size - stats.select(key).distinct().count()
    n = int(np.random.default_rng(int.from_bytes(hashlib.sha256(f"{seed}|{stage}-n".encode()).digest(), "big")).binomial(empty, p))
    if 4 * n > size:  # no longer sparse: every key, in a random order
        draws = spark.range(size).select(F.col("id").alias(key), keyed_uniform(seed, f"{stage}-k", "id").alias("turn"))
    else:  # the distinct keys of uniform draws are a random sample in a random order
        draws = spark.range(math.ceil((3 * n + 40) * size / max(1, empty))).select((F.floor(keyed_uniform(seed, f"{stage}-k", "id") * size)).cast("bigint").alias(key), F.col("id").alias("turn"))
    fresh = draws.groupBy(key).agg(F.min("turn").alias("turn")).join(stats.select(key), key, "left_anti").orderBy("turn").limit(n)
    beyond = fresh.select(key, (F.lit(threshold) - scale * F.log(keyed_uniform(seed, f"{stage}-m", key))).alias(mass))
    return occurring.unionByName(beyond)
