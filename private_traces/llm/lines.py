"""Line dedup by a deletion-neighbourhood join, with DataFrame functions alone.

A line (split at ``\\n``, trimmed) is removed if an earlier line (by doc_id, then place in the text) equals it, or,
for lines of ``least_chars`` characters or more, differs by one character inserted, deleted or substituted
(code points). What is earlier is judged on the input, so a removed line still counts as the earlier one.

Steps. (1) Exact copies: one row per distinct line with its first place; partial sums keep a line that fills the
corpus to one row per task. (2) Which lines can have a partner at all: of two lines one edit apart, the first or the
last half of the shorter one stands unchanged at the same end of the other; lines sharing no such half leave here,
without loss; of the rest, only those of ``FINE`` segments stay without which two lines are equal. (3) Every variant of a
line with at most one character of such a segment deleted becomes a hashed key. Lines that share a key at the same
place are one substitution apart, and a line that equals another's variant is one deletion
away; the earliest line of each key is joined to its later ones, never all pairs. (4) Each such pair is confirmed by
edit distance. (5) The first places that remain are regrouped by document and the text is put together from them.

Defined results: blank lines are kept and never compared; a null text has no lines and stays null; equal rows
(same id and text) are one document and all of them keep the same lines; an id that is null comes first. Further
columns pass through.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import aside, let, written

BLANK = "\x20\t\n\x0b\x0c\r"
SMALL = 500_000
FINE = 16


def _trimmed(line: Column) -> Column:
    return F.trim(line, F.lit(BLANK))


def _hash(*of: Column | str) -> list[Column]:
    """Two independent 64-bit hashes."""
    return [F.xxhash64(F.lit(1), *of), F.xxhash64(F.lit(2), *of)]


def lines_of(docs: DataFrame) -> DataFrame:
    """``doc_id, row, n, line``: every non-blank trimmed line; ``row`` tells texts under one id apart."""
    trimmed = F.transform(F.split("text", "\n", -1), _trimmed)
    cut = docs.where("text is not null").select("doc_id", F.xxhash64("text").alias("row"), F.posexplode(trimmed).alias("n", "line"))
    return cut.where("line != ''")


def _halves(line: Column, n: Column) -> Column:
    """Keys of the halves this line shares with any line one edit away: as the shorter or equal one of the two (cut at
    n div 2) and as the longer one (cut where a line one shorter is cut)."""
    first, less = (n / 2).cast("int"), ((n - 1) / 2).cast("int")
    return F.array(
        F.xxhash64(F.lit("a"), n, F.substring(line, F.lit(1), first)),
        F.xxhash64(F.lit("z"), n, F.substring(line, first + 1, n)),
        F.xxhash64(F.lit("a"), n - 1, F.substring(line, F.lit(1), less)),
        F.xxhash64(F.lit("z"), n - 1, F.substring(line, less + 2, n)),
    )


def first_places(docs: DataFrame, least_chars: int) -> DataFrame:
    """One row per distinct line: its hashes ``h1, h2``, the keys of its halves (``keys``; null below ``least_chars``) and
    where it stands first, as ``at = (doc_id, n, row)``."""
    n = F.length("line")
    keyed = lines_of(docs).select(
        *[c.alias(a) for c, a in zip(_hash("line"), ("h1", "h2"))],
        F.struct("doc_id", "n", "row").alias("at"),
        F.when(n >= least_chars, _halves(F.col("line"), n)).alias("keys"),
    )
    return keyed.groupBy("h1", "h2").agg(F.min("at").alias("at"), F.first("keys").alias("keys"))


def _shared(each: DataFrame) -> DataFrame:
    """The rows of ``each(h1, h2, key, ...)`` whose key another line has too."""
    keys = each.groupBy("key").agg(F.min("h1").alias("least"), F.max("h1").alias("most")).where("least != most").select("key")
    return each.join(keys, "key", "left_semi")


def partners_possible(firsts: DataFrame) -> DataFrame:
    """``h1, h2`` of distinct lines that share a half with another one."""
    return _shared(firsts.where("keys is not null").select("h1", "h2", F.explode("keys").alias("key"))).select("h1", "h2").distinct()


def _edge(length: Column, j: Column) -> Column:
    return F.floor(length * j / FINE).cast("int")


def segments_shared(candidates: DataFrame) -> DataFrame:
    """``h1, h2, length, j``: segments without which the line equals another one without its own; ``length`` is that of the
    shorter or equal line of the pair, by which both are cut."""

    def keys(line: Column, n: Column, length: Column) -> Column:
        one = lambda j: F.struct(length.alias("length"), j.cast("int").alias("j"), F.xxhash64(j, length, F.substring(line, F.lit(1), _edge(length, j)), F.lit("|"), F.substring(line, n - length + _edge(length, j + 1) + 1, n)).alias("key"))
        return F.transform(F.sequence(F.lit(0), F.lit(FINE - 1)), one)

    both = let(F.struct("line", F.length("line").alias("n")), lambda x: F.concat(let(x["n"], lambda n: keys(x["line"], n, n)), let(x["n"] - 1, lambda less: keys(x["line"], less + 1, less))))
    each = written(candidates.select("h1", "h2", F.inline(both)), "segments")
    return _shared(each).select("h1", "h2", "length", "j").distinct()


def variants(line: Column, n: Column, length: Column, j: Column) -> Column:
    """``(key, place)`` of the line itself (place -1) and of each deletion inside segment j."""
    gone = F.transform(
        F.sequence(_edge(length, j), _edge(length, j + 1) - 1 + n - length),
        lambda i: F.struct(F.xxhash64(F.concat(F.substring(line, F.lit(1), i), F.substring(line, i + 2, n))).alias("key"), i.cast("int").alias("place")),
    )
    return F.concat(F.array(F.struct(F.xxhash64(line).alias("key"), F.lit(-1).alias("place"))), gone)


def edited(candidates: DataFrame, segments: DataFrame) -> DataFrame:
    """``h1, h2`` of lines with a confirmed earlier line one edit away. ``candidates``: h1, h2, at, line (distinct lines)."""
    cut = candidates.join(segments, ["h1", "h2"]).withColumn("c", F.length("line"))
    inside = F.col("c") - F.col("length") + _edge(F.col("length"), F.col("j") + 1) > _edge(F.col("length"), F.col("j"))
    one = cut.where(inside).select("h1", "h2", "at", F.inline(let(F.struct("line", "c", "length", "j"), lambda x: variants(x["line"], x["c"], x["length"], x["j"]))))
    exploded = written(one.distinct(), "variants")
    who = F.struct("at", "h1", "h2")
    # equal variants with the same place are one substitution apart
    same_place = exploded.where("place >= 0").groupBy("key", "place").agg(F.min(who).alias("first"), F.count("*").alias("rows")).where("rows > 1").select("key", "place", "first")
    # a line that equals a variant of another is one deletion away: the earliest of either kind for those of the other
    by_key = exploded.groupBy("key").agg(F.min(F.when(F.col("place") < 0, who)).alias("whole"), F.min(F.when(F.col("place") >= 0, who)).alias("cut")).where("whole is not null and cut is not null")
    deletion = by_key.select("key", F.inline(F.array(F.struct(F.lit(False).alias("is_whole"), F.col("whole").alias("first")), F.struct(F.lit(True).alias("is_whole"), F.col("cut").alias("first")))))
    met = exploded.join(same_place, ["key", "place"]).select("h1", "h2", "at", "first").unionByName(
        exploded.withColumn("is_whole", F.col("place") < 0).join(deletion, ["key", "is_whole"]).select("h1", "h2", "at", "first")
    )
    pairs = met.where(F.col("first.at") < F.col("at")).select("h1", "h2", F.col("first.h1").alias("e1"), F.col("first.h2").alias("e2")).distinct()
    text = candidates.select("h1", "h2", "line")
    both = pairs.join(text, ["h1", "h2"]).join(text.select(F.col("h1").alias("e1"), F.col("h2").alias("e2"), F.col("line").alias("earlier")), ["e1", "e2"])
    return both.where(F.levenshtein("line", "earlier", 1).between(0, 1)).select("h1", "h2").distinct()


def kept_places(docs: DataFrame, least_chars: int = 16) -> DataFrame:
    """``doc_id, row, kept`` (array of line numbers) of every document that keeps a non-blank line."""
    firsts = written(first_places(docs, least_chars), "lines")
    possible = written(partners_possible(firsts), "halves")
    if possible.count() <= SMALL:  # 16 bytes a row: a checked bound for a broadcast
        possible = F.broadcast(possible)
    chosen = firsts.join(possible, ["h1", "h2"], "left_semi").select("h1", "h2", "at")
    places = chosen.select("h1", "h2", "at", "at.doc_id", "at.n", "at.row")
    few = places.count() <= SMALL  # some 60 bytes a row
    at_line, sought = lines_of(docs), F.broadcast(places) if few else places
    found = at_line.join(sought, at_line.doc_id.eqNullSafe(sought.doc_id) & (at_line.n == sought.n) & (at_line.row == sought.row))
    candidates = written(found.select(sought.h1, sought.h2, sought["at"], at_line.line).dropDuplicates(["h1", "h2"]), "candidates")
    gone = written(edited(candidates, segments_shared(candidates)), "gone")
    stay = firsts.select("h1", "h2", "at").join(gone, ["h1", "h2"], "left_anti")
    return stay.groupBy("at.doc_id", "at.row").agg(F.collect_list("at.n").alias("kept"))


def dedup(docs: DataFrame, least_chars: int = 16) -> DataFrame:
    """``docs`` with ``text`` cut down to the lines that stay, and ``n_lines``, ``n_removed`` (non-blank lines) in place of any
    columns of those names; all other columns pass through, whatever their names."""
    kept = kept_places(docs, least_chars)
    own, back = aside(docs.drop("n_lines", "n_removed"), ["doc_id", "text"])
    left = own.withColumn("__row", F.xxhash64("text"))
    met = left.join(kept, left.doc_id.eqNullSafe(kept.doc_id) & (left["__row"] == kept.row), "left").select(left["*"], kept.kept.alias("__kept"))
    blank = lambda x: _trimmed(x) == ""
    cut = F.split("text", "\n", -1)

    def flagged(s: Column) -> Column:
        """Line i is 2 i + 1 in ``s``, and has 2 i before it where it is kept."""
        marked = F.transform(s, lambda x, k: F.when(x % 2 == 1, F.coalesce(F.get(s, k - 1) == x - 1, F.lit(False))))
        return F.filter(marked, lambda x: x.isNotNull())

    merged = F.sort_array(F.concat(F.transform(F.sequence(F.lit(0), F.size(cut) - 1), lambda i: i * 2 + 1), F.transform(F.coalesce("__kept", F.array().cast("array<int>")), lambda i: i * 2)))
    done = met.withColumn("__lines", cut).withColumn("__flags", F.when(F.col("text").isNotNull(), let(merged, flagged)))
    done = done.withColumn("__out", let(F.col("__flags"), lambda keep: F.transform("__lines", lambda x, i: F.when(blank(x) | F.get(keep, i), x))))
    result = done.withColumns({
        "text": F.when(F.col("text").isNotNull(), F.array_join(F.array_compact("__out"), "\n")),
        "n_lines": F.coalesce(F.size(F.filter("__lines", lambda x: ~blank(x))), F.lit(0)),
        "n_removed": F.coalesce(F.size("__lines") - F.size(F.array_compact("__out")), F.lit(0)),
    })
    return back(result, "n_lines", "n_removed")
