"""Quality rules: a learned decision list over text statistics, with DataFrame functions alone.

Sequential covering. The statistics of at most about ``most_examples`` labelled documents (a documented bound)
are cut into bins at their quantiles. A rule grows by adding the threshold condition with the largest information
gain, found from one histogram (statistic, bin, label) of the rows still covered; it is then cut back to the
prefix that does best on rows kept aside, and accepted if it is precise enough there. Covered rows leave and
the next rule is grown. The list becomes one ordered conditional expression over all documents.

Defined results: a null or empty text has no words, so all statistics are 0 and the base rule fails it; repeated
rows are judged each; without labelled rows, or without both labels, the list is empty and every verdict is keep.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import WORD, drawn_labels, let, written

BINS = 16
STATS = ["symbol_share", "upper_share", "digit_share", "bang_share", "dup_line_share", "repeat_share", "distinct_share", "mean_word", "words_per_line", "words"]


def repeated_words(words: Column) -> Column:
    """Words that lie in a 3-word window found twice or more in the text.

    Window hashes, each with its place in the low bits, are sorted as plain longs; equal neighbours with equal words are the
    repeated windows, and their sorted places give the words covered. A window whose neighbour has its hash and other words is
    looked up among all.
    """
    n = F.size(words)

    def places(w: Column) -> Column:
        bits = F.length(F.bin(F.size(w)))
        packed = F.transform(
            F.sequence(F.lit(0), F.size(w) - 3),
            lambda i: F.call_function("shiftleft", F.xxhash64(F.get(w, i), F.get(w, i + 1), F.get(w, i + 2)), bits).bitwiseOR(i.cast("bigint")),
        )

        def repeated(s: Column) -> Column:
            top = lambda x: F.call_function("shiftright", x, bits)
            low = F.call_function("shiftleft", F.lit(1).cast("bigint"), bits) - 1
            at = lambda x, k: F.get(w, x.bitwiseAND(low).cast("int") + k)
            words_equal = lambda x, y: (at(x, 0) == at(y, 0)) & (at(x, 1) == at(y, 1)) & (at(x, 2) == at(y, 2))
            hashed = lambda x, k: F.coalesce(top(F.get(s, k)) == top(x), F.lit(False))
            same = lambda x, k: hashed(x, k) & words_equal(x, F.get(s, k))
            place = lambda x: x.bitwiseAND(low)
            other = lambda x: F.exists(s, lambda y: (top(y) == top(x)) & (y != x) & words_equal(x, y))
            marked = F.transform(s, lambda x, k: F.when(same(x, k - 1) | same(x, k + 1), place(x)).when(hashed(x, k - 1) | hashed(x, k + 1), F.when(other(x), place(x))).otherwise(F.lit(-1).cast("bigint")))
            return F.filter(marked, lambda x: x >= 0)

        return let(F.sort_array(packed), repeated)

    start = F.struct(F.lit(-3).cast("bigint").alias("last"), F.lit(0).cast("bigint").alias("total"))
    step = lambda acc, x: F.struct(x.alias("last"), (acc["total"] + F.least(F.lit(3).cast("bigint"), x - acc["last"])).alias("total"))
    covered = F.aggregate(F.sort_array(let(words, places)), start, step, lambda acc: acc["total"])
    return F.when(n < 4, F.lit(0).cast("bigint")).otherwise(covered)


def statistics(docs: DataFrame) -> DataFrame:
    """``doc_id``, the base counts and the statistics that rules may use, per row."""
    text = F.coalesce("text", F.lit(""))
    cut = docs.select("doc_id", text.alias("t")).withColumn("w", F.regexp_extract_all("t", F.lit(WORD), F.lit(0)))
    lines = F.filter(F.split("t", "\n", -1), lambda x: x.rlike(WORD))
    counted = cut.select(
        "doc_id",
        F.size("w").cast("long").alias("n_words"),
        F.length(F.array_join("w", "")).cast("long").alias("word_chars"),
        F.regexp_count("t", F.lit(r"[#*$%&|<>]")).cast("long").alias("n_symbols"),
        let(lines, lambda x: F.array(F.size(x), F.size(F.array_distinct(x)))).alias("lines"),
        repeated_words(F.col("w")).alias("n_repeat_words"),
        F.size(F.array_distinct("w")).alias("n_distinct"),
        F.regexp_count("t", F.lit(r"\p{Lu}")).alias("n_upper"),
        F.regexp_count("t", F.lit(r"[0-9]")).alias("n_digits"),
        F.regexp_count("t", F.lit(r"!")).alias("n_bangs"),
    )
    share = lambda a, b: F.round(F.coalesce(F.try_divide(F.col(a), F.col(b) if isinstance(b, str) else b), F.lit(0.0)).cast("double"), 6)
    counted = counted.withColumns({"n_lines": F.col("lines")[0], "n_dup_lines": (F.col("lines")[0] - F.col("lines")[1]).cast("long")})
    return counted.select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words",
        share("n_symbols", "n_words").alias("symbol_share"), share("n_upper", "word_chars").alias("upper_share"),
        share("n_digits", "word_chars").alias("digit_share"), share("n_bangs", "n_words").alias("bang_share"),
        share("n_dup_lines", "n_lines").alias("dup_line_share"), share("n_repeat_words", "n_words").alias("repeat_share"),
        share("n_distinct", "n_words").alias("distinct_share"), share("word_chars", "n_words").alias("mean_word"),
        share("n_words", "n_lines").alias("words_per_line"), F.col("n_words").cast("double").alias("words"),
    )


@dataclass
class Rule:
    """A conjunction of ``(statistic, above, threshold)``, with what it covered when it was accepted."""

    conditions: list[tuple[str, bool, float]]
    rejected: int = 0
    kept: int = 0

    def column(self) -> Column:
        found = F.lit(True)
        for name, above, edge in self.conditions:
            found &= F.col(name) > edge if above else F.col(name) <= edge
        return found

    def __str__(self) -> str:
        return " and ".join(f"{n} {'>' if a else '<='} {e:g}" for n, a, e in self.conditions)


@dataclass
class DecisionList:
    rules: list[Rule] = field(default_factory=list)

    def verdict(self) -> Column:
        """The number of the first rule that holds; 0 keeps."""
        found = F.lit(0)
        for i in range(len(self.rules), 0, -1):
            found = F.when(self.rules[i - 1].column(), F.lit(i)).otherwise(found)
        return found


def _gain(p: int, n: int, p0: int, n0: int) -> float:
    """Information gained about rejected rows by going from (p0, n0) to (p, n)."""
    return p * (math.log2(p / (p + n)) - math.log2(p0 / (p0 + n0))) if p else 0.0


def learn(examples: DataFrame, label: str = "quality", most_rules: int = 8, most_conditions: int = 3, precision: float = 0.9, support: int = 5) -> DecisionList:
    """Learn from ``examples`` (the statistics, ``doc_id`` and ``label``: 0 is to be rejected)."""
    edges_row = examples.agg(*[F.percentile_approx(s, [i / BINS for i in range(1, BINS)], 1000).alias(s) for s in STATS]).first()
    if edges_row[STATS[0]] is None:
        return DecisionList()
    edges = {s: sorted(set(edges_row[s])) for s in STATS}
    in_bin = lambda s: sum((F.col(s) > e).cast("int") for e in edges[s]).alias(s) if edges[s] else F.lit(0).alias(s)
    aside = (F.pmod(F.xxhash64(F.lit("aside"), "doc_id"), F.lit(3)) == 0).alias("aside")
    binned = examples.select(*[in_bin(s) for s in STATS], (F.col(label) == 0).alias("bad"), aside)
    rows = written(binned.groupBy(*STATS, "bad", "aside").agg(F.count("*").alias("rows")), "rules").coalesce(8)
    test = lambda c: F.col(c[0]) > c[2] if c[1] else F.col(c[0]) <= c[2]  # noqa: E731  a condition on bins
    found = DecisionList()
    for _ in range(most_rules):
        inside = rows
        for rule in found.rules:
            inside = inside.where(~rule.bins)
        rule, now = [], inside.where("not aside")
        while len(rule) < most_conditions:
            held = now.select(F.explode(F.array(*[F.struct(F.lit(s).alias("s"), F.col(s).alias("b")) for s in STATS])).alias("x"), "bad", "rows")
            hist = {(r.s, r.b, r.bad): r.n for r in held.groupBy("x.s", "x.b", "bad").agg(F.sum("rows").alias("n")).collect()}
            total = [sum(n for (s, _, bad), n in hist.items() if s == STATS[0] and bad is y) for y in (True, False)]
            if not total[0] or not total[1]:
                break
            best = (1e-9, None)
            for s in STATS:
                below = [0, 0]
                for k in range(len(edges[s])):
                    below = [below[0] + hist.get((s, k, True), 0), below[1] + hist.get((s, k, False), 0)]
                    for above, p, n in ((False, *below), (True, total[0] - below[0], total[1] - below[1])):
                        if p >= support and (g := round(_gain(p, n, *total), 6)) > best[0]:
                            best = (g, (s, above, k))
            if best[1] is None:
                break
            rule.append(best[1])
            now = now.where(test(best[1]))
        if not rule:
            break
        prefix = [F.lit(True)]
        for c in rule:
            prefix.append(prefix[-1] & test(c))
        sums = inside.where("aside").agg(*[F.coalesce(F.sum(F.when(q & (F.col("bad") == y), F.col("rows"))), F.lit(0)).alias(f"{y}{i}") for i, q in enumerate(prefix[1:], 1) for y in (True, False)]).first()
        worth = lambda i: (sums[f"True{i}"] - sums[f"False{i}"]) / max(1, sums[f"True{i}"] + sums[f"False{i}"])
        keep = max(range(1, len(rule) + 1), key=lambda i: (round(worth(i), 6), -i))
        p, n = sums[f"True{keep}"], sums[f"False{keep}"]
        if p < 1 or p < precision * (p + n):
            break
        done = Rule([(s, a, float(edges[s][k])) for s, a, k in rule[:keep]], p, n)
        done.bins = prefix[keep]
        found.rules.append(done)
    return found


def fit(docs: DataFrame, labels: DataFrame, most_examples: int = 12_000) -> DecisionList:
    drawn = F.broadcast(drawn_labels(labels, "quality", most_examples))
    # bounded by most_examples
    examples = statistics(docs.select("doc_id", "text").join(drawn.select("doc_id"), "doc_id")).join(drawn, "doc_id")
    return learn(written(examples, "examples"))


BASE = ("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")


def _based(docs: DataFrame, least_words: int, most_repeated: int) -> DataFrame:
    return statistics(docs).withColumn("base_failed", (F.col("n_words") < least_words) | (100 * F.col("n_repeat_words") > most_repeated * F.col("n_words")))


def base(docs: DataFrame, least_words: int = 50, most_repeated: int = 50) -> DataFrame:
    """The counts of each row and ``base_failed``."""
    return _based(docs, least_words, most_repeated).select(*BASE)


def judge(docs: DataFrame, rules: DecisionList, least_words: int = 50, most_repeated: int = 50) -> DataFrame:
    """The counts of each row, ``base_failed``, the ``rule`` that rejects it (0: none) and ``kept``."""
    judged = _based(docs, least_words, most_repeated).withColumn("rule", rules.verdict())
    return judged.select(*BASE, (~F.col("base_failed") & (F.col("rule") == 0)).alias("kept"), "rule")
