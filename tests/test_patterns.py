"""Patterns grown from prefixes against all patterns counted at once."""

from collections import Counter

from private_traces.operators import metrics


def _all(rows, k, low, high):
    found = Counter(">".join(map(str, c[i : i + n])) for c in rows for n in range(low, high + 1) for i in range(len(c) - n + 1))
    return sorted(found.items(), key=lambda r: (-r[1], r[0]))[:k]


def test_prefixes_keep_the_best_patterns_and_their_ties(spark):
    rows = [[1, 2, 3, 4]] * 5 + [[1, 2, 3]] * 2 + [[10, 2, 10, 2, 10]] * 3 + [[9, 9, 9, 9, 9]] * 2 + [[7, 8], [8, 7], [3], [], [11, 12, 13]]
    paths = spark.createDataFrame([(i, len(c), c) for i, c in enumerate(rows)], "trace_id long, n int, cells array<int>")
    for k in (1, 3, 6, 12, 100):
        assert [(r.pattern, r.support) for r in metrics.top_patterns_by_prefix(paths, k).collect()] == _all(rows, k, 2, 8), k


def test_the_paths_are_read_once(spark):
    read = spark.sparkContext.accumulator(0)

    def told(batches):
        for b in batches:
            read.add(b.num_rows)
            yield b

    paths = spark.createDataFrame([(i, 4, [i % 3, 1, 2, 1]) for i in range(60)], "trace_id long, n int, cells array<int>").mapInArrow(told, "trace_id long, n int, cells array<int>")
    metrics.top_patterns_by_prefix(paths).collect()
    assert read.value == 60
