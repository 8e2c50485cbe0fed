"""Functions and table functions for SQL text. The scalar ones are SQL bodies, which the optimizer inlines."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

BODIES = {
    "jsd_term": ("p DOUBLE, q DOUBLE", "DOUBLE", "CASE WHEN p > 0 THEN 0.5D * p * log2(2 * p / (p + q)) ELSE 0D END"),
    "keyed_uniform": ("lead STRING, k STRING", "DOUBLE", "(CAST(conv(substring(md5(concat(lead, '|', k)), 1, 12), 16, 10) AS BIGINT) + 0.5D) / 281474976710656D"),
    "keyed_laplace": ("scale DOUBLE, lead STRING, k STRING", "DOUBLE", "-scale * signum(keyed_uniform(lead, k) - 0.5D) * ln(1 - 2 * abs(keyed_uniform(lead, k) - 0.5D))"),
    "uniform_cell": (
        "x DOUBLE, y DOUBLE, x0 DOUBLE, x1 DOUBLE, y0 DOUBLE, y1 DOUBLE, n INT", "INT",
        "CAST(greatest(0, least(n - 1, floor((x - x0) / (x1 - x0) * n))) * n + greatest(0, least(n - 1, floor((y - y0) / (y1 - y0) * n))) AS INT)",
    ),
    "great_circle_km": (
        "lon0 DOUBLE, lat0 DOUBLE, lon1 DOUBLE, lat1 DOUBLE", "DOUBLE",
        "2 * 6371.0088D * asin(least(1D, sqrt(power(sin(radians(lat1 - lat0) / 2), 2) + cos(radians(lat0)) * cos(radians(lat1)) * power(sin(radians(lon1 - lon0) / 2), 2))))",
    ),
}


@udtf(returnType="pattern string")
class GappedPatterns:
    """All patterns of ``size`` cells that occur in order, with others between, in one trace: each once. For short traces: a trace of n
    cells has up to n-choose-size of them."""

    def eval(self, cells: list, size: int):
        held: list[set] = [{()}, *[set() for _ in range(size)]]
        for c in cells or []:
            for k in range(size, 0, -1):
                held[k] |= {(*p, c) for p in held[k - 1]}
        for p in sorted(held[size]):
            yield (">".join(map(str, p)),)


def register(spark: SparkSession) -> list[str]:
    """Register every function; their names."""
    for name, (args, kind, body) in BODIES.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")
    spark.udtf.register("gapped_patterns", GappedPatterns)
    return [*BODIES, "gapped_patterns"]
