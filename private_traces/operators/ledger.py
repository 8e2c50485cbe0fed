"""What each stage of a run spends of the privacy budget, at the level of a whole trace."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMA = "stage string, mechanism string, sensitivity double, epsilon double, composition string"


class Ledger:
    """Sequential releases add up; releases on disjoint sets of traces cost the largest of them."""

    def __init__(self):
        self.rows: list[tuple] = []

    def spend_sequential(self, stage: str, epsilon: float, sensitivity: float = 1.0, mechanism: str = "laplace") -> Ledger:
        self.rows.append((stage, mechanism, float(sensitivity), float(epsilon), "sequential"))
        return self

    def spend_parallel(self, stage: str, epsilons: list[float], sensitivity: float = 1.0, mechanism: str = "laplace") -> Ledger:
        self.rows.append((stage, mechanism, float(sensitivity), float(max(epsilons)), "parallel"))
        return self

    def free(self, stage: str, mechanism: str = "post-processing") -> Ledger:
        self.rows.append((stage, mechanism, 0.0, 0.0, "free"))
        return self

    def leak(self, stage: str, why: str) -> Ledger:
        """A stage that reads the exact data: no finite epsilon covers it."""
        self.rows.append((stage, why, float("inf"), float("inf"), "not private"))
        return self

    @property
    def total(self) -> float:
        return sum(r[3] for r in self.rows)

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, SCHEMA)


def neighbours(traces: DataFrame, trace_id: int) -> DataFrame:
    """The set without one trace: what every mechanism is audited against."""
    return traces.where(~F.col("trace_id").eqNullSafe(F.lit(trace_id)))
