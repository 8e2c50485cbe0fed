"""A Python data source that samples synthetic trips from a released synopsis:
``spark.read.format("synthetic_trips").option("synopsis", folder).option("n", 1000).load()``.

The folder holds the released trips table as Parquet; each partition samples its own range of trace ids.
"""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class SyntheticTrips(DataSource):
    @classmethod
    def name(cls) -> str:
        return "synthetic_trips"

    def schema(self) -> str:
        return "trace_id bigint, start_cell int, end_cell int"

    def reader(self, schema):
        return TripReader(self.options)


class Range(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class TripReader(DataSourceReader):
    def __init__(self, options):
        self.folder = options.get("synopsis")
        self.n, self.seed, self.parts = int(options.get("n", 1000)), int(options.get("seed", 42)), int(options.get("partitions", 8))

    def partitions(self):
        step = -(-self.n // self.parts) or 1
        return [Range(a, min(a + step, self.n)) for a in range(0, self.n, step)]

    def read(self, part):
        import numpy as np
        import pyarrow as pa
        import pyarrow.dataset as ds
        import pyarrow.fs as pafs

        fs, root = pafs.FileSystem.from_uri(self.folder if "://" in self.folder else f"file://{self.folder}")
        rows = ds.dataset(root, filesystem=fs, format="parquet").to_table(columns=["start_cell", "end_cell", "prob"]).sort_by([("start_cell", "ascending"), ("end_cell", "ascending")])
        cdf = np.cumsum(rows.column("prob").to_numpy())
        ids = np.arange(part.first, part.last)
        u = np.array([np.random.default_rng((self.seed, int(i))).random() for i in ids])
        at = np.minimum(np.searchsorted(cdf, u * cdf[-1], side="right"), len(cdf) - 1)
        yield pa.RecordBatch.from_pydict({"trace_id": ids, "start_cell": rows.column("start_cell").to_numpy()[at], "end_cell": rows.column("end_cell").to_numpy()[at]})


def register(spark) -> None:
    spark.dataSource.register(SyntheticTrips)
