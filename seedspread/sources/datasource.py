"""``spark.read.format("seed_graph")``: synthetic graphs as a Python data source, one partition per range of vertices."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Range(InputPartition):
    def __init__(self, lo: int, hi: int):
        super().__init__(lo)
        self.lo, self.hi = lo, hi


class _TorusReader(DataSourceReader):
    def __init__(self, options):
        self.k, self.parts = int(options.get("k", 3)), int(options.get("partitions", 4))

    def partitions(self):
        cuts = np.linspace(0, self.k**3, self.parts + 1).astype(int).tolist()
        return [_Range(a, b) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]

    def read(self, partition) -> Iterator[pa.RecordBatch]:
        k = self.k
        for lo in range(partition.lo, partition.hi, 1 << 16):
            v = np.arange(lo, min(lo + (1 << 16), partition.hi), dtype=np.int64)
            x, y, z = v % k, v // k % k, v // (k * k)
            near = [(x + d) % k + y * k + z * k * k for d in (1, -1)] + [x + (y + d) % k * k + z * k * k for d in (1, -1)] + [x + y * k + (z + d) % k * k * k for d in (1, -1)]
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(v, 6)), pa.array(np.stack(near, 1).reshape(-1))], names=["src", "dst"])


class SeedGraphSource(DataSource):
    """Options: ``k`` (side of the wrap-around grid), ``partitions``. Rows are both directions of every edge."""

    @classmethod
    def name(cls) -> str:
        return "seed_graph"

    def schema(self):
        return "src long, dst long"

    def reader(self, schema):
        return _TorusReader(dict(self.options))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(SeedGraphSource)
