"""A Python data source of metric points: clusters of vectors with known centers."""

from __future__ import annotations

import numpy as np
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Range(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.n, self.dim, self.k, self.seed, self.parts = (int(options.get(x, d)) for x, d in (("n", 1000), ("dim", 2), ("k", 5), ("seed", 0), ("partitions", 4)))

    def partitions(self):
        cut = [self.n * i // self.parts for i in range(self.parts + 1)]
        return [_Range(a, b) for a, b in zip(cut, cut[1:], strict=False)]

    def read(self, partition):
        centers = np.random.default_rng(self.seed).uniform(-1000, 1000, (self.k, self.dim))
        for i in range(partition.lo, partition.hi):
            noise = np.random.default_rng([self.seed, i]).normal(0, 10, self.dim)
            yield i, [float(x) for x in centers[i % self.k] + noise], 1


class MetricPoints(DataSource):
    """spark.dataSource.register(MetricPoints); spark.read.format("metric_points").option("n", 10000).load()"""

    @classmethod
    def name(cls):
        return "metric_points"

    def schema(self):
        return "id long, pt array<double>, w long"

    def reader(self, schema):
        return _Reader(self.options)
