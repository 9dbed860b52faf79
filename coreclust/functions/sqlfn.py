"""SQL surface: distance functions, and a table function that covers a partition of points."""

from __future__ import annotations

from fractions import Fraction

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from ..operators.cover import ball_cover
from ..operators.seed import farthest
from .metrics import Lp

#: Points that one call of the table function holds.
MOST_ROWS = 200_000


class CoverPoints:
    """SELECT * FROM cover_points(TABLE(points) PARTITION BY (part), 5, 0.5, 1.0): rows (id, w) of each partition's L1 cover.

    The input needs columns id and pt (array<bigint>).
    """

    def __init__(self):
        self.ids, self.pts, self.args = [], [], None

    def eval(self, row, m: int, eps: float, beta: float):
        if len(self.ids) >= MOST_ROWS:
            raise ValueError(f"a partition may have {MOST_ROWS} points")
        self.ids.append(row["id"])
        self.pts.append(list(row["pt"]))
        self.args = m, eps, beta

    def terminate(self):
        if not self.ids:
            return
        m, eps, beta = self.args
        order = np.argsort(self.ids, kind="stable")
        ids, metric = np.array(self.ids)[order], Lp(1)
        data = metric.load([self.pts[k] for k in order])
        w = np.ones(len(ids), np.int64)
        _, d = farthest(metric, data, w, m, 1, None)
        c = ball_cover(metric, data, d, int(d.sum()), len(ids), Fraction(eps).limit_denominator(10**6), Fraction(beta).limit_denominator(10**6))
        mass = np.bincount(c.tau, minlength=len(ids))
        for k in np.sort(c.pivots):
            yield int(ids[k]), int(mass[k])


def weighted_medoid_cost(d: pd.Series, w: pd.Series) -> float:
    """Grouped aggregate: weighted sum of distances of a group."""
    return float((d * w).sum())


def register(spark: SparkSession) -> None:
    """cover_points (table function), l1_distance, squared_distance, angular_distance and weighted_cost in SQL."""
    from pyspark.sql.functions import pandas_udf

    spark.udtf.register("cover_points", udtf(CoverPoints, returnType="id bigint, w bigint"))
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION l1_distance(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> abs(x - y)), 0D, (s, x) -> s + x)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION squared_distance(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x)")
    spark.udf.register("weighted_cost", pandas_udf(weighted_medoid_cost, "double"))
