"""Contracts between stages: column names, parameter checks, input validation."""

from __future__ import annotations

from dataclasses import dataclass, field
from fractions import Fraction

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


class CoreclustError(ValueError):
    """Bad parameters or bad input rows."""


@dataclass(frozen=True)
class ClusterSpec:
    """What to solve and how finely to summarise.

    `eps` and `beta` are kept as fractions, so integer metrics are compared without rounding.
    `m` seeds per part (at least k); `order` is the order in which a cover picks pivots.
    """

    k: int
    objective: str = "median"
    eps: Fraction = Fraction(1, 2)
    beta: Fraction = Fraction(1)
    m: int | None = None
    seeder: str = "farthest"
    order: str = "id"
    seed: int = 0
    prune: bool = False
    floor: bool = True
    strict: bool = False
    options: dict = field(default_factory=dict)

    def __post_init__(self):
        put = lambda k, v: object.__setattr__(self, k, v)
        put("eps", Fraction(self.eps).limit_denominator(10**6))
        put("beta", Fraction(self.beta).limit_denominator(10**6))
        put("m", self.k if self.m is None else self.m)
        if self.k < 1:
            raise CoreclustError(f"k must be at least 1, not {self.k}")
        if not 0 < self.eps < 1:
            raise CoreclustError(f"eps must be between 0 and 1, not {self.eps}")
        if self.beta < 1:
            raise CoreclustError(f"beta must be at least 1, not {self.beta}")
        if self.m < self.k:
            raise CoreclustError(f"m must be at least k = {self.k}, not {self.m}")
        if self.objective not in ("median", "means"):
            raise CoreclustError(f"objective is median or means, not {self.objective}")
        if self.objective == "means" and 2 * self.eps**2 >= 1:
            raise CoreclustError(f"k-means covers need eps below 1/sqrt(2), not {self.eps}")
        if self.strict and not self.proven:
            raise CoreclustError(f"no proven ratio for eps {self.eps} and {self.objective}")

    @property
    def p(self) -> int:
        """Power of a distance in the cost."""
        return 2 if self.objective == "means" else 1

    @property
    def proven(self) -> bool:
        return self.objective == "median" or self.eps + self.eps**2 <= Fraction(1, 8)


def point_schema(pt: T.DataType) -> T.StructType:
    return T.StructType([T.StructField("id", T.LongType(), False), T.StructField("pt", pt, False), T.StructField("w", T.LongType(), False)])


def check_points(points: DataFrame, on_invalid: str = "error", unique: bool = True) -> DataFrame:
    """Rows that are points: id and payload present, no null, NaN or infinite coordinate, weight at least 1, one payload length.

    `error` counts the bad rows in one pass and raises; `drop` filters them out.  Ids must be
    unique; `error` checks that by a shuffle unless `unique` is off.
    """
    return _checked(points, on_invalid, unique)[0]


def counted_points(points: DataFrame) -> tuple[DataFrame, int]:
    """The points and their number, checked in one pass without a shuffle; parts look for repeated ids themselves."""
    return _checked(points, "error", False)


def _checked(points: DataFrame, on_invalid: str, unique: bool) -> tuple[DataFrame, int]:
    for c in ("id", "pt"):
        if c not in points.columns:
            raise CoreclustError(f"points need a column {c}")
    if "w" not in points.columns:
        points = points.withColumn("w", F.lit(1).cast("long"))
    kind = points.schema["pt"].dataType
    bad = F.col("id").isNull() | F.col("pt").isNull() | F.col("w").isNull() | (F.col("w") < 1)
    if isinstance(kind, T.ArrayType):
        odd = lambda x: x.isNull() | (F.isnan(x) | (F.abs(x) == float("inf")) if isinstance(kind.elementType, (T.DoubleType, T.FloatType)) else F.lit(False))
        bad = bad | F.coalesce(F.exists("pt", odd), F.lit(True))
    if on_invalid == "drop":
        return points.where(~bad), -1
    vector = isinstance(kind, T.ArrayType) and not isinstance(kind.elementType, T.StringType)
    length = F.size("pt") if vector else F.lit(0)
    got = points.agg(F.count_if(bad).alias("bad"), F.count("*").alias("n"), F.min(length).alias("lo"), F.max(length).alias("hi")).first()
    if got["bad"]:
        raise CoreclustError(f"{got['bad']} of {got['n']} rows are no points (null, NaN or infinite values, or a weight under 1)")
    if vector and got["n"] and got["lo"] != got["hi"]:
        raise CoreclustError(f"payload lengths differ: {got['lo']} to {got['hi']}")
    if not unique:
        return points, got["n"]
    twice = points.groupBy("id").agg(F.count("*").alias("n")).where("n > 1").agg(F.count("*").alias("n")).first()["n"]
    if twice:
        raise CoreclustError(f"{twice} ids occur more than once")
    return points, got["n"]
