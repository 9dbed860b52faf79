"""Points and parts: featurising tables, collapsing equal rows, dealing rows to parts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def points(df: DataFrame, id_col: str | Column, pt: Column, w: Column | None = None) -> DataFrame:
    """(id, pt, w) by plain expressions, so that scans still prune columns and push filters."""
    key = F.col(id_col) if isinstance(id_col, str) else id_col
    return df.select(key.cast("long").alias("id"), pt.alias("pt"), (F.lit(1) if w is None else w).cast("long").alias("w"))


def quantised(c: str | Column, scale: float = 1) -> Column:
    return F.round((F.col(c) if isinstance(c, str) else c) * scale).cast("long")


def collapse(pts: DataFrame) -> DataFrame:
    """Equal payloads as one weighted point with the smallest id: costs do not change."""
    return pts.groupBy("pt").agg(F.min("id").alias("id"), F.sum("w").alias("w")).select("id", "pt", "w")


def by_content(df: DataFrame, pt: Column) -> DataFrame:
    """Points of a table without a key: equal rows become one point, its id a hash of the payload."""
    return df.select(pt.alias("pt")).groupBy("pt").agg(F.count("*").alias("w")).select(F.xxhash64("pt").alias("id"), "pt", "w")


def by_modulo(pts: DataFrame, parts: int, key: str = "id") -> DataFrame:
    return pts.withColumn("part", F.pmod(F.col(key), F.lit(parts)).cast("int"))


def by_hash(pts: DataFrame, parts: int) -> DataFrame:
    return pts.withColumn("part", F.pmod(F.xxhash64("id"), F.lit(parts)).cast("int"))


def by_column(pts: DataFrame, column: Column, rows_per_part: int | None = None) -> DataFrame:
    """Parts along a natural column; values with more rows than fit a task are salted into several parts."""
    if rows_per_part is None:
        return pts.withColumn("part", F.hash(column))
    keyed = pts.withColumn("_k", column)
    sizes = keyed.groupBy("_k").agg(F.ceil(F.count("*") / rows_per_part).cast("int").alias("_s"))
    return keyed.join(sizes, "_k").withColumn("part", F.hash("_k", F.pmod(F.xxhash64("id"), F.col("_s")))).drop("_k", "_s")


def evenly(pts: DataFrame, parts: int, buckets: int = 1024) -> DataFrame:
    """Parts of equal size (they differ by one at most) without a global sort: ranks within hash buckets, offset by the buckets before."""
    b = pts.withColumn("_b", F.pmod(F.xxhash64("id"), F.lit(buckets)).cast("int"))
    before = b.groupBy("_b").agg(F.count("*").alias("_n"))
    before = before.select("_b", (F.sum("_n").over(Window.orderBy("_b").rowsBetween(Window.unboundedPreceding, 0)) - F.col("_n")).alias("_o"))
    ranked = b.withColumn("_r", F.row_number().over(Window.partitionBy("_b").orderBy("id"))).join(F.broadcast(before), "_b")
    return ranked.withColumn("part", F.pmod(F.col("_o") + F.col("_r") - 1, F.lit(parts)).cast("int")).drop("_b", "_r", "_o")
