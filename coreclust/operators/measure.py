"""Costs, ratios, coreset errors, sizes, memory and rounds."""

from __future__ import annotations

import itertools
import time

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.metrics import Metric
from ..schema import CoreclustError
from .assign import assign
from .coreset import Coreset

MOST_SOLUTIONS = 2_000_000


def total(metric: Metric, w: Column, d: Column) -> Column:
    """Weighted sum of costs; whole numbers never overflow on the way."""
    return F.sum(w.cast("decimal(19,0)") * d.cast("decimal(19,0)")) if metric.exact else F.sum(w * d)


def cost(points: DataFrame, centers: DataFrame | list, metric: Metric, p: int = 1) -> DataFrame:
    """(cost): sum over points of weight times distance (to the power p) to the nearest center."""
    w = F.col("w") if "w" in points.columns else F.lit(1).cast("long")
    src = points if "w" in points.columns else points.withColumn("w", w)
    c = total(metric, F.col("w"), F.col("d"))
    return assign(src, centers, metric, p, keep=("w",)).agg((c.cast("long") if metric.exact else c).alias("cost"))


def ratio(value: float, optimum: float) -> float:
    return 1.0 if value == optimum else value / optimum


def part_costs(parted: DataFrame, cs: Coreset, metric: Metric, p: int = 1) -> DataFrame:
    """(part, cost) of serving each part from its own cover: points and cover of a part meet in one co-grouped Arrow task."""

    def run(key, points: pa.Table, core: pa.Table) -> pa.Table:
        n = points.num_rows
        if not n or not core.num_rows:
            return pa.table({"part": pa.array([], pa.int32()), "cost": pa.array([], number)})
        data = metric.joined(pa.concat_arrays(points.column("pt").chunks), pa.concat_arrays(core.column("pt").chunks))
        d, _ = metric.nearest(data, np.arange(n, n + core.num_rows), np.arange(n), p)
        w = points.column("w").to_numpy()
        return pa.table({"part": pa.array([key[0].as_py()], pa.int32()), "cost": pa.array([(w * d).sum()], number)})

    number = pa.int64() if metric.exact else pa.float64()
    left, right = parted.select("part", "pt", "w").groupBy("part"), cs.rows.select("part", "pt").groupBy("part")
    return left.cogroup(right).applyInArrow(run, f"part int, cost {'long' if metric.exact else 'double'}")


def mapping_cost(cs: Coreset, metric: Metric) -> DataFrame:
    """(num): summed distance of all points to the points that stand for them."""
    c = total(metric, F.col("w"), F.col("d"))
    return cs.mapping.agg((c.cast("long") if metric.exact else c).alias("num"))


def all_solutions(ids: list[int], payload: list, k: int) -> list[tuple[list[int], list]]:
    import math

    if math.comb(len(ids), k) > MOST_SOLUTIONS:
        raise CoreclustError("too many center sets")
    return list(itertools.combinations(range(len(ids)), k))


def solution_costs(points: DataFrame, solutions: list[list], metric: Metric, p: int) -> DataFrame:
    """(solution, cost) of many center sets in one pass; the sets (lists of payloads) travel, their number is checked."""
    if len(solutions) > MOST_SOLUTIONS:
        raise CoreclustError("too many center sets")
    flat = list({repr(x): x for s in solutions for x in s}.values())
    where = {repr(x): i for i, x in enumerate(flat)}
    table = np.array([[where[repr(x)] for x in s] for s in solutions], np.int64)
    sent = points.sparkSession.sparkContext.broadcast((flat, table))

    def run(batches):
        flat, table = sent.value
        out = np.zeros(len(table))
        for b in batches:
            n, w = b.num_rows, np.array(b.column(1).to_pylist(), float)
            data = metric.joined(b.column(0), flat)
            d = np.stack([metric.one(data, n + c, np.arange(n), p) for c in range(len(flat))]).astype(float)
            for at in range(0, len(table), 4096):
                out[at : at + 4096] += np.einsum("sn,n->s", d[table[at : at + 4096]].min(1), w)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(out))), pa.array(out)], ["solution", "cost"])

    return points.select("pt", "w").mapInArrow(run, "solution long, cost double").groupBy("solution").agg(F.sum("cost").alias("cost"))


def distortion(points: DataFrame, core: DataFrame, solutions: list[list], metric: Metric, p: int) -> DataFrame:
    """(solution, cost, core_cost, error): relative error of the coreset's cost, per center set."""
    a = solution_costs(points, solutions, metric, p)
    b = solution_costs(core, solutions, metric, p).withColumnRenamed("cost", "core_cost")
    return a.join(b, "solution").withColumn("error", F.when(F.col("cost") == F.col("core_cost"), 0.0).otherwise(F.abs(F.col("cost") - F.col("core_cost")) / F.col("cost")))


def centroid_witness(points: DataFrame, core: DataFrame, optimal: list, metric: Metric, p: int) -> DataFrame:
    """(cost): cost on all points of the coreset points nearest to optimal centers."""
    kind = points.schema["pt"].dataType.simpleString()
    opt = points.sparkSession.createDataFrame([(c, x) for c, x in optimal], f"id long, pt {kind}")
    near = assign(opt, core.select(F.col("id").alias("center_id"), "pt"), metric).select("center_id").distinct()
    return cost(points, core.select(F.col("id").alias("center_id"), "pt").join(near, "center_id").distinct(), metric, p)


def size(cs: Coreset) -> DataFrame:
    """(n_core, n, w_sum, compression, n_dist)."""
    s = cs.stats.agg(F.sum("n_core").alias("n_core"), F.sum("n").alias("n"), F.sum("w_sum").alias("w_sum"), F.sum("n_dist").alias("n_dist"))
    return s.select("n_core", "n", "w_sum", (F.col("n") / F.col("n_core")).alias("compression"), "n_dist")


def memory(first: Coreset, second: Coreset) -> DataFrame:
    """(round, max_rows, sum_rows): rows that the largest task and all tasks of a round hold."""
    union = first.stats.agg(F.sum("n_core").alias("c"))
    one = first.stats.agg(F.lit(1).alias("round"), F.max(F.col("n") + F.col("n_seed")).alias("max_rows"), F.sum("n").alias("sum_rows"))
    two = second.stats.join(F.broadcast(union), F.lit(True)).agg(F.lit(2).alias("round"), F.max(F.col("n") + F.col("c") + F.col("n_core")).alias("max_rows"), F.sum(F.col("n") + F.col("c")).alias("sum_rows"))
    three = second.stats.agg(F.lit(3).alias("round"), F.sum("n_core").alias("max_rows"), F.sum("n_core").alias("sum_rows"))
    return one.unionByName(two).unionByName(three)


def exchanges(df: DataFrame) -> int:
    """Shuffles and broadcasts of a frame's physical plan."""
    return df._jdf.queryExecution().executedPlan().toString().count("Exchange")


def purity(assigned: DataFrame, label: str) -> DataFrame:
    """(center_id, label, n): the most frequent label of each cluster; ties to the smaller label."""
    counts = assigned.groupBy("center_id", label).agg(F.count("*").alias("n"))
    top = counts.groupBy("center_id").agg(F.min(F.struct((-F.col("n")).alias("minus"), label)).alias("m"))
    return top.select("center_id", F.col(f"m.{label}").alias(label), (-F.col("m.minus")).alias("n"))


def pair_agreement(assigned: DataFrame, label: str) -> float:
    """Share of pairs on which clusters and labels agree, from the contingency table."""
    t = assigned.groupBy("center_id", label).agg(F.count("*").cast("double").alias("n"))
    pairs = lambda c: F.col(c) * (F.col(c) - 1) / 2
    both = t.agg(F.sum(pairs("n"))).first()[0] or 0.0
    one, two = (t.groupBy(c).agg(F.sum("n").alias("n")).agg(F.sum(pairs("n"))).first()[0] or 0.0 for c in ("center_id", label))
    n = t.agg(F.sum("n")).first()[0] or 0.0
    every = n * (n - 1) / 2
    return 1.0 if not every else (every + 2 * both - one - two) / every


def timed(df: DataFrame) -> float:
    """Seconds to compute a frame without keeping it."""
    t = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - t
