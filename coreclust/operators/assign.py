"""Nearest centers, balls, profiles and separation."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.metrics import Metric
from ..schema import CoreclustError

#: Centers that one task may hold.
MOST_CENTERS = 1_000_000


def center_rows(centers: DataFrame, most: int = MOST_CENTERS) -> list[tuple[int, object]]:
    """Centers by id, their number checked before they travel."""
    got = [(r["center_id"], r["pt"]) for r in centers.select("center_id", "pt").limit(most + 1).collect()]
    if len(got) > most:
        raise CoreclustError(f"more than {most} centers")
    return sorted(got, key=lambda x: x[0])


def assign(points: DataFrame, centers: DataFrame | list, metric: Metric, p: int = 1, keep: tuple[str, ...] = ()) -> DataFrame:
    """(id, center_id, d) with d to the power p; ties go to the smallest center id."""
    rows = center_rows(centers) if isinstance(centers, DataFrame) else sorted(centers, key=lambda x: x[0])
    sent = points.sparkSession.sparkContext.broadcast(rows)
    number = "long" if metric.exact else "double"
    fields = ["id", "pt", *keep]
    src = points.select(*fields)
    schema = ", ".join(["id long", "center_id long", f"d {number}", *(f"{c} {src.schema[c].dataType.simpleString()}" for c in keep)])

    def run(batches):
        rows = sent.value
        ids = np.array([r[0] for r in rows], np.int64)
        for b in batches:
            n = b.num_rows
            data = metric.joined(b.column(1), [x for _, x in rows])
            d, who = metric.nearest(data, np.arange(n, n + len(rows)), np.arange(n), p)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(ids[who]), pa.array(d.astype(np.int64) if metric.exact else d.astype(float)), *b.columns[2:]], ["id", "center_id", "d", *keep])

    return src.mapInArrow(run, schema)


def assign_sql(points: DataFrame, centers: list, metric: Metric, p: int = 1) -> DataFrame:
    """The same by Catalyst expressions alone: the centers are literals of the plan, so for a few of them."""
    if len(centers) > 200:
        raise CoreclustError("more than 200 centers as literals; use assign")
    kind = points.schema["pt"].dataType
    each = [F.struct(metric.power_column(F.col("pt"), F.lit(list(x) if isinstance(x, (list, tuple)) else x).cast(kind), p).alias("d"), F.lit(c).cast("long").alias("center_id")) for c, x in sorted(centers)]
    return points.select("id", F.array_min(F.array(*each)).alias("m")).select("id", "m.center_id", "m.d")


def ball(points: DataFrame, center: object, radius: float, metric: Metric) -> DataFrame:
    """(id, d) of the points within a radius of one payload."""
    kind = points.schema["pt"].dataType
    d = metric.column(F.col("pt"), F.lit(list(center) if isinstance(center, (list, tuple)) else center).cast(kind))
    return points.select("id", d.alias("d")).where(F.col("d") <= radius)


def profile(assigned: DataFrame, centers: DataFrame | None = None) -> DataFrame:
    """(center_id, n, w, cost, radius, nearest_id) by cluster; with `centers`, empty clusters too.  `assigned` may carry w."""
    w = F.col("w") if "w" in assigned.columns else F.lit(1).cast("long")
    out = assigned.groupBy("center_id").agg(F.count("*").alias("n"), F.sum(w).cast("long").alias("w"), F.sum(w * F.col("d")).alias("cost"), F.max("d").alias("radius"), F.min(F.struct("d", "id")).alias("m"))
    out = out.select("center_id", "n", "w", "cost", "radius", F.col("m.id").alias("nearest_id"))
    if centers is None:
        return out
    zero = {"n": 0, "w": 0, "cost": 0}
    return centers.select("center_id").join(out, "center_id", "left").na.fill(zero)


def _line_separation(points: DataFrame, number: str) -> DataFrame:
    """Least gap of sorted values: range-partitioned, so only each partition's ends meet on the driver."""
    x = points.select(F.col("pt")[0].cast(number).alias("x"))
    parts = int(points.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def run(batches):
        first, last, gap = None, None, None
        for b in batches:
            v = b.column(0).to_numpy()
            if len(v):
                d = np.diff(v if last is None else np.concatenate(([last], v)))
                first, last = v[0] if first is None else first, v[-1]
                gap = min([gap, *d.min(keepdims=True)] if gap is not None else d.min(keepdims=True)) if len(d) else gap
        if first is not None:
            yield pa.RecordBatch.from_pydict({"lo": pa.array([first]), "hi": pa.array([last]), "gap": pa.array([gap], pa.int64() if number == "long" else pa.float64())})

    ends = sorted((r["lo"], r["hi"], r["gap"]) for r in x.repartitionByRange(parts, "x").sortWithinPartitions("x").mapInArrow(run, f"lo {number}, hi {number}, gap {number}").collect())
    gaps = [g for *_, g in ends if g is not None] + [b[0] - a[1] for a, b in zip(ends, ends[1:], strict=False)]
    return points.sparkSession.createDataFrame([(min(gaps) if gaps else None,)], f"min_d {number}")


def separation(points: DataFrame, metric: Metric, block: int = 2_000) -> DataFrame:
    """(min_d): the least distance between two different points.

    On a line it is the least gap between neighbours in order.  In general every block of points
    meets the blocks from its own on, one Arrow task per pair of blocks; no pair is emitted.
    """
    number = "long" if metric.exact else "double"
    if metric.name in ("lp", "euclidean") and not (metric.name == "euclidean" and metric.exact):
        first = points.select(F.size("pt").alias("n")).first()
        if first is not None and first["n"] == 1:
            return _line_separation(points, number)
    n = points.count()
    blocks = max(1, -(-n // block))
    keyed = points.select("id", "pt").withColumn("b", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int"))
    left = keyed.withColumn("c", F.explode(F.sequence(F.col("b"), F.lit(blocks - 1)))).select(F.col("b").alias("i"), F.col("c").alias("j"), F.lit(0).alias("side"), "id", "pt")
    right = keyed.where("b > 0").withColumn("c", F.explode(F.sequence(F.lit(0), F.col("b") - 1))).select(F.col("c").alias("i"), F.col("b").alias("j"), F.lit(1).alias("side"), "id", "pt")

    def run(t: pa.Table) -> pa.Table:
        side = np.array(t.column("side").to_pylist())
        data = metric.load(t.column("pt").to_pylist())
        a, b = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
        best = [metric.one(data, int(x), b if len(b) else a[k + 1 :]) for k, x in enumerate(a)]
        best = [x.min() for x in best if len(x)]
        return pa.table({"d": pa.array([min(best)] if best else [], pa.int64() if metric.exact else pa.float64())})

    same = left.where("i = j").unionByName(left.where("i < j")).unionByName(right)
    return same.groupBy("i", "j").applyInArrow(run, f"d {number}").agg(F.min("d").alias("min_d"))


def is_separated(points: DataFrame, r: float, metric: Metric) -> bool:
    got = separation(points, metric).first()["min_d"]
    return got is None or got > r


def doubling_dimension(points: DataFrame, metric: Metric, balls: int = 8, sample: int = 400, seed: int = 0) -> DataFrame:
    """(radius, d_hat): log2 of the half-radius balls that greedily cover sampled balls, a diagnostic on a bounded sample."""
    few = points.select(F.lit(0).alias("g"), "id", "pt").orderBy(F.xxhash64("id", F.lit(seed)), "id").limit(sample)

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by("id")
        data, n = metric.load(t.column("pt").to_pylist()), t.num_rows
        d = np.stack([metric.one(data, i, np.arange(n)) for i in range(n)]).astype(float)
        top, out = float(d.max()), {"radius": [], "d_hat": []}
        for k in range(1, 7):
            r, most = top / 2**k, 1
            for c in range(min(balls, n)):
                left, used = np.flatnonzero(d[c] <= r), 0
                while len(left):
                    left, used = left[d[left[0], left] > r / 2], used + 1
                most = max(most, used)
            out["radius"].append(r)
            out["d_hat"].append(float(np.log2(most)))
        return pa.table(out)

    return few.groupBy("g").applyInArrow(run, "radius double, d_hat double")
