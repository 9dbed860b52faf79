"""Baselines: what the coresets are compared with."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.metrics import Euclidean, Metric
from ..schema import ClusterSpec
from .assign import assign
from .coreset import _opened, _rng
from .seed import SEEDERS
from .solve import solve


def sequential(points: DataFrame, k: int, metric: Metric, p: int, **options) -> DataFrame:
    """The sequential local search on all points, in one task (bounded rows)."""
    return solve(points, k, metric, p, "local_search", **options)


def local_centers(parted: DataFrame, spec: ClusterSpec, metric: Metric) -> DataFrame:
    """(part, id, pt, w): each part's rough centers weighted by the points nearest to them, as a coreset."""
    kind = parted.schema["pt"].dataType.simpleString()

    def run(key, t):
        ids, payload, w = _opened(t.select(["id", "pt", "w"]))
        data = metric.joined(payload)
        picks, _ = SEEDERS[spec.seeder](metric, data, w, spec.m, spec.p, _rng(spec, key[0].as_py()), **spec.options)
        picks = np.sort(picks)
        _, who = metric.nearest(data, picks, np.arange(len(ids)), spec.p)
        mass = np.bincount(who, w, len(picks)).astype(np.int64)
        keep = np.flatnonzero(mass)
        return pa.table({"part": pa.array([key[0].as_py()] * len(keep), pa.int32()), "id": ids[picks[keep]], "pt": payload.take(pa.array(picks[keep])), "w": mass[keep]})

    return parted.select("part", "id", "pt", "w").groupBy("part").applyInArrow(run, f"part int, id long, pt {kind}, w long")


def bucket(column: str, buckets: int):
    """A hash bucket that other engines can compute: the first 32 bits of the MD5 of the key's text."""
    return F.conv(F.substring(F.md5(F.col(column).cast("string").cast("binary")), 1, 8), 16, 10).cast("long") % buckets


def uniform_sample(points: DataFrame, share: int) -> DataFrame:
    """(id, pt, w): one point in `share` by hash bucket, each standing for `share`."""
    return points.where(bucket("id", share) == 0).select("id", "pt", (F.col("w") * share).alias("w"))


def importance_sample(points: DataFrame, centers: DataFrame | list, metric: Metric, p: int, size: int) -> DataFrame:
    """(id, pt, w): Poisson sample with chances in proportion to weight and cost shares, weights by inverse chance."""
    costed = assign(points, centers, metric, p, keep=("pt", "w"))
    total = costed.agg(F.sum(F.col("w") * F.col("d")).cast("double").alias("cost"), F.sum("w").cast("double").alias("w")).first()
    share = 0.5 * F.col("w") / F.lit(total["w"] or 1.0) + 0.5 * F.col("w") * F.col("d") / F.lit(total["cost"] or 1.0)
    chance = F.least(F.lit(1.0), F.lit(float(size)) * share)
    drawn = F.pmod(F.xxhash64("id", F.lit(5)), F.lit(1 << 30)) / F.lit(float(1 << 30)) < F.col("chance")
    return costed.withColumn("chance", chance).where(drawn).select("id", "pt", F.greatest(F.lit(1), F.round(F.col("w") / F.col("chance"))).cast("long").alias("w"))


def shell_grid(points: DataFrame, centers: DataFrame | list, metric: Metric, r: int, cell: int) -> DataFrame:
    """(center_id, shell, cell, id, w): vectors snapped to grids that widen with their shell around the nearest center.

    Whole-number coordinates: shell j holds distances in (2^(j-1) r, 2^j r], its cells have side cell * 2^j.
    """
    d = assign(points, centers, metric, 1, keep=("pt", "w"))
    shell = F.when(F.col("d") <= r, 0).otherwise(F.ceil(F.log2(F.col("d") / r)).cast("int"))
    d = d.withColumn("shell", shell)
    fixed = F.when(F.col("d") > F.lit(r) * F.pow(F.lit(2.0), "shell"), F.col("shell") + 1).when((F.col("shell") > 0) & (F.col("d") <= F.lit(r) * F.pow(F.lit(2.0), F.col("shell") - 1)), F.col("shell") - 1).otherwise(F.col("shell")).cast("int")
    d = d.withColumn("shell", fixed).withColumn("side", (F.lit(cell) * F.pow(F.lit(2.0), "shell")).cast("long"))
    cells = F.transform("pt", lambda x: F.floor(x / F.col("side")).cast("long"))
    return d.groupBy("center_id", "shell", F.array_join(cells.cast("array<string>"), ",").alias("cell")).agg(F.min("id").alias("id"), F.sum("w").alias("w"))


def farthest_on_parts(parted: DataFrame, spec: ClusterSpec, metric: Metric) -> DataFrame:
    """(part, rank, id): farthest-first centers of each part in order of choice."""
    from .seed import farthest

    def run(key, t):
        ids, payload, w = _opened(t.select(["id", "pt", "w"]))
        picks, _ = farthest(metric, metric.joined(payload), w, spec.m, spec.p, None)
        return pa.table({"part": pa.array([key[0].as_py()] * len(picks), pa.int32()), "rank": pa.array(range(len(picks)), pa.int32()), "id": ids[picks]})

    return parted.select("part", "id", "pt", "w").groupBy("part").applyInArrow(run, "part int, rank int, id long")


def _library_model(points: DataFrame, k: int, seed: int, passes: int):
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    rows = points.select("id", array_to_vector(F.col("pt").cast("array<double>")).alias("features"))
    return KMeans(k=k, seed=seed, maxIter=passes).fit(rows), rows


def library_kmeans(points: DataFrame, k: int, seed: int = 1, passes: int = 10) -> DataFrame:
    """(id, cluster) by Spark's own continuous k-means."""
    model, rows = _library_model(points, k, seed, passes)
    return model.transform(rows).select("id", F.col("prediction").alias("cluster"))


def library_centers(points: DataFrame, k: int, seed: int = 1, passes: int = 10) -> list[tuple[int, list[float]]]:
    """The k centers that it finds."""
    return [(i, [float(v) for v in c]) for i, c in enumerate(_library_model(points, k, seed, passes)[0].clusterCenters())]


def euclidean_cost(points: DataFrame, centers: DataFrame | list, p: int) -> float:
    return assign(points.withColumn("pt", F.col("pt").cast("array<double>")), centers, Euclidean(), p).agg(F.sum("d")).first()[0]
