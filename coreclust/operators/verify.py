"""Checks of the proven statements on a run's own output."""

from __future__ import annotations

from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.metrics import Metric
from ..schema import ClusterSpec
from .assign import assign
from .coreset import Coreset
from .solve import exact


def cover_slack(points: DataFrame, cs: Coreset, targets: DataFrame | list, r_num, r_den, metric: Metric) -> DataFrame:
    """(max_slack) of d(x, tau(x)) * left - right over all points: never positive for a correct cover.

    Whole numbers for exact metrics: both sides are multiplied by all denominators.
    """
    spec, p = cs.spec, cs.spec.p
    e, b = spec.eps**p, Fraction(2) * spec.beta
    reach = assign(points, targets, metric, p).select("id", F.col("d").alias("d_t"))
    both = cs.mapping.select("id", "d").join(reach, "id")
    left = F.lit(str(b.numerator * e.denominator * r_den)).cast("decimal(18,0)") if metric.exact else F.lit(float(b / e) * r_den)
    if metric.exact:
        right = F.greatest(F.lit(str(r_num)).cast("decimal(38,0)"), F.col("d_t").cast("decimal(19,0)") * F.lit(r_den)) * F.lit(e.numerator * b.denominator)
        return both.agg(F.max((F.col("d").cast("decimal(20,0)") * left - right).cast("decimal(38,0)")).cast("long").alias("max_slack"))
    return both.agg(F.max(F.col("d") * left - F.greatest(F.lit(float(r_num)), F.col("d_t") * r_den)).alias("max_slack"))


def shells(points: DataFrame, targets: DataFrame | list, metric: Metric, r: int) -> DataFrame:
    """(target, j, n): points within R of their target (j = -1), or in (2^j R, 2^(j+1) R].  Powers of two are compared, not logarithms."""
    d = assign(points, targets, metric)
    guess = F.floor(F.log2(F.col("d") / F.lit(float(r)))).cast("int")
    edge = lambda j: F.lit(float(r)) * F.pow(F.lit(2.0), j)
    j = F.when(F.col("d") <= r, -1).when(F.col("d") > edge(guess + 1), guess + 1).when(F.col("d") <= edge(guess), guess - 1).otherwise(guess)
    return d.select(F.col("center_id").alias("target"), j.cast("int").alias("j")).groupBy("target", "j").agg(F.count("*").alias("n"))


def shell_separation(core: list, targets: list, r: float, spec: ClusterSpec, metric: Metric) -> float:
    """Least ratio of a pair's distance to the separation that its shell promises; above 1 when all hold."""
    data = metric.load([x for _, x in core] + [x for _, x in targets])
    n = len(core)
    d, who = metric.nearest(data, np.arange(n, n + len(targets)), np.arange(n))
    j = np.where(d <= r, -1, np.ceil(np.log2(np.maximum(d, 1e-300) / r)) - 1)
    unit = float(spec.eps / (2 * spec.beta)) * r
    least = np.inf
    for t in range(len(targets)):
        for s in np.unique(j[who == t]):
            m = np.flatnonzero((who == t) & (j == s))
            promised = unit if s < 0 else unit * 2**s
            for k, x in enumerate(m[:-1]):
                least = min(least, float(metric.one(data, int(x), m[k + 1 :]).min()) / promised)
    return least


def shell_violations(cs: Coreset, metric: Metric) -> DataFrame:
    """(violations): pairs of a one-round cover, in one shell of one seed of their part, that lie no farther apart than the shell promises.

    Each part is one Arrow task over its own cover and seeds; a shell's pairs are looked at row
    by row and only counted.
    """
    spec = cs.spec
    tol = cs.stats.select("part", F.col("cost").alias("r"), F.col("w_sum").alias("n"))
    rows = cs.rows.select("part", F.lit(0).alias("role"), "id", "pt").unionByName(cs.seeds.select("part", F.lit(1).alias("role"), "id", "pt")).join(F.broadcast(tol), "part")

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by([("role", "ascending"), ("id", "ascending")])
        role = t.column("role").to_numpy()
        n, r = int((role == 0).sum()), Fraction(t.column("r")[0].as_py()) / t.column("n")[0].as_py()
        data = metric.joined(pa.concat_arrays(t.column("pt").chunks))
        d, who = metric.nearest(data, np.arange(n, len(role)), np.arange(n))
        shell = np.full(n, -1)
        edge, k = r, 0
        while r and (d > float(edge)).any():
            shell[d > float(edge)] = k
            edge, k = 2 * edge, k + 1
        unit, bad = spec.eps / (2 * spec.beta) * r, 0
        for target, j in {*zip(who.tolist(), shell.tolist(), strict=True)}:
            m = np.flatnonzero((who == target) & (shell == j))
            least = float(unit * 2 ** max(0, j))
            bad += sum(int((metric.one(data, int(x), m[i + 1 :]) <= least * (1 - 1e-12)).sum()) for i, x in enumerate(m[:-1]))
        return pa.table({"bad": pa.array([bad], pa.int64())})

    return rows.groupBy("part").applyInArrow(run, "bad long").agg(F.coalesce(F.sum("bad"), F.lit(0)).alias("violations"))


def beta_of(cost: float, metric: Metric, data, w: np.ndarray, k: int, p: int) -> float:
    """A rough solution's cost over the exact optimum of its part (tiny parts)."""
    best = exact(metric, data, w, k, p)[1]
    return 1.0 if cost == best else cost / best if best else float("inf")


def relaxed_triangle(metric: Metric, data, triples: np.ndarray, c: float) -> float:
    """Most by which d(x,y)^2 exceeds (1 + 1/c) d(x,z)^2 + (1 + c) d(z,y)^2 over triples."""
    out = -np.inf
    for x, y, z in triples:
        xy, xz, zy = (float(metric.one(data, int(a), np.array([b]), 2)[0]) for a, b in ((x, y), (x, z), (z, y)))
        out = max(out, xy - (1 + 1 / c) * xz - (1 + c) * zy)
    return out


def missing_from(points: DataFrame, core: DataFrame) -> DataFrame:
    """(n_missing): coreset rows that are no input points."""
    return core.join(points.select("id", F.col("pt").alias("pt2")), "id", "left_anti").agg(F.count("*").alias("n_missing"))
