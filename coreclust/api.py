"""End-to-end clustering: summarise in rounds, solve the summary, assign everything."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .functions.metrics import Metric
from .operators import measure
from .operators.assign import assign, profile
from .operators.coreset import Coreset, one_round, reduce_until, two_round
from .operators.points import by_hash, collapse, evenly
from .operators.solve import MOST_ROWS, local_search_distributed, solve, solve_continuous
from .plans import bounds
from .plans.resolve import ROWS, Plan, resolve
from .schema import ClusterSpec, counted_points
from .storage import Scratch


@dataclass
class ClusterResult:
    centers: DataFrame
    coreset: Coreset
    plan: Plan
    points: DataFrame
    metric: Metric
    spec: ClusterSpec
    #: Why the plan's proof does not hold for these centers, if so.
    doubt: str | None = None

    def assigned(self) -> DataFrame:
        return assign(self.points, self.centers, self.metric, self.spec.p, keep=("w",))

    def profile(self) -> DataFrame:
        return profile(self.assigned(), self.centers)

    def report(self) -> DataFrame:
        """(key, value, note): what was proven and what was measured, side by side."""
        size = measure.size(self.coreset).first()
        cost = measure.cost(self.points, self.centers, self.metric, self.spec.p).first()["cost"]
        dense = size["n_core"] > 0.5 * size["n"]
        rows = [
            ("proven_ratio", math.inf if self.doubt else float(self.plan.ratio), f"no proven ratio: {self.doubt}" if self.doubt else self.plan.why),
            ("guarantee", float(self.plan.guarantee and not self.doubt), f"no proven ratio: {self.doubt}" if self.doubt else f"holds if the rough solutions are within beta = {self.spec.beta} of the optimum"),
            ("cost", float(cost or 0), f"k-{self.spec.objective} cost of all points"),
            ("core_rows", float(size["n_core"]), "no compression at this eps and dimension" if dense else "rows of the summary"),
            ("compression", float(size["compression"] or 0), "points per summary row"),
            ("parts", float(self.plan.parts), f"{self.plan.rows_per_part} points each"),
            ("distances", float(size["n_dist"]), "distance evaluations of the last round"),
        ]
        return self.points.sparkSession.createDataFrame(rows, "key string, value double, note string")


#: Solvers that are no approximation algorithms, whatever coreset they get.
HEURISTICS = {"seed_only": "seeding alone has no ratio for k centers", "medoids": "alternating medoids have no ratio", "continuous": "alternating passes have no ratio"}


def alpha_of(spec: ClusterSpec, method: str = "local_search", t: int = 1) -> float:
    """Ratio of a solver on the weighted instance, run until no swap gains anything; infinite for heuristics."""
    return 1.0 if method == "exact" else math.inf if method in HEURISTICS else bounds.local_search_alpha(spec.objective, t)


def _stopping(spec: ClusterSpec, method: str, options: dict) -> float:
    """Factor on a local search's ratio for stopping at swaps that gain less than `min_gain` of the cost: the proof adds up k of them.  By default at most 1 %."""
    if method != "local_search":
        return 1.0
    left = 1 - spec.k * options.setdefault("min_gain", min(1e-3, 0.01 / spec.k))
    return 1 / left if left > 0 else math.inf


def _prepared(points: DataFrame, spec: ClusterSpec, alpha: float, rounds: int | None, rows: int, continuous: bool, validate: bool, even: bool) -> tuple[DataFrame, Plan]:
    """Points in parts, and the plan.  They are counted and checked in one pass; repeated ids meet in one part, which looks for them."""
    pts = points if "w" in points.columns else points.withColumn("w", F.lit(1).cast("long"))
    pts, n = counted_points(pts) if validate else (pts, pts.count())
    plan = resolve(n, spec, alpha, rounds, rows, continuous)
    return (pts if "part" in pts.columns else (evenly if even else by_hash)(pts, plan.parts)), plan


def _fitted(cs: Coreset, plan: Plan, spec: ClusterSpec, metric: Metric, alpha: float, scratch: Scratch, most: int, continuous: bool = False) -> tuple[DataFrame, int, Plan]:
    """The summary, covered again until at most `most` rows are left or covers no longer shrink it, and the plan with the ratio that this leaves.

    Equal payloads become one row first, which costs nothing; a plan with a proven ratio is not reduced beyond it.
    """
    rows = cs.rows
    if rows.count() > most:
        rows = scratch.write(collapse(rows), "places")
    proven = lambda error: not plan.guarantee or math.isfinite(bounds.ratio_of(alpha, error, spec.objective, continuous))
    rows, n, error, levels = reduce_until(rows, spec, metric, most, cs.error, scratch, proven)
    levels += cs.reduced
    if not levels:
        return rows, n, plan
    ratio = bounds.ratio_of(alpha, error, spec.objective, continuous)
    return rows, n, replace(plan, ratio=ratio, why=f"one round{', free centers' * continuous}, after {levels} further reduction{'s' * (levels > 1)}", guarantee=plan.guarantee and math.isfinite(ratio))


def cluster(points: DataFrame, spec: ClusterSpec, metric: Metric, alpha: float | None = None, rounds: int = 2, rows_per_part: int = ROWS, method: str = "local_search", validate: bool = True, even: bool = False, most_rows: int = MOST_ROWS, **options) -> ClusterResult:
    """Three rounds: cover, cover against the union, solve.

    `alpha` is the solver's ratio, by default what is proven for `method`; `even` deals parts of
    equal size instead of equal hash ranges.  A summary of more than `most_rows` rows is covered
    again, with the error that this adds; one that covers do not shrink, or only at the cost of
    the proven ratio, is solved where it lies, by the same local search over all its rows.
    """
    scratch = Scratch(points.sparkSession, "cluster")
    alpha = alpha_of(spec, method, options.get("t", 1)) * _stopping(spec, method, options) if alpha is None else alpha
    pts, plan = _prepared(points, spec, alpha, rounds, rows_per_part, False, validate, even)
    first = one_round(pts, spec, metric, scratch=scratch, unique=validate)
    cs = two_round(pts, spec, metric, scratch=scratch, first=first) if rounds == 2 else first
    rows, n, plan = _fitted(cs, plan, spec, metric, alpha, scratch, most_rows)
    if n <= most_rows:
        centers, doubt = scratch.write(solve(rows, spec.k, metric, spec.p, method, **options), "centers"), HEURISTICS.get(method)
    else:
        centers, doubt = local_search_distributed(rows, spec.k, metric, spec.p, min_gain=options.get("min_gain", 1e-3)), None
        if method != "local_search" or options.get("t", 1) > 1:
            plan = replace(plan, why=f"{plan.why}; solved by single swaps, as the summary is too large for {method}")
            doubt = "the given method's ratio is not that of single swaps"
    return ClusterResult(centers, cs, plan, pts, metric, spec, doubt)


def cluster_fast(points: DataFrame, spec: ClusterSpec, metric: Metric, **options) -> ClusterResult:
    """One coreset round, then solve: the weaker ratio for one pass over the data."""
    return cluster(points, spec, metric, rounds=1, **options)


def cluster_continuous(points: DataFrame, spec: ClusterSpec, metric: Metric, alpha: float | None = None, rows_per_part: int = ROWS, validate: bool = True, even: bool = False, **options) -> ClusterResult:
    """One coreset round, then centers anywhere in the vector space.

    The built-in solvers are heuristics, so no ratio is proven; `alpha` states the ratio of the
    centers on the summary where the caller knows one.
    """
    scratch = Scratch(points.sparkSession, "cluster")
    known = math.inf if alpha is None else alpha
    pts, plan = _prepared(points, spec, known, 1, rows_per_part, True, validate, even)
    cs = one_round(pts, spec, metric, scratch=scratch, unique=validate)
    centers = scratch.write(solve_continuous(cs.rows, spec.k, spec.objective, **options), "centers")
    return ClusterResult(centers, cs, plan, pts.withColumn("pt", F.col("pt").cast("array<double>")), metric, spec, HEURISTICS["continuous"] if alpha is None else None)
