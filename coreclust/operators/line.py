"""Two centers of points on a line, exactly: sums over sorted places instead of sums over points for every pair."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..schema import CoreclustError
from .solve import MOST_ON_LINE, exact_line, monotone_minima, whole

#: Pairs of places that a task values at once.
PAIRS = 1 << 20


@dataclass
class Places:
    """Different places in order, with the weight, the number and the smallest id of the points there."""

    x: np.ndarray
    w: np.ndarray
    n: np.ndarray
    id: np.ndarray

    def __post_init__(self):
        x, w = whole(self.x, self.w, 1)
        self.mass, self.first = np.concatenate(([0], np.cumsum(w))), np.concatenate(([0], np.cumsum(w * x)))

    def costs(self, u: np.ndarray | int, v: np.ndarray) -> np.ndarray:
        """Summed distances of all points to the nearer of the centers u <= v, element by element."""
        x, mass, first = self.x, self.mass, self.first
        a, h, b = (np.searchsorted(x, c, side) for c, side in ((u, "left"), ((u + v) // 2, "right"), (v, "left")))
        left = u * mass[a] - first[a] + first[h] - first[a] - u * (mass[h] - mass[a])
        right = v * (mass[b] - mass[h]) - (first[b] - first[h]) + first[-1] - first[b] - v * (mass[-1] - mass[b])
        return left + right


def places(pts: DataFrame) -> Places:
    """Points on a line by place: equal ones meet where they lie, and only different places come to the driver, their number checked."""
    at = pts.groupBy(F.col("pt")[0].alias("x")).agg(F.sum("w").alias("w"), F.count("*").alias("n"), F.min("id").alias("id"))
    got = at.limit(MOST_ON_LINE + 1).toArrow()
    if got.num_rows > MOST_ON_LINE:
        raise CoreclustError(f"more than {MOST_ON_LINE} different places on a line")
    return Places(*(got.sort_by("x").column(c).to_numpy() for c in ("x", "w", "n", "id")))


def two_medians(pts: DataFrame) -> tuple[int, int, int] | None:
    """(s1, s2, cost): the cheapest pair of points; of several, the one with the smallest ids.  None where there is no pair.

    In a cheapest pair of different places each center is a median of the points before, or
    behind, some cut, and there are at most two such medians.
    """
    at = places(pts)
    if len(at.x) < 2:
        few = [r["id"] for r in pts.select("id").orderBy("id").limit(2).collect()]
        return (*few, 0) if len(few) == 2 else None
    total, j = at.mass[-1], np.arange(1, len(at.x))

    def medians(lo, hi):
        return (np.searchsorted(at.mass, (lo + hi + odd) // 2, side="left") - 1 for odd in (1, 2))

    found = [(a, b, at.costs(at.x[a], at.x[b])) for a in medians(0, at.mass[j]) for b in medians(at.mass[j], total)]
    cost = min(c.min() for *_, c in found)
    pairs = {tuple(sorted((int(at.id[a]), int(at.id[b])))) for left, right, c in found for a, b in zip(left[c == cost], right[c == cost], strict=True)}
    return *min(pairs), int(cost)


def best_among(at: Places, among: Places) -> int | None:
    """The least cost, on all points, of a pair of points of `among`."""
    c = among.x
    if among.n.sum() < 2:
        return None
    if len(c) == 1:
        return int(at.costs(c, c)[0])
    m = len(c) - 1
    return int(monotone_minima(1, m, lambda a, j: at.costs(c[a], c[j]))[0].min())


def pair_errors(spark, at: Places, core: Places) -> DataFrame:
    """(error, solutions): the largest relative error of the coreset's cost over all pairs of points, and their number.

    Pairs are valued by place, in tasks that deal the rows of the triangle of pairs; equal places
    are a pair where several points lie there.
    """
    sent, n = spark.sparkContext.broadcast((at, core)), len(at.x)
    tasks = max(1, min(n, max(spark.sparkContext.defaultParallelism, n * n // (64 * PAIRS))))

    def run(batches):
        at, core = sent.value
        worst, pairs = 0.0, 0
        for b in batches:
            for task in b.column(0).to_pylist():
                for a in range(task, n, tasks):
                    for lo in range(a, n, PAIRS):
                        v = at.x[lo : lo + PAIRS]
                        count = at.n[a] * at.n[lo : lo + PAIRS]
                        if lo == a:
                            count[0] = at.n[a] * (at.n[a] - 1) // 2
                        full, less = (x.costs(at.x[a], v).astype(float) for x in (at, core))
                        gap = np.abs(full - less)
                        gap[count == 0] = 0
                        worst = max(worst, float(np.divide(gap, full, out=np.zeros(len(gap)), where=gap > 0).max()))
                        pairs += int(count.sum())
        yield pa.RecordBatch.from_pydict({"error": pa.array([worst]), "solutions": pa.array([pairs], pa.int64())})

    rows = spark.range(0, tasks, 1, tasks).mapInArrow(run, "error double, solutions long")
    return rows.agg(F.max("error").alias("error"), F.sum("solutions").alias("solutions"))


def optimum(at: Places, k: int, p: int) -> int:
    """The least cost of k centers among the points."""
    return int(exact_line(at.x, at.w, k, p)[1])
