"""Greedy ball cover of one part.

A pivot absorbs every point whose distance to it is within eps/(2 beta) times the larger of the
tolerance R and the point's own distance to the targets.  The radius belongs to the absorbed
point.  With costs to the power 2 the test is on squares with eps squared.  All figures are
whole-number ratios when the metric is exact, so no test rounds.
"""

from __future__ import annotations

from dataclasses import dataclass
from fractions import Fraction

import numpy as np

from ..functions.metrics import Metric


@dataclass
class Cover:
    pivots: np.ndarray
    tau: np.ndarray
    d: np.ndarray
    n_dist: int


def limits(d_targets: np.ndarray, r_num, r_den, eps: Fraction, beta: Fraction, p: int, exact: bool, floor: bool = True) -> tuple[object, np.ndarray]:
    """(left, right): a point q may go to a pivot at distance d when d * left <= right[q]."""
    e, b = eps**p, Fraction(2) * beta
    if not exact:
        reach = np.maximum(r_num / r_den if floor else 0.0, d_targets)
        return 1.0, float(e / b) * reach
    left = int(b.numerator * e.denominator * r_den)
    scale = int(e.numerator * b.denominator)
    top = max(int(r_num), int(r_den) * int(d_targets.max(initial=0))) * scale
    big = top >= 2**62 or left * (int(d_targets.max(initial=0)) * 4 + int(r_num) + 1) >= 2**62
    d = d_targets.astype(object) if big else d_targets.astype(np.int64)
    reach = np.maximum(d * int(r_den), int(r_num)) if floor else d * int(r_den)
    return left, reach * scale


def selection(order: str, d_targets: np.ndarray, rng) -> np.ndarray:
    """The order in which uncovered points become pivots; rows come in by id."""
    if order == "id":
        return np.arange(len(d_targets))
    if order == "random":
        return rng.permutation(len(d_targets))
    return np.lexsort((np.arange(len(d_targets)), d_targets if order == "near_first" else -d_targets))


def ball_cover(metric: Metric, data, d_targets: np.ndarray, r_num, r_den, eps: Fraction, beta: Fraction, p: int = 1, order: str = "id", rng=None, floor: bool = True, prune: bool = False) -> Cover:
    """Pivots, and for every point its pivot and the distance (to the power p) to it."""
    n = len(d_targets)
    left, right = limits(d_targets, r_num, r_den, eps, beta, p, metric.exact, floor)
    alive = selection(order, d_targets, rng)
    tau, dist = np.full(n, -1), np.zeros(n, d_targets.dtype if metric.exact else float)
    pivots, n_dist = [], 0
    if prune and n:
        return _pruned(metric, data, left, right, alive, p, tau, dist)
    while len(alive):
        k = int(alive[0])
        d = metric.one(data, k, alive, p)
        n_dist += len(alive)
        got = (d.astype(object) if right.dtype == object else d) * left <= right[alive]
        got[0] = True
        tau[alive[got]], dist[alive[got]] = k, d[got]
        pivots.append(k)
        alive = alive[~got]
    return Cover(np.array(pivots, np.int64), tau, dist, n_dist)


def _pruned(metric: Metric, data, left, right, order: np.ndarray, p: int, tau: np.ndarray, dist: np.ndarray) -> Cover:
    """Same cover: points whose distance to a common reference differs too much from the pivot's are passed over."""
    n = len(order)
    ref = metric.one(data, int(order[0]), np.arange(n), 1).astype(float)
    radius = (right / left).astype(float) ** (1 / p) * (1 + 1e-9) + 1e-12
    by = np.argsort(ref, kind="stable")
    place = np.empty(n, np.int64)
    place[by] = np.arange(n)
    free, ref_s, rad_s = np.ones(n, bool), ref[by], radius[by]
    widest, pivots, n_dist = float(radius.max()), [], n
    for k in order:
        k = int(k)
        if not free[place[k]]:
            continue
        a, b = np.searchsorted(ref_s, (ref[k] - widest, ref[k] + widest * (1 + 1e-9)))
        near = np.flatnonzero(free[a:b] & (np.abs(ref_s[a:b] - ref[k]) <= rad_s[a:b])) + a
        at = by[near]
        d = metric.one(data, k, at, p)
        n_dist += len(at)
        got = ((d.astype(object) if right.dtype == object else d) * left <= right[at]) | (at == k)
        tau[at[got]], dist[at[got]] = k, d[got]
        free[near[got]] = False
        pivots.append(k)
    return Cover(np.array(pivots, np.int64), tau, dist, n_dist)
