"""Rough solutions inside one part: m centers that every later tolerance is measured against."""

from __future__ import annotations

import numpy as np

from ..functions.metrics import Metric

#: What a seeder returns: places of the centers, and each point's cost to the nearest one.
Seeds = tuple[np.ndarray, np.ndarray]


def _distances(metric: Metric, data, i: int, n: int, p: int) -> np.ndarray:
    return metric.one(data, int(i), np.arange(n), p)


def farthest(metric: Metric, data, w: np.ndarray, m: int, p: int, rng, **_) -> Seeds:
    """From the first point on, always the point farthest from the centers so far (the first on ties)."""
    n = len(w)
    picks, best = [0], _distances(metric, data, 0, n, p)
    while len(picks) < min(m, n):
        k = int(best.argmax())
        if best[k] <= 0:
            break
        picks.append(k)
        best = np.minimum(best, _distances(metric, data, k, n, p))
    return np.array(picks), best


def dsample(metric: Metric, data, w: np.ndarray, m: int, p: int, rng, repeats: int = 1, **_) -> Seeds:
    """Each next center drawn with probability in proportion to its weighted cost; the cheapest of some repeats."""
    n, kept = len(w), None
    for _r in range(repeats):
        picks = [int(rng.choice(n, p=w / w.sum()))]
        best = _distances(metric, data, picks[0], n, p)
        while len(picks) < min(m, n):
            mass = (best * w).astype(float)
            if mass.sum() <= 0:
                break
            k = int(rng.choice(n, p=mass / mass.sum()))
            picks.append(k)
            best = np.minimum(best, _distances(metric, data, k, n, p))
        if kept is None or (best * w).sum() < (kept[1] * w).sum():
            kept = np.array(picks), best
    return kept


def uniform(metric: Metric, data, w: np.ndarray, m: int, p: int, rng, **_) -> Seeds:
    picks = np.sort(rng.choice(len(w), size=min(m, len(w)), replace=False))
    return picks, metric.nearest(data, picks, np.arange(len(w)), p)[0]


def given(metric: Metric, data, w: np.ndarray, m: int, p: int, rng, places: np.ndarray | None = None, **_) -> Seeds:
    return places, metric.nearest(data, places, np.arange(len(w)), p)[0]


def local_search(metric: Metric, data, w: np.ndarray, m: int, p: int, rng, **options) -> Seeds:
    """A full sequential approximation; quadratic in the part, so for small parts only."""
    from .solve import swap_search

    picks, _ = swap_search(metric, data, w, m, p, **options)
    return picks, metric.nearest(data, picks, np.arange(len(w)), p)[0]


SEEDERS = {f.__name__: f for f in (farthest, dsample, uniform, given, local_search)}
