"""Proven sizes, memory and ratios as functions of the parameters."""

from __future__ import annotations

import math


def cover_size(t: int, beta: float, eps: float, dim: float, c: float) -> float:
    """Most rows of a cover with t targets when no point is farther than c R from them."""
    return t * (16 * beta / eps) ** dim * (math.log2(max(1.0, c)) + 2)


def clique_size(eps: float, dim: float) -> float:
    """Most points of a ball of radius r that are pairwise more than eps r apart."""
    return (4 / eps) ** dim


def bounded(objective: str, eps: float) -> dict[str, float]:
    """Constants of per-part and final sets: mapping cost over the optimum, cost error of any solution, best subset."""
    if objective == "median":
        return {"part": eps, "union": 2 * eps, "sharp": eps + eps**2, "approximate": 2 * eps, "centroid": 7 * eps, "subset": 2}
    return {"part": eps**2, "union": 4 * eps**2, "sharp": 2 * eps**2 + 2 * eps**4, "approximate": 4 * eps + 4 * eps**2, "centroid": 27 * eps, "subset": 4}


def ratio(alpha: float, eps: float, objective: str = "median", rounds: int = 2, continuous: bool = False) -> tuple[float, str]:
    """Proven ratio of the final solution to the optimum, and the argument it rests on."""
    if objective == "median":
        outer, add = 1 + 2 * eps, 2 * eps
        one = (alpha * outer + add, "one round, free centers") if continuous else (2 * alpha * outer + add, "one round")
        if rounds == 1 or continuous:
            return one
        two = alpha * (1 + 7 * eps) * outer + add
        return (two, "two rounds") if two <= one[0] else (one[0], "two rounds, by the one-round argument")
    g = 4 * (eps + eps**2)
    if g >= 1:
        return math.inf, "no bound at this eps"
    one = alpha * (1 + g) / (1 - g) * (1 if continuous else 4)
    if rounds == 1 or continuous:
        return one, "one round, free centers" if continuous else "one round"
    if eps + eps**2 > 1 / 8:
        return one, "two rounds, by the one-round argument"
    two = alpha * (1 + 8 * eps + 8 * eps**2) * (1 + g) * (1 + 27 * eps)
    return (two, "two rounds") if two <= one else (one, "two rounds, by the one-round argument")


def first_error(objective: str, eps: float) -> float:
    """Bounded-coreset constant of the union that one or two rounds leave."""
    return 2 * eps if objective == "median" else 4 * eps**2


def reduced_error(objective: str, error: float, eps: float) -> float:
    """Bounded-coreset constant after a coreset with constant `error` is covered once more with `eps`.

    Medians: moved distances add.  Means: their roots do, by the relaxed triangle inequality with
    its best constant; the second move is measured on the first summary, whose cost is off by
    `error + 2 sqrt(error)` at most.
    """
    if objective == "median":
        return error + 2 * eps * (1 + error)
    return (math.sqrt(error) + math.sqrt(4 * eps**2 * (1 + error + 2 * math.sqrt(error)))) ** 2


def ratio_of(alpha: float, error: float, objective: str, continuous: bool = False) -> float:
    """Proven ratio of an alpha-approximation on any coreset with bounded constant `error`, by the one-round argument."""
    if objective == "median":
        return alpha * (1 if continuous else 2) * (1 + error) + error
    g = error + 2 * math.sqrt(error)
    return alpha * (1 if continuous else 4) * (1 + g) / (1 - g) if g < 1 else math.inf


def local_search_alpha(objective: str, t: int) -> float:
    return 3 + 2 / t if objective == "median" else 5 + 4 / t


def local_space(n: float, k: int, eps: float, beta: float, dim: float, objective: str = "median") -> float:
    """Rows of the largest task of three rounds, without the hidden constant."""
    base = 16 * beta / eps if objective == "median" else 8 * math.sqrt(2 * beta) / eps
    return n ** (2 / 3) * k ** (1 / 3) * base ** (2 * dim) * math.log(max(2, n)) ** 2


def aggregate(n: float) -> float:
    return n


def crossover(objective: str) -> float:
    """The eps from which on the one-round argument gives the smaller ratio."""
    return 1 / 7 if objective == "median" else 1 / 9
