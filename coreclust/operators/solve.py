"""Solvers for the small weighted instance that the rounds leave, and exact optima of tiny ones."""

from __future__ import annotations

import itertools
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.metrics import Metric
from ..schema import CoreclustError
from ..storage import Scratch

#: Rows of an instance that one task may solve: distances are quadratic in it.
MOST_ROWS = 4_000
MOST_SUBSETS = 2_000_000


def matrix(metric: Metric, data, n: int, p: int) -> np.ndarray:
    if n > MOST_ROWS:
        raise CoreclustError(f"{n} rows are too many for one task ({MOST_ROWS}); reduce the coreset again")
    every = np.arange(n)
    return np.stack([metric.one(data, i, every, p) for i in range(n)]).astype(float) if n else np.zeros((0, 0))


def swap_search(metric: Metric, data, w: np.ndarray, k: int, p: int, t: int = 1, min_gain: float = 1e-3, most_passes: int = 10_000, start: np.ndarray | None = None, **_) -> tuple[np.ndarray, float]:
    """Weighted local search by swaps of up to `t` centers; stops when no swap gains `min_gain` of the cost (so the cost bounds the passes).

    Single swaps are all valued at once from each point's nearest and second nearest center.
    """
    n = len(w)
    k = min(k, n)
    d = matrix(metric, data, n, p)
    if start is None:
        picks, best = [0], d[0].copy()
        while len(picks) < k:
            j = int((best * w).argmax())
            if best[j] <= 0:
                j = next(x for x in range(n) if x not in picks)
            picks.append(j)
            best = np.minimum(best, d[j])
    else:
        picks = [int(x) for x in start]
    cost = float((d[picks].min(0) * w).sum())
    for _pass in range(most_passes):
        rows = d[picks]
        near = rows.argmin(0)
        first = rows[near, np.arange(n)]
        rows = rows.copy()
        rows[near, np.arange(n)] = np.inf
        second = rows.min(0) if k > 1 else np.full(n, np.inf)
        kept = np.minimum(d, first[None, :])  # candidate x point, all centers stay
        base = kept @ w
        change = np.minimum(d, second[None, :]) - kept
        value = np.stack([base + change[:, near == c] @ w[near == c] for c in range(k)], 1)
        value[picks] = np.inf
        i, c = np.unravel_index(int(value.argmin()), value.shape)
        if np.isfinite(value[i, c]) and value[i, c] < cost * (1 - min_gain):
            picks[c], cost = int(i), float(value[i, c])
            continue
        better = _multi_swap(d, w, picks, cost, t, min_gain) if t > 1 else None
        if better is None:
            break
        picks, cost = better
    return np.sort(np.array(picks)), float((d[picks].min(0) * w).sum()) if n else 0.0


def _multi_swap(d: np.ndarray, w: np.ndarray, picks: list[int], cost: float, t: int, min_gain: float):
    n, k = len(w), len(picks)
    if math.comb(k, t) * math.comb(n - k, t) > MOST_SUBSETS:
        raise CoreclustError(f"too many swaps of {t} centers among {n} rows")
    rest = [x for x in range(n) if x not in picks]
    for out in itertools.combinations(range(k), t):
        stay = [picks[c] for c in range(k) if c not in out]
        left = d[stay].min(0) if stay else np.full(n, np.inf)
        for new in itertools.combinations(rest, t):
            value = float((np.minimum(left, d[list(new)].min(0)) * w).sum())
            if value < cost * (1 - min_gain):
                return [*stay, *new], value
    return None


def exact(metric: Metric, data, w: np.ndarray, k: int, p: int) -> tuple[np.ndarray, float]:
    """The optimum over all sets of k centers; refuses more than two million sets."""
    n = len(w)
    k = min(k, n)
    if math.comb(n, k) > MOST_SUBSETS:
        raise CoreclustError(f"{math.comb(n, k)} center sets are too many to try")
    d = matrix(metric, data, n, p)
    best = min(itertools.combinations(range(n), k), key=lambda s: (float((d[list(s)].min(0) * w).sum()), s))
    return np.array(best), float((d[list(best)].min(0) * w).sum())


#: Different places on a line whose optimum may be asked for: what the driver's arrays may hold.
MOST_ON_LINE = 2_000_000
#: Pairs that a step of the search for monotone minima values at once.
AT_ONCE = 1 << 20


def whole(x: np.ndarray, w: np.ndarray, p: int) -> tuple[np.ndarray, np.ndarray]:
    """Coordinates and weights as whole numbers: 64 bits where no sum can leave them, Python's integers beyond."""
    x, w = np.asarray(x).astype(np.int64), np.asarray(w).astype(np.int64)
    far = max((abs(int(v)) for v in (x.min(), x.max())), default=0) if len(x) else 0
    return (x, w) if 4 * far**p * sum(map(int, w)) < 2**62 else (x.astype(object), w.astype(object))


def _interval_costs(x: np.ndarray, w: np.ndarray, p: int):
    """cost(a, j): cheapest service of the sorted points a..j-1 (arrays of both) by one of them, and which; whole numbers."""
    mass, first = np.concatenate(([0], np.cumsum(w))), np.concatenate(([0], np.cumsum(w * x)))
    second = np.concatenate(([0], np.cumsum(w * x * x))) if p == 2 else None

    def median(a: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        c = np.searchsorted(mass, (mass[a] + mass[j] + 1) // 2, side="left") - 1
        left = x[c] * (mass[c] - mass[a]) - (first[c] - first[a])
        return left + first[j] - first[c] - x[c] * (mass[j] - mass[c]), c

    def mean(a: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        m, s = mass[j] - mass[a], first[j] - first[a]
        up = np.clip(np.searchsorted(x, -(-s // m), side="left"), a, j - 1)
        both = np.stack((np.maximum(up - 1, a), up))
        cost = second[j] - second[a] - 2 * x[both] * s + m * x[both] * x[both]
        k = cost.argmin(0)
        return np.take_along_axis(cost, k[None], 0)[0], np.take_along_axis(both, k[None], 0)[0]

    return median if p == 1 else mean


def monotone_minima(lo: int, hi: int, value) -> tuple[np.ndarray, np.ndarray]:
    """(least, where) of value(a, j) over 0 <= a < j for j = lo..hi, whose best a moves one way with j: divide and conquer, all intervals of a level at once."""
    least, where = None, np.zeros(hi - lo + 1, np.int64)
    level = [np.array([v]) for v in (lo, hi, 0, hi - 1)]
    while len(level[0]):
        first, last, low, high = level
        j = (first + last) // 2
        size = np.minimum(high, j - 1) - low + 1
        cut = np.zeros(len(j), np.int64)
        ends = np.cumsum(size)
        at = 0
        while at < len(j):
            to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + AT_ONCE, side="right")))
            n = size[at:to]
            starts = np.cumsum(n) - n
            a = np.arange(int(n.sum())) + np.repeat(low[at:to] - starts, n)
            total = value(a, np.repeat(j[at:to], n))
            best = np.minimum.reduceat(total, starts)
            if least is None:
                least = np.zeros(hi - lo + 1, total.dtype)
            hit = np.flatnonzero(total == np.repeat(best, n))
            cut[at:to] = a[hit[np.searchsorted(hit, starts)]]
            least[j[at:to] - lo] = best
            at = to
        where[j - lo] = cut
        level = [np.concatenate(x) for x in ((first, j + 1), (j - 1, last), (low, cut), (cut, high))]
        some = level[0] <= level[1]
        level = [x[some] for x in level]
    return least, where


def exact_line(x: np.ndarray, w: np.ndarray, k: int, p: int) -> tuple[np.ndarray, float]:
    """The optimum of points on a line, centers among them: dynamic programming over sorted intervals, whose best cuts move one way, so each layer is divided and conquered."""
    at, first, where = np.unique(np.asarray(x).astype(np.int64), return_index=True, return_inverse=True)
    if len(at) > MOST_ON_LINE:
        raise CoreclustError(f"{len(at)} places on a line are too many ({MOST_ON_LINE})")
    mass, n = np.zeros(len(at), np.int64), len(at)
    np.add.at(mass, where, np.asarray(w).astype(np.int64))
    cost = _interval_costs(*whole(at, mass, p), p)
    every = np.arange(1, n + 1)
    value = np.concatenate(([0], cost(np.zeros(n, np.int64), every)[0]))
    cuts = [np.zeros(n + 1, np.int64)]
    for _ in range(1, min(k, n)):
        least, cut = monotone_minima(1, n, lambda a, j, value=value: value[a] + cost(a, j)[0])
        value = np.concatenate(([0], least))
        cuts.append(np.concatenate(([-1], cut)))
    picks, j = [], n
    for cut in reversed(cuts):
        if j > 0:
            a = int(cut[j])
            picks.append(int(first[cost(np.array([a]), np.array([j]))[1][0]]))
            j = a
    return np.sort(np.array(picks)), float(value[n])


def seed_only(metric: Metric, data, w: np.ndarray, k: int, p: int, seed: int = 0, **_) -> tuple[np.ndarray, float]:
    from .seed import dsample

    picks, d = dsample(metric, data, w, k, p, np.random.default_rng(seed))
    return picks, float((d * w).sum())


def medoids(metric: Metric, data, w: np.ndarray, k: int, p: int, most_passes: int = 50, **_) -> tuple[np.ndarray, float]:
    """Alternating assignment and best medoid of each cluster."""
    d = matrix(metric, data, len(w), p)
    picks = np.sort(seed_only(metric, data, w, k, p)[0])
    for _pass in range(most_passes):
        near = d[picks].argmin(0)
        new = np.sort([int(m[(d[np.ix_(m, m)] @ w[m]).argmin()]) if len(m := np.flatnonzero(near == c)) else picks[c] for c in range(len(picks))])
        if (new == picks).all():
            break
        picks = new
    return picks, float((d[picks].min(0) * w).sum())


def lloyd(x: np.ndarray, w: np.ndarray, k: int, passes: int = 50, seed: int = 0) -> tuple[np.ndarray, float]:
    """Continuous weighted k-means from distance-proportional seeds."""
    from ..functions.metrics import Euclidean

    c = x[seed_only(Euclidean(), x, w, k, 2, seed)[0]].astype(float)
    for _ in range(passes):
        d = ((x[:, None, :] - c[None]) ** 2).sum(2)
        near = d.argmin(1)
        mass = np.bincount(near, w, len(c))
        new = np.stack([np.bincount(near, w * x[:, j], len(c)) for j in range(x.shape[1])], 1) / np.maximum(mass, 1e-300)[:, None]
        new[mass == 0] = c[mass == 0]
        if np.allclose(new, c):
            break
        c = new
    return c, float((((x[:, None, :] - c[None]) ** 2).sum(2).min(1) * w).sum())


def weiszfeld(x: np.ndarray, w: np.ndarray, k: int, passes: int = 50, inner: int = 20, seed: int = 0) -> tuple[np.ndarray, float]:
    """Continuous weighted k-median: alternating assignment and steps towards each cluster's geometric median.

    Seeds are points, which the steps could not leave; each cluster's mean is the first stop.
    """
    from ..functions.metrics import Euclidean

    c = x[seed_only(Euclidean(), x, w, k, 1, seed)[0]].astype(float)
    cost = lambda c: float((np.sqrt(((x[:, None, :] - c[None]) ** 2).sum(2)).min(1) * w).sum())
    best, seeded, value = c.copy(), cost(c), np.inf
    for _ in range(passes):
        near = ((x[:, None, :] - c[None]) ** 2).sum(2).argmin(1)
        for j in range(len(c)):
            m = near == j
            for i in range(inner if m.any() else 0):
                pull = w[m] / np.maximum(np.sqrt(((x[m] - c[j]) ** 2).sum(1)), 1e-12) if i or value < np.inf else w[m]
                c[j] = (x[m] * pull[:, None]).sum(0) / pull.sum()
        now = cost(c)
        if now >= value * (1 - 1e-7):
            break
        if now < seeded:
            best = c.copy()
        value, seeded = now, min(now, seeded)
    return best, seeded


SOLVERS = {"local_search": swap_search, "exact": exact, "seed_only": seed_only, "medoids": medoids}


def solve(rows: DataFrame, k: int, metric: Metric, p: int, method: str = "local_search", **options) -> DataFrame:
    """(center_id, pt) chosen among the rows of a bounded coreset, in one task."""
    kind = rows.schema["pt"].dataType.simpleString()
    few = rows.select(F.lit(0).alias("g"), "id", "pt", "w")

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by("id")
        if t.num_rows > MOST_ROWS:
            raise CoreclustError(f"{t.num_rows} rows are too many for one task ({MOST_ROWS}); reduce the coreset again")
        w = np.array(t.column("w").to_pylist(), np.int64)
        picks, _ = SOLVERS[method](metric, metric.load(t.column("pt").to_pylist()), w, k, p, **options)
        got = t.take(pa.array(picks))
        return pa.table({"center_id": got.column("id"), "pt": got.column("pt")})

    return few.groupBy("g").applyInArrow(run, f"center_id long, pt {kind}")


#: Rows from which the continuous solvers pass over the rows where they lie instead of in one task; rows that their seeds are drawn from.
CONTINUOUS_ROWS, SEED_ROWS = 100_000, 20_000


def _hashed(rows: DataFrame, most: int, seed: int) -> DataFrame:
    """At most `most` rows drawn by hash, without a sort of all."""
    n = rows.count()
    share = min(1.0, 2 * most / max(n, 1))
    return rows.where(F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(1 << 30)) <= int(share * (1 << 30))).orderBy(F.xxhash64("id", F.lit(seed + 1)), "id").limit(most)


def solve_continuous(rows: DataFrame, k: int, objective: str = "means", passes: int = 50, seed: int = 0, most: int = CONTINUOUS_ROWS) -> DataFrame:
    """(center_id, pt) anywhere in the vector space.

    Up to `most` rows meet in one task.  Beyond, every pass sums up where the rows lie: only the
    k centers go out, and one partial sum per task and center comes back.
    """
    if rows.count() > most:
        return _continuous_distributed(rows, k, objective, passes, seed)

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by("id")
        x, w = np.array(t.column("pt").to_pylist(), float), np.array(t.column("w").to_pylist(), np.int64)
        c, _ = (lloyd if objective == "means" else weiszfeld)(x, w, min(k, len(x)), passes=passes, seed=seed)
        return pa.table({"center_id": pa.array(range(len(c)), pa.int64()), "pt": pa.array(c.tolist(), pa.list_(pa.float64()))})

    return rows.select(F.lit(0).alias("g"), "id", "pt", "w").groupBy("g").applyInArrow(run, "center_id long, pt array<double>")


def _continuous_distributed(rows: DataFrame, k: int, objective: str, passes: int, seed: int) -> DataFrame:
    from ..functions.metrics import Euclidean

    spark, metric = rows.sparkSession, Euclidean()
    few = _hashed(rows.select("id", "pt", "w"), SEED_ROWS, seed).toPandas()
    x, w = np.array(few["pt"].tolist(), float), few["w"].to_numpy(np.int64)
    c = x[seed_only(metric, x, w, min(k, len(x)), 2 if objective == "means" else 1, seed)[0]]
    dim, best = c.shape[1], (np.inf, c)
    for step in range(passes):
        sent = spark.sparkContext.broadcast((c, objective == "means" or not step))

        def sums(batches, sent=sent):
            c, plain = sent.value
            total, mass, cost = np.zeros(c.shape), np.zeros(len(c)), 0.0
            for b in batches:
                x, w = metric.joined(b.column(0)), b.column(1).to_numpy().astype(float)
                for at in range(0, len(x), 4096):
                    y, v = x[at : at + 4096], w[at : at + 4096]
                    d = ((y[:, None, :] - c[None]) ** 2).sum(2)
                    near = d.argmin(1)
                    d = d[np.arange(len(y)), near]
                    cost += float((v * (d if objective == "means" else np.sqrt(d))).sum())
                    v = v if plain else v / np.maximum(np.sqrt(d), 1e-12)
                    mass += np.bincount(near, v, len(c))
                    total += np.stack([np.bincount(near, v * y[:, j], len(c)) for j in range(dim)], 1)
            yield pa.RecordBatch.from_pydict({"c": pa.array(np.arange(len(c))), "mass": pa.array(mass), "total": pa.array(total.tolist(), pa.list_(pa.float64())), "cost": pa.array(np.append(cost, np.zeros(len(c) - 1)))})

        parts = rows.select("pt", "w").mapInArrow(sums, "c long, mass double, total array<double>, cost double")
        got = parts.groupBy("c").agg(F.sum("mass").alias("mass"), *[F.sum(F.col("total")[j]).alias(f"t{j}") for j in range(dim)], F.sum("cost").alias("cost")).collect()
        cost = sum(r["cost"] for r in got)
        if step > 1 and cost >= best[0] * (1 - 1e-7):
            break
        best, c = min(best, (cost, c), key=lambda b: b[0]), c.copy()
        for r in got:
            if r["mass"] > 0:
                c[r["c"]] = [r[f"t{j}"] / r["mass"] for j in range(dim)]
    return spark.createDataFrame([(i, [float(v) for v in x]) for i, x in enumerate(best[1])], "center_id long, pt array<double>")


#: Rows that a task groups at once, pivots after which it leaves the rest single, and groups that the driver may group again.
GROUP_ROWS, GROUP_PIVOTS, GROUPS = 50_000, 8_000, 50_000
#: Groups' radius as a share of the mean distance to the nearest center.
NEAR = 1 / 16


def _groups(metric: Metric, data, n: int, radius: float) -> tuple[np.ndarray, np.ndarray]:
    """(head, away): each of n rows goes to an earlier one within `radius`; after GROUP_PIVOTS heads the rest stay single, as then groups do not pay."""
    head, away, alive, heads = np.arange(n), np.zeros(n), np.arange(n), 0
    while len(alive) and heads < GROUP_PIVOTS:
        d = metric.one(data, int(alive[0]), alive, 1).astype(float)
        got = d <= radius
        got[0] = True
        head[alive[got]], away[alive[got]] = alive[0], d[got]
        alive, heads = alive[~got], heads + 1
    return head, away


def _grouped_rows(places: DataFrame, metric: Metric, radius: float, tasks: int, scratch: Scratch) -> tuple[DataFrame, DataFrame, int]:
    """Rows with the head of their group, the heads (id, pt, radius, size), and their number: grouped where they lie, and the heads once more on the driver if it may hold them."""
    kind = places.schema["pt"].dataType.simpleString()

    def run(batches):
        held, n = [], 0
        for b in itertools.chain(batches, [None]):
            while n and (b is None or n >= GROUP_ROWS):
                t = pa.Table.from_batches(held).sort_by("id").combine_chunks()
                head, away = _groups(metric, metric.joined(pa.concat_arrays(t.column("pt").chunks)), t.num_rows, radius)
                yield from t.append_column("head", t.column("id").take(pa.array(head))).append_column("away", pa.array(away)).to_batches()
                held, n = [], 0
            if b is not None and b.num_rows:
                held.append(b)
                n += b.num_rows

    rows = scratch.write(places.repartition(tasks, "id").mapInArrow(run, f"id long, pt {kind}, w long, head long, away double"), "grouped")
    size = rows.groupBy("head").agg(F.max("away").alias("radius"), F.count("*").alias("n"))
    heads = scratch.write(rows.where("id = head").select("id", "pt").join(size, F.col("id") == F.col("head")).select("id", "pt", "radius", "n"), "heads")
    count = heads.count()
    if count > GROUPS:
        return rows, heads, count
    few = heads.toArrow().sort_by([("n", "descending"), ("id", "ascending")]).combine_chunks()
    top, away = _groups(metric, metric.joined(pa.concat_arrays(few.column("pt").chunks)), count, radius)
    ids = few.column("id").to_numpy()
    first, member = np.unique(top, return_inverse=True)
    far, total = np.zeros(len(first)), np.zeros(len(first), np.int64)
    np.maximum.at(far, member, away + few.column("radius").to_numpy())
    np.add.at(total, member, few.column("n").to_numpy())
    moved = places.sparkSession.createDataFrame(pa.table({"head": ids, "top": ids[top]}))
    rows = scratch.write(rows.join(F.broadcast(moved), "head").select("id", "pt", "w", F.col("top").alias("head")), "regrouped")
    new = few.select(["id", "pt"]).take(pa.array(first)).append_column("radius", pa.array(far)).append_column("n", pa.array(total))
    return rows, scratch.write(places.sparkSession.createDataFrame(new, f"id long, pt {kind}, radius double, n long"), "heads"), len(first)


def _swap_values(rows: DataFrame, metric: Metric, p: int, centers: pa.Array, batch: pa.Array, radius: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
    """(cost, value, least): the cost of the centers, of every swap of a candidate for one of them, and a lower bound on that of anything within the candidate's radius."""
    k, size = len(centers), len(batch)
    sent = rows.sparkSession.sparkContext.broadcast((pa.concat_arrays([centers, batch]), radius * (1 + 1e-9)))

    def run(batches):
        more, reach = sent.value
        both, stay = np.zeros((size, 2, k)), 0.0
        for b in batches:
            for lo in range(0, b.num_rows, 2048):
                part = b.slice(lo, 2048)
                m, w = part.num_rows, part.column(1).to_numpy().astype(float)
                data, every = metric.joined(part.column(0), more), np.arange(m)
                d = metric.block(data, m + np.arange(k), every, p).astype(float)
                near = d.argmin(0)
                first = d[near, every]
                d[near, every] = np.inf
                second, mine = d.min(0), np.zeros((m, k))
                mine[every, near] = w
                stay += float(first @ w)
                for at in range(0, size, 64):
                    new, r = metric.block(data, m + k + np.arange(at, min(at + 64, size)), every, p).astype(float), reach[at : at + 64, None]
                    for what in range(2):
                        if what and not r.any():
                            both[at : at + 64, 1] += gained
                            break
                        if what:
                            new = np.maximum(new * (1 - 1e-12) - r, 0) if p == 1 else np.maximum(np.sqrt(new) * (1 - 1e-12) - r, 0) ** 2
                        kept = np.minimum(new, first)
                        gained = (kept @ w)[:, None] + (np.minimum(new, second) - kept) @ mine
                        both[at : at + 64, what] += gained
        yield pa.RecordBatch.from_pydict({"x": pa.array(np.append(np.arange(size), -1)), "v": pa.array([*both.reshape(size, 2 * k).tolist(), [stay] * (2 * k)], pa.list_(pa.float64()))})

    got = rows.select("pt", "w").mapInArrow(run, "x long, v array<double>").select("x", F.posexplode("v").alias("c", "v")).groupBy("x", "c").agg(F.sum("v").alias("v")).toArrow()
    out = np.zeros((size + 1, 2 * k))
    out[got.column("x").to_numpy(), got.column("c").to_numpy()] = got.column("v").to_numpy()
    sent.destroy()
    return float(out[-1, 0]), out[:-1, :k], out[:-1, k:]


def local_search_distributed(rows: DataFrame, k: int, metric: Metric, p: int, passes: int = 2_000, block: int = 2_000, min_gain: float = 1e-3, start_rows: int = 2_000) -> DataFrame:
    """Local search over all rows when the instance outgrows one task: the same single swaps as `swap_search`, block after block.

    Every row is a candidate; rows of equal payload are one, of the smallest id and the summed
    weight.  Candidates are grouped around heads.  A block of heads goes out with the k centers;
    its swaps are valued where the rows lie, from each point's nearest and second nearest center.
    By the triangle inequality the same pass bounds from below what any member of a group could
    bring the cost to, so only members of groups whose bound leaves room for a gain are valued
    themselves.  The best of a block is taken if it gains `min_gain` of the cost; the search ends
    when no head and no such member brings one.  Centers start from a local search on a bounded
    sample.  After `passes` swaps it stops anyway and raises, as the result would be no local optimum.
    """
    from .points import collapse

    scratch = Scratch(rows.sparkSession, "swaps")
    places = scratch.write(collapse(rows), "places")
    n = places.count()
    few = _hashed(places, start_rows, 1).orderBy("id").toArrow()
    w, cores = few.column("w").to_numpy(), rows.sparkSession.sparkContext.defaultParallelism
    start = pa.concat_arrays(few.column("pt").chunks)
    picks, cost = swap_search(metric, metric.joined(start), w, k, p)
    ids, centers = few.column("id").to_numpy()[picks], start.take(pa.array(picks))
    grouped, heads, count = _grouped_rows(places, metric, NEAR * (cost / w.sum()) ** (1 / p), max(cores, -(-n // (2 * GROUP_ROWS))), scratch)
    block = max(1, min(block, 1_000_000 // len(ids)))
    gains = 0

    def improved(batch: pa.Table) -> pa.Table | None:
        """Takes the best swap of a block; without a gain, the candidates whose groups leave room for one."""
        nonlocal ids, centers, gains
        batch = batch.filter(pa.array(~np.isin(batch.column("id").to_numpy(), ids) | (batch.column("n").to_numpy() > 1)))
        if not batch.num_rows:
            return batch
        own = batch.column("id").to_numpy()
        pt = pa.concat_arrays(batch.column("pt").chunks)
        now, value, least = _swap_values(grouped, metric, p, centers, pt, batch.column("radius").to_numpy())
        value[np.isin(own, ids)] = np.inf
        x, c = np.unravel_index(int(value.argmin()), value.shape)
        if not value[x, c] < now * (1 - min_gain):
            return batch.filter(pa.array((least.min(1) < now * (1 - min_gain)) & (batch.column("n").to_numpy() > 1)))
        ids = np.where(np.arange(len(ids)) == c, own[x], ids)
        centers = pa.concat_arrays([pt.slice(x, 1) if j == c else centers.slice(j, 1) for j in range(len(ids))])
        gains += 1
        if gains >= passes:
            raise CoreclustError(f"no local optimum after {passes} swaps")
        return None

    def dealt(df: DataFrame, blocks: int, at: int) -> pa.Table:
        return df.where(F.pmod(F.xxhash64("id", F.lit(2)), F.lit(blocks)) == at).select("id", "pt", "radius", "n").toArrow().sort_by("id").combine_chunks()

    blocks, idle, at, open_ = max(1, -(-count // block)), 0, 0, []
    while idle < blocks:
        room = improved(dealt(heads, blocks, at))
        at, idle, open_ = (at + 1) % blocks, 0 if room is None else idle + 1, [] if room is None else [*open_, room.select(["id", "n"])]
        if idle < blocks or not any(t.num_rows for t in open_):
            continue
        room = pa.concat_tables(open_)
        chosen = rows.sparkSession.createDataFrame(room.select(["id"]).rename_columns(["head"]))
        members = grouped.where("id <> head").join(F.broadcast(chosen), "head").select("id", "pt", F.lit(0.0).alias("radius"), F.lit(1).alias("n"))
        for b in range(more := max(1, -(-int(room.column("n").to_numpy().sum()) // block))):
            if improved(dealt(members, more, b)) is None:
                idle, open_ = 0, []
                break
    return places.where(F.col("id").isin([int(x) for x in ids])).select(F.col("id").alias("center_id"), "pt")


def local_search(rows: DataFrame, k: int, metric: Metric, p: int, most: int = MOST_ROWS, **options) -> DataFrame:
    """(center_id, pt) by single swaps over all rows: in one task up to `most` rows, where they lie beyond."""
    return solve(rows, k, metric, p, **options) if rows.count() <= most else local_search_distributed(rows, k, metric, p, **options)
