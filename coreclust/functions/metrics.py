"""Metrics in two forms: a Column expression for Catalyst, and blocks of NumPy distances for tasks.

`exact` metrics have whole-number distances (or squared distances), so covers, costs and ties
come out the same on every engine.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..schema import CoreclustError


class Metric:
    """Distances d(x, y); `p` = 2 asks for d squared without a detour over roots."""

    name = "metric"
    exact = False
    vector = False

    def column(self, a: Column, b: Column) -> Column:
        raise NotImplementedError

    def power_column(self, a: Column, b: Column, p: int) -> Column:
        d = self.column(a, b)
        return d if p == 1 else d * d

    def load(self, payload: Sequence):
        """Payloads as the object that `one` reads."""
        raise NotImplementedError

    def joined(self, column: pa.Array, more: Sequence | pa.Array = ()):
        """`load` of an Arrow column with further payloads, listed or in Arrow, behind it."""
        return self.load([*column.to_pylist(), *(more.to_pylist() if isinstance(more, pa.Array) else more)])

    def distances(self, data, i: int, at: np.ndarray) -> np.ndarray:
        raise NotImplementedError

    def one(self, data, i: int, at: np.ndarray, p: int = 1) -> np.ndarray:
        """Distance (to the power p) of element i to the elements `at`."""
        d = self.distances(data, i, at)
        return d if p == 1 else d * d

    def block(self, data, sources: np.ndarray, at: np.ndarray, p: int = 1) -> np.ndarray:
        """Distances (to the power p) of each of `sources`, a row each, to the elements `at`."""
        return np.stack([self.one(data, int(s), at, p) for s in sources]) if len(sources) else np.zeros((0, len(at)))

    def nearest(self, data, sources: np.ndarray, at: np.ndarray, p: int = 1) -> tuple[np.ndarray, np.ndarray]:
        """Least distance of each of `at` to `sources`, and which source (the first on ties)."""
        best, who = None, np.zeros(len(at), np.int64)
        for k, s in enumerate(sources):
            d = self.one(data, int(s), at, p)
            if best is None:
                best = d.copy()
            else:
                less = d < best
                best[less], who[less] = d[less], k
        return (best if best is not None else np.full(len(at), np.inf)), who


class _Vector(Metric):
    vector = True

    def load(self, payload: Sequence) -> np.ndarray:
        x = np.array(payload, np.int64 if self.exact else np.float64)
        return self.prepared(x.reshape(len(payload), -1))

    def prepared(self, x: np.ndarray) -> np.ndarray:
        return x

    def joined(self, column: pa.Array, more: Sequence | pa.Array = ()) -> np.ndarray:
        """The column's values without a detour over Python objects."""
        if isinstance(more, pa.Array):
            return np.concatenate((self.joined(column), self.joined(more))) if len(column) and len(more) else self.joined(column if len(column) else more)
        x = column.flatten().to_numpy(zero_copy_only=False).astype(np.int64 if self.exact else np.float64, copy=False)
        x = self.prepared(x.reshape(len(column), -1)) if len(column) else self.load([])
        return np.concatenate((x, self.load(more))) if len(more) and len(column) else self.load(more) if len(more) else x


def _summed(data: np.ndarray, sources: np.ndarray, at: np.ndarray, f) -> np.ndarray:
    """f of the coordinates' differences, summed coordinate by coordinate, of all pairs at once."""
    x, y = data[sources], data[at]
    out = np.zeros((len(x), len(y)), data.dtype)
    for j in range(data.shape[1]):
        out += f(x[:, j, None] - y[None, :, j])
    return out


@dataclass
class Lp(_Vector):
    """Minkowski distances: p = 1 (whole numbers stay whole), any p, or infinity."""

    order: float = 1
    exact: bool = True
    name: str = field(default="lp", init=False)

    def __post_init__(self):
        if self.order < 1:
            raise CoreclustError(f"Minkowski order must be at least 1, not {self.order}")
        self.exact = self.exact and self.order in (1, float("inf"))

    def column(self, a: Column, b: Column) -> Column:
        gaps = F.zip_with(a, b, lambda x, y: F.abs(x - y))
        if self.order == float("inf"):
            return F.coalesce(F.array_max(gaps), F.lit(0))
        zero = F.lit(0).cast("long") if self.exact else F.lit(0.0)
        if self.order == 1:
            return F.aggregate(gaps, zero, lambda s, x: s + x)
        return F.pow(F.aggregate(gaps, F.lit(0.0), lambda s, x: s + F.pow(x, F.lit(self.order))), F.lit(1 / self.order))

    def distances(self, data: np.ndarray, i: int, at: np.ndarray) -> np.ndarray:
        gap = np.abs(data[at] - data[i])
        if self.order == float("inf"):
            return gap.max(1) if gap.shape[1] else np.zeros(len(at))
        return gap.sum(1) if self.order == 1 else (gap**self.order).sum(1) ** (1 / self.order)

    def block(self, data: np.ndarray, sources: np.ndarray, at: np.ndarray, p: int = 1) -> np.ndarray:
        if self.order != 1:
            return super().block(data, sources, at, p)
        d = _summed(data, sources, at, np.abs)
        return d if p == 1 else d * d


@dataclass
class Euclidean(_Vector):
    """Straight-line distance; with `exact` (whole coordinates) the squares are whole numbers."""

    exact: bool = False
    name: str = field(default="euclidean", init=False)

    def power_column(self, a: Column, b: Column, p: int) -> Column:
        zero = F.lit(0).cast("long") if self.exact else F.lit(0.0)
        s = F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), zero, lambda s, x: s + x)
        return s if p == 2 else F.sqrt(s)

    def column(self, a: Column, b: Column) -> Column:
        return self.power_column(a, b, 1)

    def one(self, data: np.ndarray, i: int, at: np.ndarray, p: int = 1) -> np.ndarray:
        gap = data[at] - data[i]
        s = np.einsum("ij,ij->i", gap, gap)
        return s if p == 2 else np.sqrt(s)

    distances = one

    def block(self, data: np.ndarray, sources: np.ndarray, at: np.ndarray, p: int = 1) -> np.ndarray:
        s = _summed(data, sources, at, np.square)
        return s if p == 2 else np.sqrt(s)


@dataclass
class Angular(_Vector):
    """Angle over pi.  One minus the cosine is no metric, so it is not offered."""

    name: str = field(default="angular", init=False)

    def column(self, a: Column, b: Column) -> Column:
        dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda u, v: u.cast("double") * v), F.lit(0.0), lambda s, u: s + u)
        cos = dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))
        return F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), cos))) / F.lit(float(np.pi))

    def prepared(self, x: np.ndarray) -> np.ndarray:
        return x / np.sqrt((x * x).sum(1, keepdims=True))

    def distances(self, data: np.ndarray, i: int, at: np.ndarray) -> np.ndarray:
        return np.arccos(np.clip(data[at] @ data[i], -1, 1)) / np.pi


@dataclass
class Jaccard(Metric):
    """One minus intersection over union of arrays as sets; two empty sets are equal."""

    name: str = field(default="jaccard", init=False)

    def column(self, a: Column, b: Column) -> Column:
        union = F.size(F.array_union(a, b))
        return F.when(union == 0, F.lit(0.0)).otherwise(1 - F.size(F.array_intersect(a, b)) / union)

    def load(self, payload: Sequence) -> tuple[np.ndarray, np.ndarray]:
        """The sets' distinct elements as numbers, one set after the other, and where each set starts."""
        sets = [dict.fromkeys(x) for x in payload]
        number: dict = {}
        return np.fromiter((number.setdefault(v, len(number)) for x in sets for v in x), np.int64, sum(map(len, sets))), np.concatenate(([0], np.cumsum([len(x) for x in sets], dtype=np.int64)))

    def distances(self, data: tuple[np.ndarray, np.ndarray], i: int, at: np.ndarray) -> np.ndarray:
        element, start = data
        held = np.zeros(int(element.max(initial=-1)) + 1, bool)
        held[element[start[i] : start[i + 1]]] = True
        size = start[at + 1] - start[at]
        ends = np.cumsum(size)
        each = np.repeat(start[at] - (ends - size), size) + np.arange(int(size.sum()))
        met = np.concatenate(([0], np.cumsum(held[element[each]])))
        common = met[ends] - met[ends - size]
        union = start[i + 1] - start[i] + size - common
        return np.where(union == 0, 0.0, 1 - common / np.maximum(union, 1))


@dataclass
class Edit(Metric):
    """Insertions, deletions and substitutions between strings."""

    exact: bool = True
    name: str = field(default="edit", init=False)

    def column(self, a: Column, b: Column) -> Column:
        return F.levenshtein(a, b).cast("long")

    def load(self, payload: Sequence[str]) -> tuple[np.ndarray, np.ndarray]:
        codes = [np.frombuffer(s.encode("utf-32-le"), np.uint32).astype(np.int64) for s in payload]
        size = np.array([len(c) for c in codes], np.int64)
        table = np.full((len(codes), max(1, int(size.max(initial=0)))), -1, np.int64)
        for k, c in enumerate(codes):
            table[k, : len(c)] = c
        return table, size

    def distances(self, data: tuple[np.ndarray, np.ndarray], i: int, at: np.ndarray) -> np.ndarray:
        table, size = data
        width = int(size[at].max(initial=0))
        other, x = table[at, :width], table[i, : size[i]]
        steps = np.arange(width + 1)
        row = np.tile(steps, (len(at), 1))
        for k, c in enumerate(x, 1):
            best = np.empty_like(row)
            best[:, 0] = k
            best[:, 1:] = np.minimum(row[:, 1:] + 1, row[:, :-1] + (other != c))
            row = np.minimum.accumulate(best - steps, axis=1) + steps  # insertions
        return row[np.arange(len(at)), size[at]]


@dataclass
class Hamming(Metric):
    """Number of positions in which two arrays of categories differ."""

    exact: bool = True
    name: str = field(default="hamming", init=False)

    def column(self, a: Column, b: Column) -> Column:
        return F.aggregate(F.zip_with(a, b, lambda x, y: F.when(x.eqNullSafe(y), 0).otherwise(1)), F.lit(0).cast("long"), lambda s, x: s + x)

    def load(self, payload: Sequence) -> np.ndarray:
        flat = np.array([str(v) for x in payload for v in x])
        return np.unique(flat, return_inverse=True)[1].reshape(len(payload), -1)

    def distances(self, data: np.ndarray, i: int, at: np.ndarray) -> np.ndarray:
        return (data[at] != data[i]).sum(1)


@dataclass
class Mix(Metric):
    """Weighted sum of metrics over the fields of a struct payload."""

    parts: list[tuple[int, str, Metric]] = field(default_factory=list)
    name: str = field(default="mix", init=False)

    def __post_init__(self):
        if any(w < 0 for w, _, _ in self.parts):
            raise CoreclustError("weights of a mixed metric must not be negative")
        self.exact = all(m.exact and float(w).is_integer() and not isinstance(m, Euclidean) for w, _, m in self.parts)

    def column(self, a: Column, b: Column) -> Column:
        return sum((F.lit(w) * m.column(a[f], b[f]) for w, f, m in self.parts[1:]), F.lit(self.parts[0][0]) * self.parts[0][2].column(a[self.parts[0][1]], b[self.parts[0][1]]))

    def load(self, payload: Sequence):
        return [m.load([x[f] for x in payload]) for _, f, m in self.parts]

    def distances(self, data, i: int, at: np.ndarray) -> np.ndarray:
        return sum(w * m.one(d, i, at) for (w, _, m), d in zip(self.parts, data, strict=True))


@dataclass
class Table(Metric):
    """A finite metric given as rows (u, v, d), such as shortest paths of a graph; payloads are node ids.

    The table is held whole by every task, so its size is checked.
    """

    pairs: dict[tuple[int, int], float] = field(default_factory=dict)
    exact: bool = True
    name: str = field(default="table", init=False)
    MOST, MOST_LITERALS = 1_000_000, 20_000

    @classmethod
    def of(cls, rows: DataFrame) -> Table:
        got = rows.select("u", "v", "d").limit(cls.MOST + 1).collect()
        if len(got) > cls.MOST:
            raise CoreclustError(f"a table metric may have {cls.MOST} pairs")
        both = {(r["u"], r["v"]): r["d"] for r in got} | {(r["v"], r["u"]): r["d"] for r in got}
        return cls(both, all(float(d).is_integer() for d in both.values()))

    def attached(self, df: DataFrame, a: str, b: str, name: str = "d") -> DataFrame:
        """`df` with the distance of its node columns `a` and `b` looked up by an equi-join on the pair."""
        rows = [(int(u), int(v), int(d) if self.exact else float(d)) for (u, v), d in self.pairs.items()]
        table = df.sparkSession.createDataFrame(rows, f"_u long, _v long, _d {'long' if self.exact else 'double'}")
        near = df.join(F.broadcast(table), (F.col(a) == F.col("_u")) & (F.col(b) == F.col("_v")), "left")
        return near.withColumn(name, F.when(F.col(a) == F.col(b), F.lit(0)).otherwise(F.col("_d"))).drop("_u", "_v", "_d")

    def column(self, a: Column, b: Column) -> Column:
        if len(self.pairs) > self.MOST_LITERALS:
            raise CoreclustError(f"{len(self.pairs)} pairs are too many for literals of a plan; use attached")
        keys = F.create_map(*[x for (u, v), d in self.pairs.items() for x in (F.lit(f"{u}:{v}"), F.lit(d))])
        return F.when(a == b, F.lit(0)).otherwise(F.element_at(keys, F.concat_ws(":", a.cast("string"), b.cast("string"))))

    def load(self, payload: Sequence[int]) -> list[int]:
        return list(payload)

    def distances(self, data: list[int], i: int, at: np.ndarray) -> np.ndarray:
        return np.array([0 if data[i] == data[j] else self.pairs[data[i], data[j]] for j in at])


def euclidean(exact: bool = False) -> Metric:
    return Euclidean(exact)


def lp(order: float = 1, exact: bool = True) -> Metric:
    return Lp(order, exact)


def angular() -> Metric:
    return Angular()


def jaccard() -> Metric:
    return Jaccard()


def edit() -> Metric:
    return Edit()


def hamming() -> Metric:
    return Hamming()


def mix(parts: list[tuple[int, str, Metric]]) -> Metric:
    return Mix(parts)


def shortest_paths(edges: DataFrame, most_nodes: int = 500) -> Metric:
    """Finite metric of a small weighted undirected graph (u, v, d), closed over paths; the number of nodes is checked."""
    rows = edges.select("u", "v", "d").limit(most_nodes**2 + 1).collect()
    nodes = sorted({x for r in rows for x in (r["u"], r["v"])})
    if len(nodes) > most_nodes:
        raise CoreclustError(f"a graph metric may have {most_nodes} nodes")
    at = {x: i for i, x in enumerate(nodes)}
    d = np.full((len(nodes), len(nodes)), np.inf)
    np.fill_diagonal(d, 0)
    for r in rows:
        i, j = at[r["u"]], at[r["v"]]
        d[i, j] = d[j, i] = min(d[i, j], r["d"])
    for k in range(len(nodes)):
        d = np.minimum(d, d[:, k : k + 1] + d[k : k + 1, :])
    whole = bool(np.all(np.isinf(d) | (d == np.floor(d))))
    value = (lambda x: int(x)) if whole else float
    return Table({(u, v): value(d[at[u], at[v]]) for u in nodes for v in nodes if np.isfinite(d[at[u], at[v]])}, whole)


def verify(points: DataFrame, metric: Metric, sample: int = 60, seed: int = 0, p: int = 1) -> DataFrame:
    """(axiom, violations) over all triples of a bounded sample of points; p = 2 shows that squares are no metric."""
    few = points.orderBy(F.xxhash64("id", F.lit(seed)), "id").limit(sample).select("id", "pt")
    pair = lambda x, y: metric.power_column(F.col(f"{x}.pt"), F.col(f"{y}.pt"), p)
    a, b, c = (F.broadcast(few).alias(x) for x in "abc")
    ab = a.join(b, F.lit(True))
    two = ab.agg(F.count_if((F.col("a.id") == F.col("b.id")) & (pair("a", "b") != 0)).alias("identity"), F.count_if(F.abs(pair("a", "b") - pair("b", "a")) > 1e-9).alias("symmetry"), F.count_if(pair("a", "b") < 0).alias("sign"))
    tri = ab.join(c, F.lit(True)).agg(F.count_if(pair("a", "c") > pair("a", "b") + pair("b", "c") + 1e-9).alias("triangle"))
    return two.select(F.explode(F.array(*[F.struct(F.lit(x).alias("axiom"), F.col(x).alias("violations")) for x in ("identity", "symmetry", "sign")])).alias("r")).select("r.*").unionByName(tri.select(F.lit("triangle").alias("axiom"), F.col("triangle").alias("violations")))
