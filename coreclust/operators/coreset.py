"""Coresets in one and two rounds over parts.

Round 1 seeds each part, measures its tolerance and covers it, in one grouped Arrow task per
part.  Its tagged output (core, seed, stat and map rows) is written once and read for all that
follows.  Round 2 covers every part again, now against the union of the round-1 covers and the
corpus-wide tolerance.  Weights count the points that a pivot stands for.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace
from decimal import Decimal
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.metrics import Metric
from ..plans import bounds
from ..plans.resolve import ROWS
from ..schema import ClusterSpec, CoreclustError
from ..storage import Scratch
from .cover import ball_cover
from .seed import SEEDERS
from .solve import MOST_ROWS

#: What a task may be sent at once: payload rows of the round-1 union, and the bytes of their Arrow buffers.
BROADCAST_ROWS, BROADCAST_BYTES = 1_000_000, 256 << 20
#: Share of its rows to which a further reduction must bring a summary to be worth it, and what eps grows to when it does not.
SHRINKS, COARSEST = 0.7, {"median": Fraction(9, 10), "means": Fraction(7, 10)}


def _number(metric: Metric) -> T.DataType:
    return T.DecimalType(38, 0) if metric.exact else T.DoubleType()


def tagged_schema(pt: T.DataType, metric: Metric) -> T.StructType:
    n = _number(metric)
    f = lambda name, kind: T.StructField(name, kind)
    return T.StructType([f("part", T.IntegerType()), f("kind", T.StringType()), f("id", T.LongType()), f("tau_id", T.LongType()), f("pt", pt), f("w", T.LongType()), f("d", n), f("cost", n), f("n", T.LongType()), f("w_sum", T.LongType()), f("n_seed", T.LongType()), f("n_dist", T.LongType())])


class _Rows:
    """Collects tagged rows of a task and turns them into Arrow."""

    def __init__(self, schema: pa.Schema, exact: bool):
        self.schema, self.exact, self.cols = schema, exact, {f.name: [] for f in schema}

    def number(self, x):
        return Decimal(int(x)) if self.exact else float(x)

    def add(self, **row) -> None:
        for k, v in self.cols.items():
            v.append(row.get(k))

    def table(self) -> pa.Table:
        return pa.Table.from_pydict(self.cols, schema=self.schema)


def _rng(spec: ClusterSpec, part: int) -> np.random.Generator:
    return np.random.default_rng([spec.seed & 0x7FFFFFFF, part & 0x7FFFFFFF])


def _opened(t: pa.Table) -> tuple[np.ndarray, pa.Array, np.ndarray]:
    t = t.sort_by("id")
    ids = t.column("id").to_numpy()
    chunks = t.column("pt").chunks
    return ids, pa.concat_arrays(chunks) if chunks else pa.array([], t.schema.field("pt").type), t.column("w").to_numpy()


def _emit(rows: _Rows, part: int, ids, payload, w, cover, p: int, mapping: bool) -> None:
    weight = np.bincount(np.searchsorted(cover.pivots[np.argsort(cover.pivots)], cover.tau), w, len(cover.pivots)).astype(np.int64) if len(ids) else []
    for k, x in zip(np.sort(cover.pivots), weight, strict=True):
        rows.add(part=part, kind="core", id=int(ids[k]), pt=payload[int(k)].as_py(), w=int(x))
    if mapping:
        for q in range(len(ids)):
            rows.add(part=part, kind="map", id=int(ids[q]), tau_id=int(ids[cover.tau[q]]), w=int(w[q]), d=rows.number(cover.d[q]))


def first_round(t: pa.Table, part: int, metric: Metric, spec: ClusterSpec, schema: pa.Schema, mapping: bool, unique: bool = False) -> pa.Table:
    """Seeds, tolerance and cover of one part; with `unique`, ids that it holds twice are an error."""
    rows = _Rows(schema, metric.exact)
    ids, payload, w = _opened(t)
    if unique and (ids[1:] == ids[:-1]).any():
        raise CoreclustError(f"id {ids[1:][ids[1:] == ids[:-1]][0]} occurs more than once")
    data, rng = metric.joined(payload), _rng(spec, part)
    picks, d = SEEDERS[spec.seeder](metric, data, w, spec.m, spec.p, rng, **spec.options)
    cost = sum(int(a) * int(b) for a, b in zip(w, d, strict=True)) if metric.exact else float((w * d).sum())
    n = int(w.sum())
    cover = ball_cover(metric, data, d, cost, n, spec.eps, spec.beta, spec.p, spec.order, rng, spec.floor, spec.prune)
    for k in picks:
        rows.add(part=part, kind="seed", id=int(ids[k]), pt=payload[int(k)].as_py())
    _emit(rows, part, ids, payload, w, cover, spec.p, mapping)
    rows.add(part=part, kind="stat", n=len(ids), w_sum=n, cost=rows.number(cost), n_seed=len(picks), n_dist=cover.n_dist + len(picks) * len(ids), w=len(cover.pivots))
    return rows.table()


def second_round(t: pa.Table, part: int, metric: Metric, spec: ClusterSpec, schema: pa.Schema, union: dict, r_num, r_den, mapping: bool) -> pa.Table:
    """Cover of one part against the whole union and the global tolerance.

    The distance to the part's own pivots bounds the distance to the union from above; where it
    is within the tolerance already, the rest of the union cannot change the test, and is not
    looked at.
    """
    rows = _Rows(schema, metric.exact)
    ids, payload, w = _opened(t)
    n, rng = len(ids), _rng(spec, part)
    data = metric.joined(payload, union["pt"])
    own = np.flatnonzero(union["part"] == part)
    every = np.arange(n)
    d, _ = metric.nearest(data, own + n, every, spec.p)
    n_dist = n * len(own)
    outside = np.flatnonzero(d.astype(object) * int(r_den) > int(r_num) if metric.exact and len(own) else d * r_den > r_num)
    if len(outside):
        rest = np.setdiff1d(np.arange(len(union["pt"])), own)
        far, _ = metric.nearest(data, rest + n, outside, spec.p)
        if not len(own):
            d = far
        elif len(rest):
            d[outside] = np.minimum(d[outside], far)
        n_dist += len(outside) * len(rest)
    cover = ball_cover(metric, data, d, r_num, r_den, spec.eps, spec.beta, spec.p, spec.order, rng, spec.floor, spec.prune)
    _emit(rows, part, ids, payload, w, cover, spec.p, mapping)
    rows.add(part=part, kind="stat", n=n, w_sum=int(w.sum()), cost=rows.number(0), n_seed=len(union["pt"]), n_dist=cover.n_dist + n_dist, w=len(cover.pivots))
    return rows.table()


def _arrow(schema: T.StructType) -> pa.Schema:
    from pyspark.sql.pandas.types import to_arrow_schema

    return to_arrow_schema(schema)


def _grouped(parted: DataFrame, schema: T.StructType, task) -> DataFrame:
    def run(key, table):
        return task(table.select(["id", "pt", "w"]), key[0].as_py())

    return parted.select("part", "id", "pt", "w").groupBy("part").applyInArrow(run, schema)


#: Parts of one input split are numbered in steps of this.
SPLITS = 1 << 20


def _split(pts: DataFrame, schema: T.StructType, task, rows: int = ROWS) -> DataFrame:
    """Input splits as parts, a split of more than `rows` points as several: no point is shuffled."""

    def run(batches):
        held, n, k, split = [], 0, 0, TaskContext.get().partitionId()
        for b in batches:
            while b.num_rows:
                part, b = b.slice(0, rows - n), b.slice(rows - n)
                held.append(part)
                n += part.num_rows
                if n == rows:
                    yield from task(pa.Table.from_batches(held), split + k * SPLITS).to_batches()
                    held, n, k = [], 0, k + 1
        if n:
            yield from task(pa.Table.from_batches(held), split + k * SPLITS).to_batches()

    return pts.select("id", "pt", "w").mapInArrow(run, schema)


@dataclass
class Coreset:
    """A weighted summary: `tagged` rows as written, and views of them."""

    tagged: DataFrame
    spec: ClusterSpec
    rounds: int
    #: Further reductions of the first union before it was sent out, and the constant that they left it with.
    reduced: int = 0
    union_error: float | None = None

    @property
    def error(self) -> float:
        """Bounded-coreset constant of these rows, as proven for certified rough solutions."""
        eps = float(self.spec.eps)
        if not self.reduced:
            return bounds.first_error(self.spec.objective, eps)
        return eps * (1 + self.union_error / 2) if self.spec.p == 1 else eps**2 * (2 + self.union_error / 2)

    @property
    def rows(self) -> DataFrame:
        return self.tagged.where("kind = 'core'").select("part", "id", "pt", "w", F.lit(self.rounds).alias("round"))

    @property
    def stats(self) -> DataFrame:
        return self.tagged.where("kind = 'stat'").select("part", "n", "w_sum", "cost", "n_seed", F.col("w").alias("n_core"), "n_dist")

    @property
    def seeds(self) -> DataFrame:
        return self.tagged.where("kind = 'seed'").select("part", "id", "pt")

    @property
    def mapping(self) -> DataFrame:
        return self.tagged.where("kind = 'map'").select("id", "part", "tau_id", "w", "d")


def one_round(points: DataFrame, spec: ClusterSpec, metric: Metric, mapping: bool = False, scratch: Scratch | None = None, unique: bool = False) -> Coreset:
    """Cover of every part.  `points` with a column `part` are grouped by it; without, input splits are the parts.  `unique` looks for repeated ids in each part."""
    scratch = scratch or Scratch(points.sparkSession, "coreset")
    schema = tagged_schema(points.schema["pt"].dataType, metric)
    arrow = _arrow(schema)

    def task(t: pa.Table, part: int) -> pa.Table:
        return first_round(t, part, metric, spec, arrow, mapping, unique)

    run = _grouped if "part" in points.columns else _split
    return Coreset(scratch.write(run(points, schema, task), "round1"), spec, 1)


def tolerance(first: Coreset) -> tuple[object, int]:
    """Global R (or R squared) as a ratio: summed costs of the parts over summed weights."""
    got = first.stats.agg(F.sum("cost").alias("cost"), F.sum("w_sum").alias("n")).first()
    cost = got["cost"] or 0
    return (int(cost) if isinstance(cost, Decimal) else cost), int(got["n"] or 1)


def _union(rows: DataFrame, most_rows: int, most_bytes: int) -> tuple[tuple[np.ndarray, pa.Array] | None, int]:
    """Parts and payloads of a cover in the order of ids, or None where they are more than a task may be sent; and how many rows may be."""
    kind = rows.schema["pt"].dataType
    wide = F.length(F.col("pt").cast("string")) if not isinstance(kind, T.ArrayType) or isinstance(kind.elementType, T.StringType) else F.size("pt") * 8
    size = rows.agg(F.count("*").alias("n"), F.coalesce(F.sum(wide), F.lit(0)).alias("bytes")).first()
    if size["n"] > most_rows or size["bytes"] > most_bytes:
        return None, max(1, min(most_rows, most_bytes * size["n"] // max(1, size["bytes"])))
    got = rows.select("part", "id", "pt").toArrow().sort_by([("part", "ascending"), ("id", "ascending")])
    pt = got.column("pt")
    return (got.column("part").to_numpy().astype(np.int64), pa.concat_arrays(pt.chunks) if pt.num_chunks else pa.array([], pt.type)), size["n"]


def two_round(points: DataFrame, spec: ClusterSpec, metric: Metric, mapping: bool = False, scratch: Scratch | None = None, first: Coreset | None = None, broadcast_rows: int = BROADCAST_ROWS, broadcast_bytes: int = BROADCAST_BYTES) -> Coreset:
    """Second cover against the union of the first covers.

    A union beyond the limits is covered again until it may be broadcast, which `error` of the
    result carries; where covers no longer shrink it, the run says so instead of sending more.
    """
    spark = points.sparkSession
    scratch = scratch or Scratch(spark, "coreset")
    first = first or one_round(points, spec, metric, scratch=scratch)
    r_num, r_den = tolerance(first)
    rows, reduced, error = first.rows, 0, first.error
    sent, most = _union(rows, broadcast_rows, broadcast_bytes)
    if sent is None:
        rows, n, error, reduced = reduce_until(rows, spec, metric, most, error, scratch)
        sent, _ = _union(rows, broadcast_rows, broadcast_bytes)
        if sent is None:
            raise CoreclustError(f"the union still has {n} rows, more than tasks may be sent, and further covers do not shrink it: use one round, or a larger eps")
    union = spark.sparkContext.broadcast({"part": sent[0], "pt": sent[1]})
    schema = tagged_schema(points.schema["pt"].dataType, metric)
    arrow = _arrow(schema)

    def task(t: pa.Table, part: int) -> pa.Table:
        return second_round(t, part, metric, spec, arrow, union.value, r_num, r_den, mapping)

    run = _grouped if "part" in points.columns else _split
    return Coreset(scratch.write(run(points, schema, task), "round2"), spec, 2, reduced, error)


def given_targets(points: DataFrame, targets: DataFrame, spec: ClusterSpec, metric: Metric, mapping: bool = False, scratch: Scratch | None = None, most: int = BROADCAST_ROWS) -> Coreset:
    """One-round cover of every part against a table of centers (center_id, pt), with the part's own tolerance to them.  Their number is checked."""
    scratch = scratch or Scratch(points.sparkSession, "coreset")
    got = targets.select("center_id", "pt").orderBy("center_id").limit(most + 1).toArrow()
    if not 0 < got.num_rows <= most:
        raise CoreclustError(f"{got.num_rows} given centers; between 1 and {most} are needed")
    sent = points.sparkSession.sparkContext.broadcast(pa.concat_arrays(got.column("pt").chunks))
    schema = tagged_schema(points.schema["pt"].dataType, metric)
    arrow = _arrow(schema)

    def task(t: pa.Table, part: int) -> pa.Table:
        rows = _Rows(arrow, metric.exact)
        ids, payload, w = _opened(t)
        data, n = metric.joined(payload, sent.value), len(ids)
        d, _ = metric.nearest(data, np.arange(n, n + len(sent.value)), np.arange(n), spec.p)
        cost = sum(int(a) * int(b) for a, b in zip(w, d, strict=True)) if metric.exact else float((w * d).sum())
        cover = ball_cover(metric, data, d, cost, int(w.sum()), spec.eps, spec.beta, spec.p, spec.order, _rng(spec, part), spec.floor, spec.prune)
        _emit(rows, part, ids, payload, w, cover, spec.p, mapping)
        rows.add(part=part, kind="stat", n=n, w_sum=int(w.sum()), cost=rows.number(cost), n_seed=len(sent.value), n_dist=cover.n_dist + n * len(sent.value), w=len(cover.pivots))
        return rows.table()

    run = _grouped if "part" in points.columns else _split
    return Coreset(scratch.write(run(points, schema, task), "given"), spec, 1)


def union(coresets: list[Coreset]) -> DataFrame:
    """Rows of several coresets as one: parts are numbered anew so that they stay apart."""
    out = None
    for k, c in enumerate(coresets):
        rows = c.rows.withColumn("part", F.hash(F.lit(k), "part"))
        out = rows if out is None else out.unionByName(rows)
    return out


def reduce_again(cs: Coreset | DataFrame, spec: ClusterSpec, metric: Metric, scratch: Scratch | None = None, rows_per_part: int | None = None) -> Coreset:
    """A weighted coreset covered once more, over as few parts as a task's memory allows; `bounds.reduced_error` has what that costs.

    Parts that are seeded by local search hold half of what that takes at most, as hashed parts differ in size.
    """
    rows_per_part = rows_per_part or (MOST_ROWS // 2 if spec.seeder == "local_search" else ROWS)
    rows = cs.rows if isinstance(cs, Coreset) else cs
    n = rows.count()
    if not n:
        raise CoreclustError("nothing to reduce")
    parts = max(1, -(-n // rows_per_part))
    pts = rows.select("id", "pt", "w").withColumn("part", F.pmod(F.xxhash64("id"), F.lit(parts)).cast("int"))
    return one_round(pts, spec, metric, scratch=scratch)


def reduce_until(rows: DataFrame, spec: ClusterSpec, metric: Metric, most: int, error: float, scratch: Scratch, allowed: Callable[[float], bool] = lambda _: True) -> tuple[DataFrame, int, float, int]:
    """(rows, their number, error constant, reductions): covered again and again while more than `most` rows are left and covers shrink them.

    A level that does not shrink its input to the share SHRINKS is dropped, and the next one
    tried with twice the eps, up to the coarsest that has a proof.  It also ends before a level
    whose error constant is not `allowed`.
    """
    eps, n, levels = spec.eps, rows.count(), 0
    while n > most and allowed(bounds.reduced_error(spec.objective, error, float(eps))):
        level = replace(spec, eps=eps)
        less = reduce_again(rows, level, metric, scratch).rows
        m = less.count()
        if m <= SHRINKS * n or m <= most:
            rows, n, levels, error = less, m, levels + 1, bounds.reduced_error(spec.objective, error, float(eps))
        elif eps < COARSEST[spec.objective]:
            eps = min(2 * eps, COARSEST[spec.objective])
        else:
            break
    return rows, n, error, levels


def ablation_sizes(points: DataFrame, specs: dict[str, ClusterSpec], metric: Metric) -> DataFrame:
    """(variant, n_core, w_sum, n_dist) of one-round covers under several parameter sets."""
    out = None
    for name, spec in specs.items():
        s = one_round(points, spec, metric).stats.agg(F.sum("n_core").alias("n_core"), F.sum("w_sum").alias("w_sum"), F.sum("n_dist").alias("n_dist")).select(F.lit(name).alias("variant"), "*")
        out = s if out is None else out.unionByName(s)
    return out
