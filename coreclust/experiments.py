"""Workloads that hold measured figures against proven ones, compare all methods, and sweep parameters."""

from __future__ import annotations

import itertools
import math
from fractions import Fraction

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import workload_sql as Q
from .api import cluster, cluster_continuous
from .functions.metrics import Angular, Edit, Hamming, Lp, Mix, Table
from .operators import assign as A
from .operators import baseline as B
from .operators import coreset as C
from .operators import measure as M
from .operators import verify as V
from .operators.line import places
from .operators.points import by_column, by_hash, by_modulo, collapse, evenly
from .operators.solve import MOST_ON_LINE, MOST_ROWS, MOST_SUBSETS, exact, exact_line, solve
from .plans import bounds
from .plans.resolve import resolve
from .schema import ClusterSpec
from .sources.tables import table
from .workloads import L1, ORACLE_SQL, QUERIES, SQ, centers, customer, lineitem, orders, part, parted, query, spec, supplier

TENTH = Fraction(1, 10)

# ---------------------------------------------------------------- proven ratios, measured


def _line_optimum(src: str, k: int, p: int) -> str:
    """SQL of the optimum on a line: costs of all intervals of sorted points, then one layer of cuts per center."""
    if p == 1:
        cost = "iv as materialized (select a.r as a, j.r as j, (m.x * (m.r - a.r) - (m.sx - a.sx) + (j.sx - m.sx) - m.x * (j.r - m.r))::bigint as c from pre a join pre j on a.r < j.r join pre m on m.r = (a.r + j.r + 1) // 2)"
    else:
        cost = """mean as (select a.r as a, j.r as j, j.r - a.r as n, j.sx - a.sx as sx, j.sxx - a.sxx as sxx, floor((j.sx - a.sx) / (j.r - a.r))::bigint as mu from pre a join pre j on a.r < j.r),
lo as (select mean.*, x.x as lo from mean asof join (select distinct x from pre where r > 0) x on mean.mu >= x.x),
iv as materialized (select a, j, least(sxx - 2 * lo * sx + n * lo * lo, sxx - 2 * x.x * sx + n * x.x * x.x)::bigint as c from lo asof left join (select distinct x from pre where r > 0) x on lo.mu < x.x)"""
    layers = "".join(f", d{t} as materialized (select j, min(c) as c from (select j, c from d{t - 1} union all select iv.j, d{t - 1}.c + iv.c from iv join d{t - 1} on d{t - 1}.j = iv.a) group by j)" for t in range(2, k + 1))
    return f"""pts as materialized ({src}), s as (select v.x as x, row_number() over (order by v.x) as r from pts),
pre as materialized (select r, x, sum(x) over (order by r)::bigint as sx, sum(x::hugeint * x) over (order by r)::hugeint as sxx from s union all select 0, 0, 0, 0),
{cost}, d1 as materialized (select j, c from iv where a = 0){layers},
best as materialized (select c as optimum from d{k} where j = (select count(*) from pts))"""


def _holds(k: int, p: int, src: str = Q.CUSTOMER) -> str:
    return f"with {_line_optimum(src, k, p)} select optimum::bigint as optimum, true as holds from best"


def _line(pts: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Places and weights of points on a line; equal ones meet where they lie, and the number of places is checked before they come to the driver."""
    at = places(pts)
    return at.x, at.w


def _against_optimum(s: SparkSession, pts: DataFrame, cost: float, ratio: float, k: int, p: int) -> DataFrame:
    """(optimum, holds): whether a cost lies between the exact optimum and the proven multiple of it."""
    best = exact_line(*_line(pts), k, p)[1]
    return s.createDataFrame([(int(best), bool(best <= cost * (1 + 1e-9) and cost <= ratio * best * (1 + 1e-9)))], "optimum long, holds boolean")


def _certified(objective: str) -> ClusterSpec:
    """Rough solutions by local search, so beta is that search's ratio (5 or 9, over 1 - 5 / 1000 for where it stops) and every premise of the proofs holds."""
    return ClusterSpec(5, objective, TENTH, beta=Fraction(51, 10) if objective == "median" else Fraction(91, 10), seeder="local_search", strict=True)


def _guarantee(s: SparkSession, d: str, objective: str, rounds: int) -> DataFrame:
    pts, metric = collapse(customer(s, d)), L1 if objective == "median" else SQ  # equal balances as one weighted point: no cost changes
    r = cluster(pts, _certified(objective), metric, rounds=rounds, rows_per_part=2_000)
    cost = M.cost(pts, r.centers, metric, r.spec.p).first()["cost"]
    return _against_optimum(s, pts, cost, r.plan.ratio if r.plan.guarantee and not r.doubt else -1, 5, r.spec.p)


@query(_holds(5, 1))
def guarantee_median_customer(s, d):
    """Three rounds for medians, eps 1/10: the cost is within the proven ratio of the exact optimum."""
    return _guarantee(s, d, "median", 2)


@query(_holds(5, 2))
def guarantee_means_customer(s, d):
    """Three rounds for means inside the proven range of eps."""
    return _guarantee(s, d, "means", 2)


@query(_holds(5, 1))
def guarantee_fast_customer(s, d):
    return _guarantee(s, d, "median", 1)


@query(_holds(5, 2))
def guarantee_fast_means_customer(s, d):
    return _guarantee(s, d, "means", 1)


@query(_holds(5, 1))
def guarantee_continuous_customer(s, d):
    """Free centers for medians.  Their own ratio on the summary is measured against the summary's exact optimum, and the proof carries it to all points; on a line the best free centers are points."""
    pts = collapse(customer(s, d))
    r = cluster_continuous(pts, _certified("median"), L1, rows_per_part=2_000)
    free = Lp(1, exact=False)
    found = r.centers.select("center_id", "pt").collect()
    cost, on_core = (M.cost(x.withColumn("pt", F.col("pt").cast("array<double>")), [(c["center_id"], c["pt"]) for c in found], free).first()["cost"] for x in (pts, r.coreset.rows))
    alpha = on_core / exact_line(*_line(r.coreset.rows), 5, 1)[1]
    return _against_optimum(s, pts, cost, bounds.ratio_of(alpha, r.coreset.error, "median", continuous=True), 5, 1)


@query(_holds(2, 1, Q.SUPPLIER))
def multi_swap_supplier(s, d):
    """Local search with two swaps at a time on a summary small enough for them: ratio 4 instead of 5."""
    pts = supplier(s, d)
    sp = ClusterSpec(2, eps=Fraction(1, 2), m=8, seeder="dsample")
    cs = C.two_round(by_hash(pts, 2), sp, L1)
    rows, n, error, _ = C.reduce_until(cs.rows, sp, L1, 400, cs.error, C.Scratch(s, "swap"))
    found = solve(rows, 2, L1, 1, t=2)
    return _against_optimum(s, pts, M.cost(pts, found, L1).first()["cost"], bounds.ratio_of(bounds.local_search_alpha("median", 2), error, "median"), 2, 1)


@query(f"with pts as ({Q.SUPPLIER}), k as (select a.id as s1, b.id as s2, c.id as s3, a.v.x as ax, b.v.x as bx, c.v.x as cx from pts a join pts b on a.id < b.id join pts c on b.id < c.id) select min(cost)::bigint as cost from (select sum(p.w * least(abs(p.v.x - ax), abs(p.v.x - bx), abs(p.v.x - cx))) as cost from k cross join pts p group by s1, s2, s3)")
def exact_triple_supplier(s, d):
    """Three central suppliers: all sets where they may be tried, the line's optimum (the same) beyond."""
    x, w = _line(supplier(s, d))
    few = math.comb(len(x), 3) <= MOST_SUBSETS
    return s.createDataFrame([(int((exact(L1, L1.load(x[:, None].tolist()), w, 3, 1) if few else exact_line(x, w, 3, 1))[1]),)], "cost long")


# ---------------------------------------------------------------- all methods side by side


def _compared(s: SparkSession, pts: DataFrame, sp: ClusterSpec, metric, grid: tuple[int, int]) -> DataFrame:
    """(method, rows, cost, ratio_to_optimum, ratio_to_best, note) of every way to get k centers.

    A method that cannot run at this size keeps its row, without a cost and with the reason.
    """
    k, p, n = sp.k, sp.p, pts.count()
    cut = parted(pts)
    first = C.one_round(cut, sp, metric)
    seeds = [(r["id"], r["pt"]) for r in pts.select("id", "pt").orderBy(F.xxhash64("id"), "id").limit(k).collect()]
    two = C.two_round(cut, sp, metric, first=first).rows
    size = max(k, two.count())
    ways = {
        "sequential on all points": pts,
        "one round": first.rows,
        "two rounds": two,
        "weighted local centers": B.local_centers(cut, sp, metric),
        "importance sample": B.importance_sample(pts, seeds, metric, p, size),
        "shell grid": B.shell_grid(pts, seeds, metric, *grid).select("id", "w").join(pts.select("id", "pt"), "id"),
        "uniform sample": B.uniform_sample(pts, max(1, n // size)),
    }
    out = []
    for name, rows in ways.items():
        few = C.Scratch(s, "compared").write(rows.select("id", "pt", "w"), "rows")
        m = few.count()
        cost = int(M.cost(pts, solve(few, k, metric, p), metric, p).first()["cost"]) if m <= MOST_ROWS else None
        out.append((name, m, cost, None if m <= MOST_ROWS else f"more than {MOST_ROWS} rows for one task"))
    spread = B.farthest_on_parts(cut, sp, metric).select("id").join(pts, "id").select("id", "pt", F.lit(1).cast("long").alias("w"), F.lit(0).alias("part"))
    picks = B.farthest_on_parts(spread, ClusterSpec(k), metric).select(F.col("id").alias("center_id")).join(pts.select(F.col("id").alias("center_id"), "pt"), "center_id")
    out.append(("farthest first on parts", spread.count(), int(M.cost(pts, picks, metric, p).first()["cost"]), None))
    free = Lp(1, exact=False) if metric is L1 else None
    if free is not None:
        means = B.library_centers(pts, k)
        out.append(("library k-means", n, int(M.cost(pts.withColumn("pt", F.col("pt").cast("array<double>")), means, free).first()["cost"]), "free centers, made for squared distances"))
    best, why = _optimum(pts, k, metric, p, n)
    out.append(("exact optimum", n, best, why))
    least = min(c for _, _, c, _ in out if c is not None)
    ratio = lambda c, by: None if c is None or by is None else M.ratio(c, by)
    return s.createDataFrame([(a, m, c, ratio(c, best), ratio(c, least), why) for a, m, c, why in out], "method string, rows long, cost long, ratio_to_optimum double, ratio_to_best double, note string")


def _optimum(pts: DataFrame, k: int, metric, p: int, n: int) -> tuple[int | None, str | None]:
    if len(pts.first()["pt"]) == 1:
        return (int(exact_line(*_line(pts), k, p)[1]), None) if n <= MOST_ON_LINE else (None, f"more than {MOST_ON_LINE} points on a line")
    if math.comb(n, k) > MOST_SUBSETS:
        return None, f"more than {MOST_SUBSETS} sets of centers"
    rows = pts.orderBy("id").collect()
    return int(exact(metric, metric.load([r["pt"] for r in rows]), np.array([r["w"] for r in rows]), k, p)[1]), None


@query()
def baseline_costs_customer(s, d):
    return _compared(s, customer(s, d), spec(5, seeder="dsample"), L1, (5_000, 2_500))


@query()
def baseline_costs_supplier(s, d):
    return _compared(s, supplier(s, d), spec(2, 3, seeder="dsample"), L1, (5_000, 2_500))


@query()
def baseline_costs_part(s, d):
    return _compared(s, part(s, d), spec(10, 20, seeder="dsample"), L1, (200, 100))


@query()
def baseline_costs_orders(s, d):
    return _compared(s, orders(s, d), spec(10, 20, seeder="dsample"), L1, (2_000, 1_000))


# ---------------------------------------------------------------- sweeps


@query()
def eps_sweep_orders(s, d):
    """(eps, n_core, w_sum, n_dist, bound): covers of all orders by eps, and the proven size at the estimated dimension."""
    pts = orders(s, d)
    cut, dim = parted(pts, 11), A.doubling_dimension(pts, L1).agg(F.max("d_hat")).first()[0]
    out = None
    for eps in (Fraction(1, 10), Fraction(1, 4), Fraction(1, 2), Fraction(9, 10)):
        cs = C.one_round(cut, ClusterSpec(10, m=20, eps=eps, prune=True), L1)
        row = M.size(cs).select(F.lit(float(eps)).alias("eps"), "n_core", "w_sum", "n_dist")
        seeds = cs.stats.agg(F.sum("n_seed"), F.max("w_sum")).first()
        row = row.withColumn("bound", F.lit(bounds.cover_size(seeds[0], 1, float(eps), dim, seeds[1])))
        out = row if out is None else out.unionByName(row)
    return out


@query(Q.core(f"{Q.given(Q.PART, Q.L1_2D, 10)}"))
def cover_given_part(s, d):
    """Covers against a stated table of centers instead of each part's own."""
    pts = part(s, d)
    targets = s.createDataFrame(centers(pts, 10), "center_id long, pt array<bigint>")
    return C.given_targets(parted(pts), targets, spec(10), L1).rows.select("part", "id", "w")


@query()
def parts_ablation_part(s, d):
    """(variant, parts, largest, one_round, two_rounds): equal, hashed and skewed parts, and m from k to 4 k, under one and two rounds."""
    pts = part(s, d)
    kinds = table(s, d, "part").select(F.col("p_partkey").cast("long").alias("id"), "p_type")
    skewed = by_column(pts.join(kinds, "id").withColumn("k", F.when(F.col("p_type") < "M", "one").otherwise(F.col("p_type"))), F.col("k")).drop("p_type", "k")
    sp = lambda m: spec(10, m)
    ways = {"equal parts": (evenly(pts, 6), sp(20)), "hashed parts": (by_hash(pts, 6), sp(20)), "skewed parts": (skewed, sp(20))} | {f"m {m}": (by_hash(pts, 6), sp(m)) for m in (10, 20, 40)}
    out = []
    for name, (cut, way) in ways.items():
        first = C.one_round(cut, way, L1)
        two = C.two_round(cut, way, L1, first=first)
        a, b = (c.stats.agg(F.count("*"), F.max("n"), F.sum("n_core")).first() for c in (first, two))
        out.append((name, a[0], a[1], a[2], b[2]))
    return s.createDataFrame(out, "variant string, parts long, largest long, one_round long, two_rounds long")


@query()
def memory_law_orders(s, d):
    """(n, parts, max_rows, sum_rows, exponent): rows that the largest task of the first round holds, at a sixteenth, a quarter and all of the orders.

    The whole table is the last row; the smaller ones are what the law is fitted on, with
    (n/k)^(1/3) parts each.  `exponent` is the slope against the row before.
    """
    pts, out = orders(s, d), []
    for share in (16, 4, 1):
        some = pts.where(B.bucket("id", share) == 0)
        n = some.count()
        parts = resolve(n, spec(10), rounds=2).parts
        row = C.one_round(by_hash(some, parts), spec(10), L1).stats.agg(F.max(F.col("n") + F.col("n_seed")).alias("most"), F.sum("n").alias("all")).first()
        slope = math.log(row["most"] / out[-1][2]) / math.log(n / out[-1][0]) if out else None
        out.append((n, parts, row["most"], row["all"], slope))
    return s.createDataFrame(out, "n long, parts long, max_rows long, sum_rows long, exponent double")


@query()
def three_rounds_lineitem(s, d):
    """The largest table, four dimensions, all three rounds: where the dimension costs most."""
    pts = lineitem(s, d)
    r = cluster(pts, ClusterSpec(20, eps=Fraction(9, 10), m=20, seeder="dsample", prune=True), L1, validate=False)
    return r.profile().select("center_id", "n", "w", F.col("cost").cast("long").alias("cost"))


# ---------------------------------------------------------------- further metrics and operators


@query("with t as (select vec_id as id, list_transform(embedding, lambda x: x::double) as v from embeddings), cen as (select id as center_id, v as cv from t order by id limit 10), n as (select id, center_id, acos(greatest(-1, least(1, list_dot_product(v, cv) / sqrt(list_dot_product(v, v) * list_dot_product(cv, cv))))) / pi() as d from t cross join cen) select id, arg_min(center_id, (round(d, 9), center_id)) as center_id, round(min(d), 6) as d from n group by id")
def assign_angular_embeddings(s, d):
    """Nearest of ten stated centers by angle."""
    pts = table(s, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("pt"))
    return A.assign(pts, centers(pts, 10), Angular()).select("id", "center_id", F.round("d", 6).alias("d"))


@query(f"with t as ({Q.PART_CATEGORIES}), q as ({Q.PART}), pts as (select t.id, t.v as c, q.v as v from t join q using (id)), o as (select c as oc, v as ov from pts order by id limit 1) select id, (100 * {Q._d(Q.HAMMING, 'c', 'oc')} + 2 * {Q._d(Q.L1_2D, 'v', 'ov')})::bigint as d from pts cross join o")
def metric_mix_part(s, d):
    """Categories and measures under one weighted mixed metric."""
    from .workloads import part_categories

    rows = part_categories(s, d).select("id", F.col("pt").alias("c")).join(part(s, d).select("id", F.col("pt").alias("v")), "id").select("id", F.struct("c", "v").alias("pt"))
    first = rows.orderBy("id").limit(1).select(F.col("pt").alias("o"))
    mixed = Mix([(100, "c", Hamming()), (2, "v", L1)])
    return rows.join(F.broadcast(first), F.lit(True)).select("id", mixed.column(F.col("pt"), F.col("o")).cast("long").alias("d"))


@query("with e as (select n_nationkey as a, n_regionkey as r from nation), pair as (select x.a as u, y.a as v, case when x.a = y.a then 0 when x.r = y.r then 1 else 2 + abs(x.r - y.r) end as d from e x cross join e y) select c_custkey as id, d::bigint as d from customer join pair on u = c_nationkey and v = 0")
def metric_table_customer(s, d):
    """Customers' distance to nation 0 under a stated table of pairs: one step inside a region, more between regions."""
    n = table(s, d, "nation").select(F.col("n_nationkey").alias("a"), F.col("n_regionkey").alias("r"))
    x, y = n.toDF("u", "ru"), n.toDF("v", "rv")
    pairs = x.join(F.broadcast(y), F.lit(True)).select("u", "v", F.when(F.col("u") == F.col("v"), 0).when(F.col("ru") == F.col("rv"), 1).otherwise(2 + F.abs(F.col("ru") - F.col("rv"))).alias("d"))
    c = table(s, d, "customer").select(F.col("c_custkey").alias("id"), F.col("c_nationkey").cast("long").alias("a"), F.lit(0).cast("long").alias("b"))
    return Table.of(pairs).attached(c, "a", "b").select("id", F.col("d").cast("long").alias("d"))


@query("select 0::bigint as violations")
def shell_separation_customer(s, d):
    """Pairs of a cover in one shell of one target that lie closer than the shell promises: none."""
    pts = parted(customer(s, d))
    cs = C.one_round(pts, spec(5), L1)
    return V.shell_violations(cs, L1)


@query(f"with recursive {Q.one_round(Q.PART, Q.L1_2D, 20)}, co as (select distinct part, tau_id from cov_tau), c as (select co.part, pts.v from co join pts on pts.id = co.tau_id), n as (select p.id, p.part, min({Q._d(Q.L1_2D, 'p.v', 'c.v')}) as d from pts p join c using (part) group by p.id, p.part) select part, sum(d)::bigint as cost from n group by part")
def cogrouped_cost_part(s, d):
    """Every part meets the cover of its own in one co-grouped Arrow task: the cost of serving it from there."""
    pts = parted(part(s, d))
    return M.part_costs(pts, C.one_round(pts, spec(10, 20), L1), L1)


@query("with x as (select c_custkey as id, c_nationkey as nation, cast(round(c_acctbal * 100) as bigint) as x from customer) select id, rank() over w as r, dense_rank() over w as dr, ntile(4) over (partition by nation order by x, id) as q, lead(x) over (partition by nation order by x, id) as following, count(*) over (partition by nation order by x range between 50000 preceding and current row) as n_near from x window w as (partition by nation order by floor(x / 100000.0))")
def ranks_customer(s, d):
    """Ranks, quartiles and neighbours of balances inside a nation, and how many lie within 500.00 below."""
    x = table(s, d, "customer").select(F.col("c_custkey").alias("id"), F.col("c_nationkey").alias("nation"), F.round(F.col("c_acctbal") * 100).cast("long").alias("x"))
    coarse, fine = Window.partitionBy("nation").orderBy(F.floor(F.col("x") / 100000)), Window.partitionBy("nation").orderBy("x", "id")
    near = Window.partitionBy("nation").orderBy("x").rangeBetween(-50000, 0)
    return x.select("id", F.rank().over(coarse).cast("long").alias("r"), F.dense_rank().over(coarse).cast("long").alias("dr"), F.ntile(4).over(fine).cast("long").alias("q"), F.lead("x").over(fine).alias("following"), F.count("*").over(near).alias("n_near"))


@query("with a as (select c_nationkey::bigint as k from customer), b as (select s_nationkey::bigint as k from supplier) select 'both' as what, count(*) as n from (select k from a intersect select k from b) union all select 'customers only', count(*) from (select k from a except all select k from b) union all select 'either', count(*) from (select k from a union select k from b)")
def set_operations_nation(s, d):
    a, b = (table(s, d, t).select(F.col(c).cast("long").alias("k")) for t, c in (("customer", "c_nationkey"), ("supplier", "s_nationkey")))
    sets = {"both": a.intersect(b), "customers only": a.exceptAll(b), "either": a.union(b).distinct()}
    out = [x.agg(F.count("*").alias("n")).select(F.lit(name).alias("what"), "n") for name, x in sets.items()]
    return out[0].unionByName(out[1]).unionByName(out[2])
