"""The engine's queries over the given tables, and their SQL counterparts."""

from __future__ import annotations

from collections.abc import Callable
from fractions import Fraction

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import workload_sql as Q
from .api import cluster
from .functions.metrics import Edit, Euclidean, Hamming, Jaccard, Lp, verify
from .operators import assign as A
from .operators import baseline as B
from .operators import coreset as C
from .operators import measure as M
from .operators import verify as V
from .operators.line import best_among, optimum, pair_errors, places, two_medians
from .operators.points import by_modulo, points, quantised
from .operators.solve import exact, exact_line
from .plans.resolve import ROWS, part_count
from .schema import ClusterSpec
from .sources.tables import stream, table, with_event_time
from .storage import Scratch
from .streaming.windows import window_coreset

L1, SQ, HAM, EDIT, JAC = Lp(1), Euclidean(exact=True), Hamming(), Edit(), Jaccard()
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLE_SQL[f.__name__] = sql
        return f

    return keep


# ---------------------------------------------------------------- instances


def customer(s: SparkSession, d: str) -> DataFrame:
    return points(table(s, d, "customer"), "c_custkey", F.array(quantised("c_acctbal", 100)))


def supplier(s: SparkSession, d: str) -> DataFrame:
    return points(table(s, d, "supplier"), "s_suppkey", F.array(quantised("s_acctbal", 100)))


def _part_vector():
    return F.array((F.col("p_size") * 10).cast("long"), quantised("p_retailprice", 10))


def part(s: SparkSession, d: str) -> DataFrame:
    return points(table(s, d, "part"), "p_partkey", _part_vector())


def part_categories(s: SparkSession, d: str) -> DataFrame:
    return points(table(s, d, "part"), "p_partkey", F.array("p_brand", "p_type", F.col("p_size").cast("string")))


def part_weighted(s: SparkSession, d: str) -> DataFrame:
    n = table(s, d, "lineitem").groupBy(F.col("l_partkey").alias("p_partkey")).agg(F.count("*").alias("n"))
    return points(table(s, d, "part").join(n, "p_partkey", "left"), "p_partkey", _part_vector(), F.greatest(F.lit(1), F.coalesce("n", F.lit(0))))


def orders(s: SparkSession, d: str) -> DataFrame:
    day = F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date")) * 10
    return points(table(s, d, "orders"), "o_orderkey", F.array(quantised(F.col("o_totalprice") / 100), day.cast("long")))


def _event_vector():
    seconds = F.hour("ts") * 3600 + F.minute("ts") * 60 + F.second("ts")
    return F.array(quantised("value", 100), F.floor(seconds / 36).cast("long"))


#: Parts of one day are numbered in steps of this.
DAYS = 100_000


def events(s: SparkSession, d: str) -> DataFrame:
    """Days as parts; a day of more events than a task holds is dealt to several, which are the same modulo DAYS."""
    e = table(s, d, "events").select(F.col("event_id").alias("id"), _event_vector().alias("pt"), F.lit(1).cast("long").alias("w"), F.unix_date(F.col("ts").cast("date")).alias("day"))
    sizes = e.groupBy("day").agg(F.ceil(F.count("*") / ROWS).cast("int").alias("tasks"))
    return e.join(F.broadcast(sizes), "day").select("id", "pt", "w", (F.col("day") + F.pmod(F.xxhash64("id"), F.col("tasks")) * DAYS).cast("int").alias("part"))


def lineitem(s: SparkSession, d: str) -> DataFrame:
    """No key in this table: equal feature rows are one weighted point."""
    from .operators.points import by_content

    return by_content(table(s, d, "lineitem"), F.array(quantised("l_quantity"), quantised(F.col("l_extendedprice") / 1000), quantised("l_discount", 100), quantised("l_tax", 100)))


def benchmark(s: SparkSession, d: str) -> DataFrame:
    """Whole texts; edits count characters (the SQL counterpart, whose engine counts bytes, gives every character a byte of its own)."""
    return points(table(s, d, "benchmark"), "item_id", F.coalesce("text", F.lit("")))


def documents(s: SparkSession, d: str) -> DataFrame:
    words = F.array_sort(F.array_distinct(F.filter(F.split(F.coalesce("text", F.lit("")), r"[\x20\t\n\x0B\f\r]+"), lambda w: w != "")))
    return points(table(s, d, "documents"), "doc_id", words)


def parted(pts: DataFrame, least: int = 4) -> DataFrame:
    """Parts by id, as many as keep a task's points bounded."""
    return by_modulo(pts, part_count(pts.count(), least))


def centers(pts: DataFrame, k: int) -> list:
    """The k smallest ids serve as stated centers."""
    return [(r["id"], r["pt"]) for r in pts.select("id", "pt").orderBy("id").limit(k).collect()]


def spec(k: int, m: int | None = None, objective: str = "median", **options) -> ClusterSpec:
    return ClusterSpec(k, objective, Fraction(1, 2), m=m, **options)


def core(cs: C.Coreset) -> DataFrame:
    return cs.rows.select("part", "id", "w")


# ---------------------------------------------------------------- metrics


def _to_first(src: str, *cols: str, k: int = 3) -> str:
    return f"with pts as ({src}), o as (select id as other, v from pts order by id limit {k}) select pts.id as id_a, o.other as id_b, {', '.join(cols)} from pts cross join o"


def _first(pts: DataFrame):
    return F.lit(pts.orderBy("id").first()["pt"])


def _pairs(pts: DataFrame, k: int = 3) -> DataFrame:
    """(id_a, id_b, a, b): every point against the k points of smallest ids."""
    few = pts.select(F.col("id").alias("id_b"), F.col("pt").alias("b")).orderBy("id_b").limit(k)
    return pts.select(F.col("id").alias("id_a"), F.col("pt").alias("a")).join(F.broadcast(few), F.lit(True))


@query(_to_first(Q.PART, f"{Q._d(Q.L1_2D, 'pts.v', 'o.v')} as d1", "greatest(abs(pts.v.x - o.v.x), abs(pts.v.y - o.v.y)) as dmax", f"{Q._d(Q.SQUARE_2D, 'pts.v', 'o.v')} as d2", f"round((abs(pts.v.x - o.v.x)::double ** 3 + abs(pts.v.y - o.v.y)::double ** 3) ** (1 / 3.0), 4) as d3"))
def metric_lp_part(s, d):
    a, b = F.col("a"), F.col("b")
    return _pairs(part(s, d)).select("id_a", "id_b", L1.column(a, b).alias("d1"), Lp(float("inf")).column(a, b).alias("dmax"), SQ.power_column(a, b, 2).alias("d2"), F.round(Lp(3).column(a, b), 4).alias("d3"))


@query(_to_first(Q.PART_CATEGORIES, f"{Q._d(Q.HAMMING, 'pts.v', 'o.v')} as d"))
def metric_hamming_part(s, d):
    return _pairs(part_categories(s, d)).select("id_a", "id_b", HAM.column(F.col("a"), F.col("b")).alias("d"))


@query(_to_first(Q.BENCHMARK, f"{Q._d(Q.EDIT, 'pts.v', 'o.v')}::bigint as d"))
def metric_edit_benchmark(s, d):
    return _pairs(benchmark(s, d)).select("id_a", "id_b", EDIT.column(F.col("a"), F.col("b")).alias("d"))


_WORDS = "list_distinct(list_filter(regexp_split_to_array(coalesce(text, ''), '[ \\t\\n\\x0B\\f\\r]+'), lambda x: x <> ''))"


@query(f"with t as (select doc_id as id, {_WORDS} as w from documents), o as (select id as other, w as ow from t order by id limit 3) select id as id_a, other as id_b, len(list_intersect(w, ow))::bigint as common, (len(w) + len(ow) - len(list_intersect(w, ow)))::bigint as united from t cross join o")
def metric_jaccard_documents(s, d):
    common = F.size(F.array_intersect("a", "b")).cast("long")
    return _pairs(documents(s, d)).select("id_a", "id_b", common.alias("common"), (F.size("a") + F.size("b") - common).cast("long").alias("united"))


@query("select * from (values ('identity', 0::bigint), ('symmetry', 0), ('sign', 0), ('triangle', 0)) t(axiom, violations)")
def metric_axioms_part(s, d):
    return verify(part(s, d), L1)


@query("with t as (select vec_id as id, list_transform(embedding, lambda x: round(x::double * 10000)::bigint) as v from embeddings), o as (select id as other, v as ov from t order by id limit 3) select id as id_a, other as id_b, d2, round(sqrt(d2), 6) as d from (select id, other, list_sum(list_transform(list_zip(v, ov), lambda z: (z[1] - z[2]) * (z[1] - z[2]))) as d2 from t cross join o)")
def metric_sq_embeddings(s, d):
    pts = points(table(s, d, "embeddings"), "vec_id", F.transform("embedding", lambda x: F.round(x.cast("double") * 10000).cast("long")))
    a, b = F.col("a"), F.col("b")
    return _pairs(pts).select("id_a", "id_b", SQ.power_column(a, b, 2).alias("d2"), F.round(Euclidean().column(a, b), 6).alias("d"))


@query(f"{Q.nearest(Q.PART, Q.L1_2D, 10)} select id, center_id, d from near")
def nearest_part(s, d):
    pts = part(s, d)
    return A.assign(pts, centers(pts, 10), L1)


@query(f"{Q.nearest(Q.PART, Q.L1_2D, 10)} select id, center_id, d from near")
def nearest_sql_part(s, d):
    pts = part(s, d)
    return A.assign_sql(pts, centers(pts, 10), L1)


@query(f"with pts as ({Q.ORDERS}), o as (select v from pts order by id limit 1) select pts.id, {Q._d(Q.L1_2D, 'pts.v', 'o.v')} as d from pts cross join o where {Q._d(Q.L1_2D, 'pts.v', 'o.v')} <= 5000")
def ball_orders(s, d):
    pts = orders(s, d)
    return A.ball(pts, pts.orderBy("id").first()["pt"], 5000, L1)


@query(f"with pts as ({Q.CUSTOMER}) select min(g)::bigint as min_d from (select v.x - lag(v.x) over (order by v.x) as g from pts)")
def separation_customer(s, d):
    return A.separation(customer(s, d), L1)


@query()
def dd_estimate_orders(s, d):
    return A.doubling_dimension(orders(s, d), L1)


# ---------------------------------------------------------------- costs


def _cost(src: str, dist: str, k: int) -> str:
    return f"{Q.nearest(src, dist, k)} select sum(w::hugeint * d)::bigint as cost from near"


@query(_cost(Q.CUSTOMER, Q.L1, 5))
def cost_median_customer(s, d):
    pts = customer(s, d)
    return M.cost(pts, centers(pts, 5), L1)


@query(_cost(Q.CUSTOMER, Q.SQUARE, 5))
def cost_means_customer(s, d):
    pts = customer(s, d)
    return M.cost(pts, centers(pts, 5), SQ, 2)


@query(_cost(Q.PART_WEIGHTED, Q.L1_2D, 10))
def cost_weighted_part(s, d):
    pts = part_weighted(s, d)
    return M.cost(pts, centers(pts, 10), L1)


@query(f"with pts as ({Q.CUSTOMER}) select part, count(*) as n from pts group by part")
def part_sizes_customer(s, d):
    return parted(customer(s, d)).groupBy("part").agg(F.count("*").alias("n"))


@query("select id % 7 as k, count(*) as n from (select row_number() over (order by c_custkey) - 1 as id from customer) group by 1")
def even_parts_customer(s, d):
    from .operators.points import evenly

    return evenly(customer(s, d), 7).groupBy(F.col("part").cast("long").alias("k")).agg(F.count("*").alias("n"))


# ---------------------------------------------------------------- seeding and covers


@query(f"with recursive {Q.seeded(Q.CUSTOMER, Q.L1, 5)} select distinct part, (step - 1)::int as rank, pid as id from ff")
def farthest_first_customer(s, d):
    return B.farthest_on_parts(parted(customer(s, d)), spec(5), L1)


@query()
def dsample_customer(s, d):
    return C.one_round(parted(customer(s, d)), spec(5, seeder="dsample"), L1).seeds.select("part", "id")


@query(Q.core(Q.one_round(Q.CUSTOMER, Q.L1, 5)))
def cover_median_customer(s, d):
    return core(C.one_round(parted(customer(s, d)), spec(5), L1))


@query(Q.core(Q.one_round(Q.CUSTOMER, Q.SQUARE, 5, p=2)))
def cover_means_customer(s, d):
    return core(C.one_round(parted(customer(s, d)), spec(5, objective="means"), SQ))


@query(Q.core(Q.one_round(Q.ORDERS, Q.L1_2D, 20, order="far_first")))
def cover_order_orders(s, d):
    return core(C.one_round(parted(orders(s, d), 11), spec(10, 20, order="far_first"), L1))


@query(Q.core(Q.one_round(Q.PART_WEIGHTED, Q.L1_2D, 20)))
def cover_weighted_part(s, d):
    return core(C.one_round(parted(part_weighted(s, d)), spec(10, 20), L1))


@query(Q.core(Q.one_round(Q.PART, Q.L1_2D, 20, floor=False)))
def cover_nofloor_part(s, d):
    return core(C.one_round(parted(part(s, d)), spec(10, 20, floor=False), L1))


@query(Q.core(Q.one_round(Q.PART_CATEGORIES, Q.HAMMING, 20)))
def cover_hamming_part(s, d):
    return core(C.one_round(parted(part_categories(s, d)), spec(10, 20), HAM))


@query(Q.core(Q.one_round(Q.BENCHMARK, Q.EDIT, 8)))
def cover_edit_benchmark(s, d):
    return core(C.one_round(parted(benchmark(s, d), 2), spec(4, 8), EDIT))


_EMBEDDED = f"select vec_id::bigint as id, {Q.parts('vec_id', 'embeddings')} as part, 1::bigint as w, {{'x': list_transform(embedding, lambda x: round(x::double * 10000)::bigint)}} as v from embeddings"


@query(Q.core(Q.one_round(_EMBEDDED, "list_sum(list_transform(list_zip({a}.x, {b}.x), lambda z: (z[1] - z[2]) * (z[1] - z[2])))::bigint", 20, p=2)))
def cover_embeddings(s, d):
    """The case without compression: 64 dimensions, all distances alike, so the cover keeps (nearly) every point."""
    pts = points(table(s, d, "embeddings"), "vec_id", F.transform("embedding", lambda x: F.round(x.cast("double") * 10000).cast("long")))
    return core(C.one_round(parted(pts), spec(10, 20, objective="means"), SQ))


_DOCUMENTS = f"select doc_id as id, (doc_id % 4)::int as part, 1::bigint as w, {{'x': {_WORDS}}} as v from documents"
_JACCARD = "(case when len({a}.x) + len({b}.x) = 0 then 0.0::double else 1 - len(list_intersect({a}.x, {b}.x))::double / (len({a}.x) + len({b}.x) - len(list_intersect({a}.x, {b}.x)))::double end)"


@query(Q.core(Q.one_round(_DOCUMENTS, _JACCARD, 20, number="double")))
def cover_jaccard_documents(s, d):
    pts = documents(s, d)
    return core(C.one_round(by_modulo(pts, part_count(pts.count(), 4, 1_000)), spec(10, 20), JAC))


@query(Q.core(Q.one_round(Q.ORDERS, Q.L1_2D, 20)))
def cover_pruned_orders(s, d):
    return core(C.one_round(parted(orders(s, d), 11), spec(10, 20, prune=True), L1))


@query(f"with recursive {Q.one_round(Q.CUSTOMER, Q.L1, 5)} select id, tau_id, d::bigint as d from cov_tau")
def tau_customer(s, d):
    return C.one_round(parted(customer(s, d)), spec(5), L1, mapping=True).mapping.select("id", "tau_id", F.col("d").cast("long").alias("d"))


@query(f"with recursive {Q.two_round(Q.CUSTOMER, Q.L1, 5)} select max(d::hugeint * 4 * n - greatest(r, n * d_t))::bigint as max_slack from cov2_tau cross join every")
def cover_slack_customer(s, d):
    pts = parted(customer(s, d))
    first = C.one_round(pts, spec(5), L1)
    cs = C.two_round(pts, spec(5), L1, mapping=True, first=first)
    r_num, r_den = C.tolerance(first)
    return V.cover_slack(pts, cs, first.rows.select(F.col("id").alias("center_id"), "pt"), r_num, r_den, L1)


@query(f"{Q.nearest(Q.EVENTS, Q.L1_2D, 10)}, g as (select center_id, d, (select max(j) from range(0, 60) t(j) where d > 500::hugeint * (1::hugeint << j)) as j from near) select center_id as target, coalesce(j, -1)::int as j, count(*) as n from g group by 1, 2")
def shells_events(s, d):
    pts = events(s, d)
    return V.shells(pts, centers(pts, 10), L1, 500)


@query(Q.core(Q.one_round(Q.CUSTOMER, Q.L1, 5)))
def one_round_median_customer(s, d):
    return core(C.one_round(parted(customer(s, d)), spec(5), L1))


@query(Q.core(Q.one_round(Q.CUSTOMER, Q.SQUARE, 5, p=2)))
def one_round_means_customer(s, d):
    return core(C.one_round(parted(customer(s, d)), spec(5, objective="means"), SQ))


@query(Q.core(Q.two_round(Q.CUSTOMER, Q.L1, 5), "cov2_tau"))
def two_round_median_customer(s, d):
    return core(C.two_round(parted(customer(s, d)), spec(5), L1))


@query(Q.core(Q.two_round(Q.CUSTOMER, Q.SQUARE, 5, p=2), "cov2_tau"))
def two_round_means_customer(s, d):
    return core(C.two_round(parted(customer(s, d)), spec(5, objective="means"), SQ))


@query(Q.core(Q.two_round(Q.PART, Q.L1_2D, 20), "cov2_tau"))
def two_round_median_part(s, d):
    return core(C.two_round(parted(part(s, d)), spec(10, 20), L1))


@query(Q.core(Q.one_round(Q.EVENTS, Q.L1_2D, 20), label="day"))
def window_coreset_events(s, d):
    return core(C.one_round(events(s, d), spec(10, 20), L1)).select((F.col("part") % DAYS).alias("day"), "id", "w")


@query(f"with recursive {Q.one_round(Q.EVENTS, Q.L1_2D, 20)}, c as (select part, tau_id, sum(w) as w from cov_tau group by 1, 2) select count(*) as n_core, sum(w)::bigint as w_sum from c")
def compose_events(s, d):
    e = events(s, d)
    halves = [C.one_round(e.where(F.col("part") % 2 == k), spec(10, 20), L1) for k in (0, 1)]
    return C.union(halves).agg(F.count("*").alias("n_core"), F.sum("w").alias("w_sum"))


@query(
    f"with recursive {Q.one_round(Q.CUSTOMER, Q.L1, 5)}, first as materialized (select tau_id as id, 0 as part, sum(w)::bigint as w from cov_tau group by tau_id), "
    f"{Q.one_round('select first.id, first.part, first.w, pts.v from first join pts using (id)', Q.L1, 5).replace('pts as', 'pts2 as').replace('from pts)', 'from pts2)').replace(' ff', ' gg').replace('ff as', 'gg as').replace('dt', 'dt2').replace('tol', 'tol2').replace('cov', 'cow')} "
    "select tau_id as id, sum(w)::bigint as w from cow_tau group by tau_id"
)
def re_reduce_customer(s, d):
    return C.reduce_again(C.one_round(parted(customer(s, d)), spec(5), L1), spec(5), L1).rows.select("id", "w")


@query(f"with recursive {Q.seeded(Q.CUSTOMER, Q.L1, 5)}, g as (select sum(n)::bigint as n, sum(r)::bigint as nu from tol), mu as (select sum(d::hugeint * d)::bigint as mu from dt) select n, nu, mu from g cross join mu")
def r_global_customer(s, d):
    pts = parted(customer(s, d))
    one, two = (C.one_round(pts, spec(5, objective=o), m) for o, m in (("median", L1), ("means", SQ)))
    return one.stats.agg(F.sum("w_sum").alias("n"), F.sum("cost").cast("long").alias("nu")).join(two.stats.agg(F.sum("cost").cast("long").alias("mu")), F.lit(True))


@query(f"""with recursive {Q.two_round(Q.CUSTOMER, Q.L1, 5)}, nc as (select count(*) as c from c1), e as (select part, count(distinct tau_id) as e from cov2_tau group by part), s as (select part, count(distinct pid) as m from ff group by part), x as (select tol.part, tol.n::bigint as n, s.m, e.e from tol join s using (part) join e using (part))
select 1 as round, max(n + m)::bigint as max_rows, sum(n)::bigint as sum_rows from x union all select 2, max(n + c + e)::bigint, sum(n + c)::bigint from x cross join nc union all select 3, sum(e)::bigint, sum(e)::bigint from x""")
def memory_customer(s, d):
    pts = parted(customer(s, d))
    first = C.one_round(pts, spec(5), L1)
    return M.memory(first, C.two_round(pts, spec(5), L1, first=first))


# ---------------------------------------------------------------- optima and solvers


def _local(pts: DataFrame, most: int = 2_000):
    """A small instance on the driver, its size checked."""
    rows = pts.orderBy("id").limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError(f"more than {most} points")
    import numpy as np

    return [r["id"] for r in rows], [r["pt"] for r in rows], np.array([r["w"] for r in rows])


@query(f"with pts as ({Q.SUPPLIER}), c as (select a.id as s1, b.id as s2, a.v as av, b.v as bv from pts a join pts b on a.id < b.id), k as (select s1, s2, sum(p.w * least({Q._d(Q.L1, 'p.v', 'c.av')}, {Q._d(Q.L1, 'p.v', 'c.bv')}))::bigint as cost from c cross join pts p group by s1, s2) select s1, s2, cost from k order by cost, s1, s2 limit 1")
def exact_supplier(s, d):
    best = two_medians(supplier(s, d))
    return s.createDataFrame([best] if best else [], "s1 long, s2 long, cost long")


@query(f"with pts as ({Q.SUPPLIER}), c as (select a.id as s1, b.id as s2, a.v as av, b.v as bv from pts a join pts b on a.id < b.id) select min(cost)::bigint as cost from (select sum(p.w * least({Q._d(Q.L1, 'p.v', 'c.av')}, {Q._d(Q.L1, 'p.v', 'c.bv')})) as cost from c cross join pts p group by s1, s2)")
def exact_line_supplier(s, d):
    got = supplier(s, d).select(F.col("pt")[0].alias("x"), "w").toArrow()
    return s.createDataFrame([(int(exact_line(got.column("x").to_numpy(), got.column("w").to_numpy(), 2, 1)[1]),)], "cost long")


_OPT = f"pairs as (select a.id as s1, b.id as s2, a.v as av, b.v as bv from pts a join pts b on a.id < b.id), opt as materialized (select min(cost) as den from (select sum(p.w * least({Q._d(Q.L1, 'p.v', 'c.av')}, {Q._d(Q.L1, 'p.v', 'c.bv')})) as cost from pairs c cross join pts p group by s1, s2))"


@query(f"with recursive {Q.two_round(Q.SUPPLIER, Q.L1, 3)}, {_OPT} select sum(w * d)::bigint as num, any_value(den)::bigint as den from cov2_tau cross join opt")
def bounded_supplier(s, d):
    pts = supplier(s, d)
    cs = C.two_round(parted(pts, 2), spec(2, 3), L1, mapping=True)
    return M.mapping_cost(cs, L1).withColumn("den", F.lit(optimum(places(pts), 2, 1)).cast("long"))


@query(f"with recursive {Q.two_round(Q.SUPPLIER, Q.L1, 3)}, {_OPT.split(', opt as')[0]}, co as materialized (select tau_id as id, sum(w) as w from cov2_tau group by 1), k as materialized (select s1, s2, sum(p.w * least({Q._d(Q.L1, 'p.v', 'c.av')}, {Q._d(Q.L1, 'p.v', 'c.bv')})) as cost from pairs c cross join pts p group by s1, s2), l as materialized (select s1, s2, sum(co.w * least({Q._d(Q.L1, 'p.v', 'c.av')}, {Q._d(Q.L1, 'p.v', 'c.bv')})) as core_cost from pairs c cross join co join pts p using (id) group by s1, s2) select round(max(abs(cost - core_cost)::double / cost::double), 9) as max_error, count(*) as solutions from k join l using (s1, s2)")
def distortion_supplier(s, d):
    pts = supplier(s, d)
    cs = C.two_round(parted(pts, 2), spec(2, 3), L1)
    return pair_errors(s, places(pts), places(cs.rows)).select(F.round("error", 9).alias("max_error"), "solutions")


@query(f"with recursive {Q.two_round(Q.SUPPLIER, Q.L1, 3)}, {_OPT}, ce as (select distinct pts.id, pts.v from cov2_tau join pts on pts.id = tau_id), ep as (select a.id as s1, b.id as s2, a.v as av, b.v as bv from ce a join ce b on a.id < b.id) select min(cost)::bigint as cost_best_in_e, any_value(den)::bigint as opt from (select sum(p.w * least({Q._d(Q.L1, 'p.v', 'c.av')}, {Q._d(Q.L1, 'p.v', 'c.bv')})) as cost from ep c cross join pts p group by s1, s2) cross join opt")
def centroid_supplier(s, d):
    pts = supplier(s, d)
    cs = C.two_round(parted(pts, 2), spec(2, 3), L1)
    at = places(pts)
    best = best_among(at, places(cs.rows))
    return s.createDataFrame([(best, None if best is None else optimum(at, 2, 1))], "cost_best_in_e long, opt long")


@query()
def local_search_part(s, d):
    from .operators.solve import local_search

    cs = C.one_round(parted(part(s, d)), spec(10, 20), L1)
    return local_search(cs.rows, 10, L1, 1).select("center_id")


@query()
def local_search_distributed_part(s, d):
    from .operators.solve import local_search_distributed

    return local_search_distributed(part(s, d), 5, L1, 1).select("center_id")


def flagship(s: SparkSession, d: str) -> DataFrame:
    """Three-round k-median of customer balances: centers, sizes and costs."""
    r = cluster(customer(s, d), spec(5, seeder="dsample"), L1)
    return r.profile().select("center_id", "n", F.col("cost").cast("long").alias("cost"))


@query()
def flagship_customer(s, d):
    return flagship(s, d)


@query()
def report_customer(s, d):
    return cluster(customer(s, d), spec(5, seeder="dsample"), L1).report()


@query()
def fast_orders(s, d):
    return cluster(orders(s, d), spec(10, 20, seeder="dsample"), L1, rounds=1).profile().select("center_id", "n", F.col("cost").cast("long").alias("cost"))


@query()
def continuous_orders(s, d):
    from .api import cluster_continuous

    r = cluster_continuous(orders(s, d), spec(10, 20, objective="means", seeder="dsample"), SQ)
    out = A.assign(r.points, r.centers, Euclidean(), 2)
    return out.groupBy("center_id").agg(F.count("*").alias("n"), F.sum("d").alias("cost"))


@query()
def lineitem_one_round(s, d):
    pts = lineitem(s, d)
    cs = C.one_round(by_modulo(pts, part_count(pts.count(), 16, 10_000)), spec(20, 40, seeder="dsample", prune=True), L1)
    return M.size(cs).select("n_core", "n", "w_sum")


# ---------------------------------------------------------------- assignment and profiles


@query(f"{Q.nearest(Q.ORDERS, Q.L1_2D, 10)} select id, center_id, d from near")
def assign_orders(s, d):
    pts = orders(s, d)
    return A.assign(pts, centers(pts, 10), L1)


@query(f"{Q.nearest(Q.PART_WEIGHTED, Q.L1_2D, 10)} select center_id, count(*) as n, sum(w)::bigint as w, sum(w * d)::bigint as cost, max(d) as radius, arg_min(id, (d, id)) as nearest_id from near group by center_id")
def profile_part(s, d):
    pts = part_weighted(s, d)
    return A.profile(A.assign(pts, centers(pts, 10), L1, keep=("w",)))


# ---------------------------------------------------------------- baselines


@query(f"with recursive {Q.seeded(Q.CUSTOMER, Q.L1, 5)}, sd as (select distinct part, pid from ff), c as (select sd.part, sd.pid, pts.v from sd join pts on pts.id = sd.pid), n as (select p.id, p.part, p.w, arg_min(c.pid, ({Q._d(Q.L1, 'p.v', 'c.v')}, c.pid)) as center from pts p join c using (part) group by p.id, p.part, p.w) select part, center as id, sum(w)::bigint as w from n group by 1, 2")
def baseline_local_centers_customer(s, d):
    return B.local_centers(parted(customer(s, d)), spec(5), L1).select("part", "id", "w")


@query("select o_orderkey as id, 8::bigint as w from orders where ('0x' || substr(md5(o_orderkey::varchar), 1, 8))::bigint % 8 = 0")
def baseline_uniform_orders(s, d):
    return B.uniform_sample(orders(s, d), 8).select("id", "w")


@query()
def baseline_importance_orders(s, d):
    pts = orders(s, d)
    return B.importance_sample(pts, centers(pts, 10), L1, 1, 500).agg(F.count("*").alias("n_sample"), F.sum("w").alias("w_sum"))


_GRID = "coalesce((select max(j) + 1 from range(0, 40) t(j) where d > 200::hugeint * (1::hugeint << j)), 0)"


@query(f"{Q.nearest(Q.PART, Q.L1_2D, 10)}, g as (select near.*, {_GRID}::int as shell, pts.v from near join pts using (id)), h as (select *, (100 * (1::bigint << shell))::bigint as side from g) select center_id, shell, floor(v.x / side)::bigint::varchar || ',' || floor(v.y / side)::bigint::varchar as cell, min(id) as id, sum(w)::bigint as w from h group by 1, 2, 3")
def baseline_grid_part(s, d):
    pts = part(s, d)
    return B.shell_grid(pts, centers(pts, 10), L1, 200, 100)


@query()
def baseline_mllib_orders(s, d):
    return B.library_kmeans(orders(s, d), 10).groupBy("cluster").agg(F.count("*").alias("n"))


@query(f"with t as (select doc_id as id, lang, {_WORDS} as v from documents), cen as (select id as center_id, v as cv from t order by id limit 5), n as (select t.id, t.lang, arg_min(c.center_id, (1 - len(list_intersect(v, cv))::double / (len(v) + len(cv) - len(list_intersect(v, cv)))::double, c.center_id)) as center_id from t cross join cen c group by t.id, t.lang), k as (select center_id, lang, count(*) as n from n group by 1, 2) select center_id, arg_min(lang, (-n, lang)) as lang, max(n) as n from k group by center_id")
def purity_documents(s, d):
    pts = documents(s, d)
    near = A.assign(pts, centers(pts, 5), JAC)
    return M.purity(near.join(table(s, d, "documents").select(F.col("doc_id").alias("id"), "lang"), "id"), "lang")


# ---------------------------------------------------------------- ablations and scaling


@query()
def ablation_part(s, d):
    pts = parted(part(s, d))
    variants = {"base": {}, "no floor": {"floor": False}, "far first": {"order": "far_first"}, "near first": {"order": "near_first"}, "random": {"order": "random"}, "dsample": {"seeder": "dsample"}, "uniform": {"seeder": "uniform"}, "pruned": {"prune": True}, "beta 2": {"beta": 2}, "beta 4": {"beta": 4}}
    specs = {k: ClusterSpec(10, m=20, **{"eps": Fraction(1, 2)} | v) for k, v in variants.items()}
    specs |= {f"m {m}": ClusterSpec(10, m=m) for m in (10, 40)} | {f"eps {e}": ClusterSpec(10, m=20, eps=e) for e in (0.1, 0.25, 0.9)}
    return C.ablation_sizes(pts, specs, L1)


@query()
def scaling_orders(s, d):
    """(parts, round, max_rows, sum_rows) over all orders, from too few parts over the balanced number to too many."""
    from .plans.resolve import resolve

    pts, out = orders(s, d), None
    balanced = resolve(pts.count(), spec(10, 20), rounds=2).parts
    for n in sorted({max(1, balanced // 2), balanced, 2 * balanced, 4 * balanced}):
        cut = by_modulo(pts, n)
        first = C.one_round(cut, spec(10, 20), L1)
        row = M.memory(first, C.two_round(cut, spec(10, 20), L1, first=first)).select(F.lit(n).alias("parts"), "*")
        out = row if out is None else out.unionByName(row)
    return out


# ---------------------------------------------------------------- surrounding operators


@query(f"with recursive {Q.one_round(Q.CUSTOMER, Q.L1, 5)} select id from pts where id not in (select tau_id from cov_tau)")
def not_in_coreset_customer(s, d):
    pts = parted(customer(s, d))
    return pts.join(C.one_round(pts, spec(5), L1).rows, "id", "left_anti").select("id")


@query("select 0::bigint as n_missing")
def coreset_subset_check(s, d):
    pts = parted(customer(s, d))
    return V.missing_from(pts, C.one_round(pts, spec(5), L1).rows)


@query(f"select id, w from ({Q.PART_WEIGHTED})")
def weights_part_lineitem(s, d):
    return part_weighted(s, d).select("id", "w")


@query(f"{Q.nearest(Q.ORDERS, Q.L1_2D, 10)}, r as (select *, row_number() over (partition by center_id order by d, id) as rank from near) select center_id, rank::int as rank, id, d from r where rank <= 5")
def topk_near_center_orders(s, d):
    pts = orders(s, d)
    order = Window.partitionBy("center_id").orderBy("d", "id")
    return A.assign(pts, centers(pts, 10), L1).withColumn("rank", F.row_number().over(order)).where("rank <= 5").select("center_id", "rank", "id", "d")


_NEAR_CUSTOMER = f"{Q.nearest(Q.CUSTOMER, Q.L1, 5)}, x as (select near.d, c_mktsegment as segment, n_name as nation, r_name as region from near join customer on c_custkey = near.id join nation on n_nationkey = c_nationkey join region on r_regionkey = n_regionkey)"


def _near_customer(s, d):
    pts = customer(s, d)
    near = A.assign(pts, centers(pts, 5), L1)
    place = table(s, d, "nation").join(F.broadcast(table(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    c = table(s, d, "customer").select(F.col("c_custkey").alias("id"), "c_mktsegment", "c_nationkey")
    return near.join(c, "id").join(F.broadcast(place), F.col("c_nationkey") == F.col("n_nationkey")).select("d", F.col("c_mktsegment").alias("segment"), F.col("n_name").alias("nation"), F.col("r_name").alias("region"))


@query(f"{_NEAR_CUSTOMER} select region, nation, count(*) as n, sum(d)::bigint as cost from x group by rollup (region, nation)")
def rollup_cost_region(s, d):
    return _near_customer(s, d).rollup("region", "nation").agg(F.count("*").alias("n"), F.sum("d").alias("cost"))


@query(f"{_NEAR_CUSTOMER} select segment, region, count(*) as n, sum(d)::bigint as cost from x group by cube (segment, region)")
def cube_cost_segment(s, d):
    return _near_customer(s, d).cube("segment", "region").agg(F.count("*").alias("n"), F.sum("d").alias("cost"))


@query("select e.event_id, (select arg_max(p.event_id, (p.ts, p.event_id)) from events p where p.user_id = e.user_id and p.event_type = 'purchase' and (p.ts, p.event_id) < (e.ts, e.event_id)) as prev_purchase_id from events e")
def asof_purchase_events(s, d):
    """Each event with its user's latest earlier purchase: one sorted pass per user."""
    order = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    bought = F.when(F.col("event_type") == "purchase", F.col("event_id"))
    return table(s, d, "events").select("event_id", F.last(bought, ignorenulls=True).over(order).alias("prev_purchase_id"))


@query("with t as (select user_id, ts, event_id, case when ts - lag(ts) over w > interval 12 hour or lag(ts) over w is null then 1 else 0 end as new from events window w as (partition by user_id order by ts, event_id)), u as (select user_id, sum(new) over (partition by user_id order by ts, event_id rows unbounded preceding)::bigint as session from t) select user_id, session, count(*) as n from u group by 1, 2")
def session_events(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    gap = F.col("ts") - F.lag("ts").over(w)
    new = F.when(F.lag("ts").over(w).isNull() | (gap > F.expr("interval 12 hours")), 1).otherwise(0)
    t = table(s, d, "events").select("user_id", "ts", "event_id", new.cast("long").alias("new"))
    t = t.select("user_id", F.sum("new").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("session"))
    return t.groupBy("user_id", "session").agg(F.count("*").alias("n"))


@query("with t as (select ts::date as day, count(*) as n from events group by 1) select day, n, sum(n) over (order by day rows unbounded preceding)::bigint as running_n from t")
def day_running_events(s, d):
    t = table(s, d, "events").groupBy(F.col("ts").cast("date").alias("day")).agg(F.count("*").alias("n"))
    return t.withColumn("running_n", F.sum("n").over(Window.orderBy("day").rowsBetween(Window.unboundedPreceding, 0)))


_TYPES = ["click", "purchase", "view"]


@query("select ts::date as day, count(*) filter (event_type = 'click') as click, count(*) filter (event_type = 'purchase') as purchase, count(*) filter (event_type = 'view') as view from events group by 1")
def pivot_events(s, d):
    t = table(s, d, "events").groupBy(F.col("ts").cast("date").alias("day")).pivot("event_type", _TYPES).count()
    return t.na.fill(0)


@query("select p.event_id, count(e.event_id) as n from events p left join events e on e.user_id = p.user_id and e.ts > p.ts and e.ts <= p.ts + interval 6 hour where p.event_type = 'purchase' group by p.event_id")
def interval_events(s, d):
    """Events of the same user within six hours of each purchase: an equi-join on six-hour buckets, then the exact range."""
    e = table(s, d, "events").select("event_id", "user_id", "ts", "event_type", F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 21600).alias("b"))
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("p_id"), "user_id", F.col("ts").alias("p_ts"), F.explode(F.array(F.col("b"), F.col("b") + 1)).alias("b"))
    near = p.join(e.select("user_id", "b", "ts"), ["user_id", "b"]).where((F.col("ts") > F.col("p_ts")) & (F.col("ts") <= F.col("p_ts") + F.expr("interval 6 hours")))
    n = near.groupBy("p_id").agg(F.count("*").alias("n"))
    every = e.where("event_type = 'purchase'").select(F.col("event_id").alias("p_id"))
    return every.join(n, "p_id", "left").select(F.col("p_id").alias("event_id"), F.coalesce("n", F.lit(0)).alias("n"))


@query("select event_type, round(median(value), 6) as q50 from events group by event_type")
def quantiles_events(s, d):
    return table(s, d, "events").groupBy("event_type").agg(F.round(F.median("value"), 6).alias("q50"))


@query("select json_extract(props, '$.k')::bigint as k, count(*) as n from events group by 1")
def json_feature_events(s, d):
    return table(s, d, "events").groupBy(F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count("*").alias("n"))


_CLOSED = f"select * from ({Q.EVENTS}) where part < (select date_diff('day', date '1970-01-01', (max(ts) - interval 1 hour)::date) from events)"


@query(Q.core(Q.one_round(_CLOSED, Q.L1_2D, 20), label="day"))
def stream_day_coreset_events(s, d):
    """Day coresets from a stream of event files; the last day stays open behind the watermark."""
    scratch = Scratch(s, "stream")
    e = with_event_time(stream(s, d, "events"))
    pts = e.select("ts", F.col("event_id").alias("id"), _event_vector().alias("pt"), F.lit(1).cast("long").alias("w"))
    out = window_coreset(pts, spec(10, 20), L1)
    q = out.writeStream.outputMode("append").option("checkpointLocation", f"{scratch.root}/state").trigger(availableNow=True).start(f"{scratch.root}/days", format="parquet")
    q.awaitTermination()
    days = s.read.schema(out.schema).parquet(f"{scratch.root}/days")
    return days.select(F.unix_date(F.col("start").cast("date")).alias("day"), "id", "w")


_NATION = "select c_nationkey::bigint as id, {'x': count(*)::bigint, 'y': (sum(cast(round(c_acctbal * 100) as bigint))::bigint // count(*)) } as v from customer group by c_nationkey"


@query(f"with pts as ({_NATION}), c as (select a.id as s1, b.id as s2, a.v as av, b.v as bv from pts a join pts b on a.id < b.id), k as (select s1, s2, sum(least({Q._d(Q.L1_2D, 'p.v', 'c.av')}, {Q._d(Q.L1_2D, 'p.v', 'c.bv')}))::bigint as cost from c cross join pts p group by s1, s2) select s1, s2, cost from k order by cost, s1, s2 limit 1")
def exact_nation(s, d):
    """Two central nations by customers and mean balance: brute force over all pairs."""
    mean = F.floor(F.sum(quantised("c_acctbal", 100)) / F.count("*")).cast("long")
    g = table(s, d, "customer").groupBy(F.col("c_nationkey").cast("long").alias("id")).agg(F.array(F.count("*"), mean).alias("pt")).withColumn("w", F.lit(1))
    ids, pt, w = _local(g)
    best, cost = exact(L1, L1.load(pt), w, 2, 1)
    return s.createDataFrame([(ids[best[0]], ids[best[1]], int(cost))], "s1 long, s2 long, cost long")


def entry(s: SparkSession, d: str) -> DataFrame:
    return flagship(s, d)


