from __future__ import annotations

import itertools
import math
from fractions import Fraction

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from coreclust.api import alpha_of, cluster, cluster_continuous, cluster_fast
from coreclust.functions.metrics import Edit, Euclidean, Hamming, Lp
from coreclust.operators import coreset as C
from coreclust.operators import measure as M
from coreclust.operators import solve as S
from coreclust.operators import verify as V
from coreclust.operators.cover import ball_cover
from coreclust.operators.points import by_column, by_hash, by_modulo
from coreclust.operators.seed import SEEDERS
from coreclust.plans import bounds
from coreclust.plans.resolve import part_count, resolve
from coreclust.schema import ClusterSpec, CoreclustError, check_points
from coreclust.sources.tables import load_model, save_model, write_coreset

L1, SQ = Lp(1), Euclidean(exact=True)
HALF = Fraction(1, 2)


def line(spark, xs, w=None, parts=2):
    rows = [(i, [int(x)], int(1 if w is None else w[i])) for i, x in enumerate(xs)]
    return by_modulo(spark.createDataFrame(rows, "id long, pt array<bigint>, w long"), parts)


def plain_cover(d, dt, r, eps, beta, p):
    """The cover by its definition, in floats of whole numbers, pivots by id."""
    alive, tau = list(range(len(dt))), {}
    while alive:
        k = alive[0]
        got = [q for q in alive if d[k][q] <= Fraction(eps**p) / (2 * Fraction(beta)) * max(r, Fraction(int(dt[q])))]
        tau |= {q: k for q in got}
        alive = [q for q in alive if q not in got]
    return [tau[q] for q in range(len(dt))]


@given(st.lists(st.tuples(st.integers(0, 60), st.integers(0, 60)), min_size=1, max_size=40), st.sampled_from([Fraction(1, 10), Fraction(1, 4), HALF]), st.sampled_from([1, 2]), st.integers(1, 3))
@settings(max_examples=60, deadline=None)
def test_cover_matches_its_definition_with_and_without_pruning(xs, eps, p, beta):
    metric = L1 if p == 1 else SQ
    data = metric.load([list(x) for x in xs])
    n, w = len(xs), np.ones(len(xs), np.int64)
    _, dt = SEEDERS["farthest"](metric, data, w, 3, p, None)
    d = [metric.one(data, i, np.arange(n), p).tolist() for i in range(n)]
    want = plain_cover(d, dt, Fraction(int(dt.sum()), n), eps, beta, p)
    for prune in (False, True):
        c = ball_cover(metric, data, dt, int(dt.sum()), n, eps, Fraction(beta), p, prune=prune)
        assert c.tau.tolist() == want and sorted(set(want)) == sorted(c.pivots.tolist())
        assert c.d.tolist() == [d[t][q] for q, t in enumerate(want)]


@pytest.mark.parametrize("order", ["id", "random", "near_first", "far_first"])
def test_every_order_covers_and_separates(order):
    rng = np.random.default_rng(3)
    xs = rng.integers(0, 5000, (300, 1))
    data, w = L1.load(xs.tolist()), np.ones(300, np.int64)
    picks, dt = SEEDERS["farthest"](L1, data, w, 5, 1, rng)
    r = Fraction(int(dt.sum()), 300)
    c = ball_cover(L1, data, dt, int(dt.sum()), 300, HALF, Fraction(1), order=order, rng=rng)
    assert all(c.d[q] <= Fraction(1, 4) * max(r, int(dt[q])) for q in range(300))
    spec = ClusterSpec(5)
    targets = [(int(k), xs[k].tolist()) for k in picks]
    core = [(int(k), xs[k].tolist()) for k in np.sort(c.pivots)]
    assert V.shell_separation(core, targets, float(r), spec, L1) > 1
    worst = max(1.0, float(dt.max() / r))
    assert len(core) <= bounds.cover_size(len(picks), 1, 0.5, 1, worst)


def test_floor_bounds_the_cover():
    xs = np.concatenate((np.arange(200) * 0 + np.arange(200), [10**6]))
    data, w = L1.load([[int(x)] for x in xs]), np.ones(201, np.int64)
    _, dt = SEEDERS["farthest"](L1, data, w, 2, 1, None)
    size = [len(ball_cover(L1, data, dt, 2_000, 1, HALF, Fraction(1), floor=f).pivots) for f in (True, False)]
    assert size[0] < size[1]


def test_zero_tolerance_keeps_one_point_per_place(spark):
    cs = C.one_round(line(spark, [7] * 100, parts=1), ClusterSpec(1), L1)
    assert [(r["id"], r["w"]) for r in cs.rows.collect()] == [(0, 100)]
    few = C.one_round(line(spark, [1, 2, 2, 3], parts=1), ClusterSpec(3), L1)
    assert sorted((r["id"], r["w"]) for r in few.rows.collect()) == [(0, 1), (1, 2), (3, 1)]


def test_large_numbers_do_not_overflow():
    xs = [[0], [10**9], [2 * 10**9], [2 * 10**9 + 1]]
    data, w = SQ.load(xs), np.ones(4, np.int64)
    _, dt = SEEDERS["farthest"](SQ, data, w, 2, 2, None)
    c = ball_cover(SQ, data, dt, int(dt.sum()), 4, HALF, Fraction(1), 2)
    want = plain_cover([SQ.one(data, i, np.arange(4), 2).tolist() for i in range(4)], dt, Fraction(int(dt.sum()), 4), HALF, 1, 2)
    assert c.tau.tolist() == want


@pytest.mark.parametrize("objective,metric", [("median", L1), ("means", SQ)])
def test_proven_constants_on_an_instance_with_its_optimum(spark, objective, metric):
    rng = np.random.default_rng(5)
    xs = np.concatenate((rng.integers(0, 300, 20), rng.integers(1000, 1400, 20)))
    eps = Fraction(1, 10)
    spec = ClusterSpec(2, objective, eps, beta=Fraction(3), m=4)
    p, pts = spec.p, line(spark, xs)
    data, w = metric.load([[int(x)] for x in xs]), np.ones(40, np.int64)
    best, opt = S.exact(metric, data, w, 2, p)
    first = C.one_round(pts, spec, metric, mapping=True)
    second = C.two_round(pts, spec, metric, mapping=True, first=first)
    limit = bounds.bounded(objective, float(eps))
    for part in (0, 1):  # the seeds are within beta of each part's own optimum, so the constants must hold
        m = np.arange(40) % 2 == part
        sub = metric.load([[int(x)] for x in xs[m]])
        _, dt = SEEDERS["farthest"](metric, sub, np.ones(m.sum(), np.int64), 4, p, None)
        assert V.beta_of(float(dt.sum()), metric, sub, np.ones(m.sum(), np.int64), 2, p) <= 3
    for cs in (first, second):
        assert sum(r["w"] for r in cs.rows.collect()) == 40
        assert M.mapping_cost(cs, metric).first()["num"] <= limit["union"] * opt
        pairs = [[[int(a)], [int(b)]] for a, b in itertools.combinations(xs, 2)]
        worst = M.distortion(pts, cs.rows, pairs, metric, p).agg(F.max("error")).first()[0]
        gamma = limit["union"] if objective == "median" else limit["union"] + 2 * math.sqrt(limit["union"])
        assert worst <= gamma
    centers = [(0, [int(xs[best[0]])]), (1, [int(xs[best[1]])])]
    witness = M.centroid_witness(pts, second.rows, centers, metric, p).first()["cost"]
    assert witness <= (1 + limit["centroid"]) * opt
    rows = second.rows.orderBy("id").collect()
    core_data = metric.load([r["pt"] for r in rows])
    found, _ = S.exact(metric, core_data, np.array([r["w"] for r in rows]), 2, p)
    cost = M.cost(pts, [(int(k), rows[k]["pt"]) for k in found], metric, p).first()["cost"]
    assert cost <= bounds.ratio(1, float(eps), objective)[0] * opt
    slack_targets = first.rows.select(F.col("id").alias("center_id"), "pt")
    num, den = C.tolerance(first)
    assert V.cover_slack(pts, second, slack_targets, num, den, metric).first()["max_slack"] <= 0


def test_known_figures(spark):
    """Customer balances in cents, four parts, five farthest-first seeds, eps 1/2: figures found two independent ways beforehand."""
    from coreclust import workloads as W

    d = "/root/testdata/sf0.01"
    pts = W.parted(W.customer(spark, d))
    means = C.one_round(pts, W.spec(5, objective="means"), SQ).rows
    assert means.count() == 94 and means.agg(F.sum("w")).first()[0] == 1500
    assert [(r["id"], r["w"]) for r in means.where("part = 0").orderBy("id").limit(5).collect()] == [(0, 24), (4, 17), (8, 14), (16, 26), (24, 6)]
    first = C.one_round(pts, W.spec(5), L1)
    assert first.rows.count() == 148 and C.tolerance(first)[0] == 110715729
    second = C.two_round(pts, W.spec(5), L1, first=first, mapping=True)
    assert second.rows.count() == 175 and M.mapping_cost(second, L1).first()["num"] == 11049186


def test_union_beyond_the_broadcast_limit_is_reduced_first(spark):
    rng = np.random.default_rng(8)
    pts = line(spark, rng.integers(0, 10**6, 400), parts=4)
    cs = C.two_round(pts, ClusterSpec(5), L1, broadcast_rows=20)
    assert cs.rows.agg(F.sum("w")).first()[0] == 400


def test_results_do_not_depend_on_row_order_or_partitions(spark):
    rng = np.random.default_rng(9)
    xs = rng.integers(0, 4000, (200, 2))
    rows = [(i, [int(a), int(b)], 1) for i, (a, b) in enumerate(xs)]
    runs = []
    for order, n in ((rows, 1), (rows[::-1], 7)):
        pts = by_modulo(spark.createDataFrame(order, "id long, pt array<bigint>, w long").repartition(n), 3)
        runs.append(sorted((r["part"], r["id"], r["w"]) for r in C.two_round(pts, ClusterSpec(4, m=8), L1).rows.collect()))
    assert runs[0] == runs[1]
    scaled = by_modulo(spark.createDataFrame([(i, [x * 3 for x in p], w) for i, p, w in rows], "id long, pt array<bigint>, w long"), 3)
    assert sorted((r["part"], r["id"], r["w"]) for r in C.two_round(scaled, ClusterSpec(4, m=8), L1).rows.collect()) == runs[0]


def test_weights_stand_for_repeated_rows(spark):
    rng = np.random.default_rng(10)
    xs, w = rng.integers(0, 900, 60), rng.integers(1, 5, 60)
    one = line(spark, xs, w, parts=1)
    many = spark.createDataFrame([(i, [int(x)], 1) for i, x in enumerate(np.repeat(xs, w))], "id long, pt array<bigint>, w long")
    centers = [(0, [100]), (1, [700])]
    assert M.cost(one, centers, L1).first()["cost"] == M.cost(many, centers, L1).first()["cost"]
    assert C.one_round(one, ClusterSpec(3), L1).rows.agg(F.sum("w")).first()[0] == w.sum()


def test_splits_as_parts_and_composition(spark):
    rng = np.random.default_rng(11)
    pts = line(spark, rng.integers(0, 5000, 300)).drop("part").repartition(3)
    cs = C.one_round(pts, ClusterSpec(4), L1)
    assert cs.stats.count() == 3 and cs.rows.agg(F.sum("w")).first()[0] == 300
    both = C.union([cs, cs])
    assert both.select("part").distinct().count() == 6
    again = C.reduce_again(cs, ClusterSpec(4), L1)
    assert again.rows.agg(F.sum("w")).first()[0] == 300 and again.rows.count() < cs.rows.count()
    assert bounds.reduced_error("median", 0.1, 0.1) == pytest.approx(0.32) and bounds.reduced_error("means", 0.04, 0.1) > 0.16
    schema = C.tagged_schema(pts.schema["pt"].dataType, L1)
    arrow = C._arrow(schema)
    cut = C._split(pts, schema, lambda t, part: C.first_round(t, part, L1, ClusterSpec(4), arrow, False), rows=30)
    stats = cut.where("kind = 'stat'").collect()
    assert max(r["n"] for r in stats) <= 30 and sum(r["n"] for r in stats) == 300 and len({r["part"] for r in stats}) == len(stats)


def test_skewed_natural_parts_are_salted(spark):
    pts = spark.createDataFrame([(i, [i], 1, "a" if i < 95 else "b") for i in range(100)], "id long, pt array<bigint>, w long, k string")
    sizes = by_column(pts, F.col("k"), 20).groupBy("part").count().collect()
    assert sum(r["count"] for r in sizes) == 100 and max(r["count"] for r in sizes) < 60


def test_general_metrics(spark):
    words = ["kitten", "mitten", "sitting", "bitten", "zzzzzz", "zzzzz"]
    pts = spark.createDataFrame([(i, x, 1, 0) for i, x in enumerate(words)], "id long, pt string, w long, part int")
    assert C.one_round(pts, ClusterSpec(2), Edit()).rows.agg(F.sum("w")).first()[0] == 6
    cats = spark.createDataFrame([(i, [str(i % 2), "x"], 1, 0) for i in range(10)], "id long, pt array<string>, w long, part int")
    assert sorted(r["w"] for r in C.one_round(cats, ClusterSpec(2), Hamming()).rows.collect()) == [5, 5]


@pytest.mark.parametrize("t", [1, 2])
def test_local_search_within_its_ratio_of_the_optimum(t):
    rng = np.random.default_rng(12)
    for _ in range(5):
        data, w = L1.load(rng.integers(0, 100, (14, 2)).tolist()), rng.integers(1, 4, 14)
        _, opt = S.exact(L1, data, w, 3, 1)
        _, cost = S.swap_search(L1, data, w, 3, 1, t=t)
        assert opt <= cost <= bounds.local_search_alpha("median", t) * opt


@pytest.mark.parametrize("p", [1, 2])
def test_line_optimum_equals_enumeration(p):
    rng = np.random.default_rng(13)
    for k in (1, 2, 3):
        x, w = rng.integers(0, 60, 12), rng.integers(1, 4, 12)
        picks, cost = S.exact_line(x, w, k, p)
        metric = L1 if p == 1 else SQ
        assert cost == S.exact(metric, metric.load(x[:, None].tolist()), w, k, p)[1]
        assert (np.min(np.abs(x[:, None] - x[picks][None]) ** p, 1) * w).sum() == cost


def test_other_solvers_do_not_beat_the_optimum():
    rng = np.random.default_rng(14)
    x, w = rng.normal(0, 10, (30, 2)), np.ones(30, np.int64)
    e = Euclidean()
    opt = {p: S.exact(e, x, w, 2, p)[1] for p in (1, 2)}
    assert S.medoids(e, x, w, 2, 2)[1] >= opt[2] - 1e-9 and S.seed_only(e, x, w, 2, 1)[1] >= opt[1] - 1e-9
    assert S.lloyd(x, w, 2)[1] <= S.seed_only(e, x, w, 2, 2)[1] + 1e-9
    assert S.weiszfeld(x, w, 2)[1] <= S.seed_only(e, x, w, 2, 1)[1] + 1e-9
    with pytest.raises(CoreclustError):
        S.exact(e, np.zeros((3000, 1)), np.ones(3000), 3, 1)


def test_a_large_summary_is_reduced_until_it_fits(spark):
    """The ratio carries the error of every reduction, and holds."""
    xs = np.random.default_rng(21).integers(0, 10**5, 600)
    pts = line(spark, xs).select("id", "pt")
    opt = S.exact_line(xs, np.ones(600, np.int64), 3, 1)[1]
    plain, tight = (cluster(pts, ClusterSpec(3, eps=Fraction(1, 10), m=6), L1, most_rows=most) for most in (4000, 60))
    a, b = ({x["key"]: x for x in r.report().collect()} for r in (plain, tight))
    assert plain.plan.ratio == pytest.approx(bounds.ratio(5 / (1 - 3 * 1e-3), 0.1)[0])
    assert a["guarantee"]["value"] == b["guarantee"]["value"] == 1 and "further reduction" in b["proven_ratio"]["note"]
    assert a["proven_ratio"]["value"] < b["proven_ratio"]["value"] < math.inf
    for r in (a, b):
        assert opt <= r["cost"]["value"] <= r["proven_ratio"]["value"] * opt


@pytest.mark.parametrize("metric, p", [(L1, 1), (SQ, 2)])
def test_swaps_where_the_rows_lie_end_in_a_local_optimum(spark, metric, p):
    rng = np.random.default_rng(22)
    xs, w = rng.integers(0, 1000, (150, 3)), rng.integers(1, 5, 150)
    pts = spark.createDataFrame([(i, x.tolist(), int(v)) for i, (x, v) in enumerate(zip(xs, w, strict=True))], "id long, pt array<bigint>, w long")
    got = S.local_search_distributed(pts, 4, metric, p, block=40, start_rows=30)
    picks = sorted(r["center_id"] for r in got.collect())
    data = metric.load(xs.tolist())
    again, _ = S.swap_search(metric, data, w, 4, p, start=np.array(picks))
    assert again.tolist() == picks and got.count() == 4


def test_swaps_value_few_candidates_and_no_copies(spark, monkeypatch):
    """Copies are one candidate, and groups without room for a gain are passed over; the result is still a local optimum of all rows."""
    rng = np.random.default_rng(26)
    xs = np.concatenate([rng.integers(c, c + 3000, (500, 2)) for c in (0, 4000, 9000)])
    rows = [(i, xs[i % 1500].tolist(), 1) for i in range(6000)]
    valued, plain = [], S._swap_values
    monkeypatch.setattr(S, "_swap_values", lambda *a: valued.append(len(a[4])) or plain(*a))
    got = S.local_search_distributed(spark.createDataFrame(rows, "id long, pt array<bigint>, w long"), 3, L1, 1, start_rows=100)
    picks = sorted(r["center_id"] for r in got.collect())
    again, _ = S.swap_search(L1, L1.load(xs.tolist()), np.full(1500, 4), 3, 1, start=np.array(picks))
    assert again.tolist() == picks and max(picks) < 1500
    assert max(valued) < 1000


def test_local_search_beyond_one_task(spark):
    xs = np.random.default_rng(27).integers(0, 1000, (90, 2))
    pts = spark.createDataFrame([(i, x.tolist(), 1) for i, x in enumerate(xs)], "id long, pt array<bigint>, w long")
    for most in (90, 60):
        picks = sorted(r["center_id"] for r in S.local_search(pts, 4, L1, 1, most=most).collect())
        assert S.swap_search(L1, L1.load(xs.tolist()), np.ones(90, np.int64), 4, 1, start=np.array(picks))[0].tolist() == picks


@pytest.mark.parametrize("metric, data", [(L1, [[1, 2], [5, 9], [-3, 4]]), (SQ, [[1, 2], [5, 9], [-3, 4]]), (Lp(3), [[1.0], [4.5], [2.0]]), (Edit(), ["a", "abc", "xyz"])])
def test_blocks_of_distances_equal_single_rows(metric, data):
    loaded, at = metric.load(data), np.array([0, 2, 1])
    for p in (1, 2):
        assert np.allclose(metric.block(loaded, np.array([1, 2]), at, p), [metric.one(loaded, i, at, p) for i in (1, 2)])


@pytest.mark.parametrize("objective", ["median", "means"])
def test_summaries_of_certified_covers_are_reduced_in_small_parts_and_keep_their_ratio(spark, objective):
    """Seeds by local search take no part of any size, and a reduction that would lose the proof is not made."""
    p, metric = (1, L1) if objective == "median" else (2, SQ)
    spec = ClusterSpec(2, objective, Fraction(1, 10), beta=Fraction(51 if p == 1 else 91, 10), seeder="local_search", strict=True)
    xs = np.random.default_rng(28).integers(0, 10**6, 4_600)
    less = C.reduce_again(line(spark, xs, parts=1), spec, metric)
    assert less.stats.count() == 3 and less.rows.agg(F.sum("w")).first()[0] == 4_600
    few = np.unique(xs[:400])
    r = cluster(line(spark, few).select("id", "pt"), spec, metric, most_rows=50)
    report = {x["key"]: x["value"] for x in r.report().collect()}
    opt = S.exact_line(few, np.ones(len(few), np.int64), 2, p)[1]
    assert report["guarantee"] == 1 and opt <= report["cost"] <= report["proven_ratio"] * opt < math.inf


def test_a_summary_that_does_not_shrink_is_solved_where_it_lies(spark):
    xs = np.random.default_rng(23).normal(0, 1, (120, 40))
    pts = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(xs)], "id long, pt array<double>")
    r = cluster(pts, ClusterSpec(3, eps=Fraction(1, 10)), Euclidean(), most_rows=50)
    report = {x["key"]: x for x in r.report().collect()}
    assert report["core_rows"]["value"] == 120 and report["guarantee"]["value"] == 1 and r.centers.count() == 3
    with pytest.raises(CoreclustError, match="do not shrink"):
        C.two_round(by_hash(pts.withColumn("w", F.lit(1).cast("long")), 2), ClusterSpec(3, eps=Fraction(1, 10)), Euclidean(), broadcast_rows=50)


def test_heuristics_claim_no_ratio(spark):
    pts = line(spark, range(0, 900, 30)).select("id", "pt")
    for r in (cluster(pts, ClusterSpec(3, m=6), L1, method="medoids"), cluster_continuous(pts, ClusterSpec(3, m=6), L1)):
        report = {x["key"]: x for x in r.report().collect()}
        assert report["proven_ratio"]["value"] == math.inf and report["guarantee"]["value"] == 0
        assert report["proven_ratio"]["note"].startswith("no proven ratio")
    assert alpha_of(ClusterSpec(2, "means", Fraction(1, 10))) == 9 and alpha_of(ClusterSpec(2), t=2) == 4 and alpha_of(ClusterSpec(2), "exact") == 1


@pytest.mark.parametrize("objective", ["means", "median"])
def test_continuous_passes_where_the_rows_lie(spark, objective):
    rng = np.random.default_rng(24)
    x = np.concatenate([rng.normal(c, 5, (80, 2)) for c in (0, 100, 250)])
    pts = spark.createDataFrame([(i, v.tolist(), 1 + i % 3) for i, v in enumerate(x)], "id long, pt array<double>, w long").repartition(3)
    cost = [M.cost(pts, S.solve_continuous(pts, 3, objective, most=most), Euclidean(), 2 if objective == "means" else 1).first()["cost"] for most in (10**6, 10)]
    assert cost[1] <= 1.02 * cost[0]


def test_given_table_of_centers(spark):
    """Targets outside the points: the cover holds against them, with the parts' own tolerances."""
    xs = np.random.default_rng(25).integers(0, 5000, 200)
    pts = line(spark, xs, parts=2)
    targets = spark.createDataFrame([(1, [100]), (2, [2600]), (3, [4700])], "center_id long, pt array<bigint>")
    cs = C.given_targets(pts, targets, ClusterSpec(3), L1, mapping=True)
    part = {r["id"]: r["part"] for r in pts.collect()}
    d = np.abs(xs[:, None] - [100, 2600, 4700]).min(1)
    tolerance = {p: d[[i for i in range(200) if part[i] == p]].mean() for p in (0, 1)}
    got = cs.mapping.collect()
    assert len(got) == 200 and all(4 * r["d"] <= max(tolerance[r["part"]], d[r["id"]]) + 1e-9 for r in got)
    assert cs.rows.agg(F.sum("w")).first()[0] == 200 and cs.rows.count() < 100


def test_repeated_ids_are_found_in_their_part(spark):
    with pytest.raises(Exception, match="more than once"):
        cluster(spark.createDataFrame([(1, [1]), (2, [5]), (1, [9])], "id long, pt array<bigint>"), ClusterSpec(1), L1)


def test_end_to_end_and_report(spark, tmp_path):
    rng = np.random.default_rng(15)
    xs = np.concatenate([rng.integers(c, c + 50, 60) for c in (0, 1000, 5000)])
    pts = line(spark, xs).select("id", "pt")
    for run in (cluster, cluster_fast):
        r = run(pts, ClusterSpec(3, m=6), L1)
        assert r.profile().count() == 3 and r.profile().agg(F.sum("n")).first()[0] == 180
        report = {x["key"]: x["value"] for x in r.report().collect()}
        opt = S.exact_line(xs, np.ones(180, np.int64), 3, 1)[1]
        assert opt <= report["cost"] <= report["proven_ratio"] * opt
    free = cluster_continuous(pts, ClusterSpec(3, "means", Fraction(1, 10), m=6), SQ)
    assert free.centers.count() == 3
    save_model(r.centers, {"k": 3}, str(tmp_path / "m"))
    centers, params = load_model(spark, str(tmp_path / "m"))
    assert centers.count() == 3 and params == {"k": 3}
    write_coreset(r.coreset.rows, str(tmp_path / "c"))
    assert "part" in spark.read.parquet(str(tmp_path / "c")).columns


def test_more_centers_than_places(spark):
    r = cluster(line(spark, [1, 1, 2]).select("id", "pt"), ClusterSpec(5), L1)
    assert M.cost(r.points, r.centers, L1).first()["cost"] == 0


@pytest.mark.parametrize("bad", [{"k": 0}, {"eps": 1}, {"eps": 0}, {"beta": Fraction(1, 2)}, {"m": 1}, {"objective": "modes"}, {"objective": "means", "eps": Fraction(3, 4)}, {"objective": "means", "eps": Fraction(1, 5), "strict": True}])
def test_bad_parameters(bad):
    with pytest.raises(CoreclustError):
        ClusterSpec(**{"k": 2} | bad)


@pytest.mark.parametrize("rows", [[(1, [1]), (None, [2])], [(1, None)], [(1, [1]), (1, [2])], [(1, [1]), (2, [1, 2])]])
def test_bad_rows(spark, rows):
    with pytest.raises(CoreclustError):
        check_points(spark.createDataFrame(rows, "id long, pt array<bigint>"))


def test_nan_is_reported_or_dropped(spark):
    df = spark.createDataFrame([(1, [1.0]), (2, [float("nan")])], "id long, pt array<double>")
    with pytest.raises(CoreclustError, match="1 of 2"):
        check_points(df)
    assert check_points(df, "drop").count() == 1
    assert check_points(df.where("id > 9")).count() == 0


def test_bounds_and_plans():
    assert bounds.ratio(1, 0.1)[0] == pytest.approx(2.24) and bounds.ratio(4, 0.05)[0] == pytest.approx(6.04)
    assert bounds.ratio(1, 0.1, rounds=1)[0] == pytest.approx(2.6) and bounds.ratio(1, 0.1, continuous=True)[0] == pytest.approx(1.4)
    assert bounds.ratio(1, 0.5)[1].endswith("one-round argument") and bounds.ratio(1, 0.05, "means")[0] == pytest.approx(4.038, abs=1e-3)
    assert resolve(10**6, ClusterSpec(10, eps=0.1)).rounds == 2 and resolve(10**6, ClusterSpec(10, eps=0.5)).rounds == 1
    p = resolve(10**12, ClusterSpec(100, eps=0.1), rows=10**6)
    assert p.parts == 10**6 and p.rows_per_part == 10**6
    assert part_count(10) == 4 and part_count(10**6, rows=1000) == 1000
    small, large = (bounds.local_space(n, 10, 0.5, 1, 1) for n in (10**6, 8 * 10**6))
    assert 4 <= large / small < 6


def test_relaxed_triangle_inequality():
    rng = np.random.default_rng(16)
    data = L1.load(rng.integers(0, 100, (30, 2)).tolist())
    for c in (0.1, 1, 7):
        assert V.relaxed_triangle(L1, data, rng.integers(0, 30, (50, 3)), c) <= 1e-9


def test_subset_optimum_factor():
    rng = np.random.default_rng(17)
    xs = rng.integers(0, 200, (16, 1)).tolist()
    for metric, p, factor in ((L1, 1, 2), (SQ, 2, 4)):
        data, w = metric.load(xs), np.ones(16, np.int64)
        best, _ = S.exact(metric, data, w, 2, p)
        for _ in range(10):
            m = np.sort(rng.choice(16, 6, replace=False))
            sub = metric.load([xs[k] for k in m])
            own = S.exact(metric, sub, np.ones(6, np.int64), 2, p)[1]
            outer = metric.nearest(data, best, m, p)[0].sum()
            assert own <= factor * outer


def test_hash_parts_keep_all_rows(spark):
    pts = line(spark, range(50)).drop("part")
    assert by_hash(pts, 4).count() == 50


def test_second_round_shortcut_changes_nothing(spark):
    """Skipping the union where the part's own cover is near enough gives the cover of the plain rule."""
    rng = np.random.default_rng(18)
    xs = np.concatenate((rng.integers(0, 500, 150), rng.integers(10**5, 10**5 + 10**4, 30)))
    pts, spec = line(spark, xs, parts=3), ClusterSpec(3, m=4)
    first = C.one_round(pts, spec, L1)
    got = {(r["part"], r["id"]): r["w"] for r in C.two_round(pts, spec, L1, first=first).rows.collect()}
    union = np.array([r["pt"][0] for r in first.rows.collect()])
    num, den = C.tolerance(first)
    for part in range(3):
        ids = np.flatnonzero(np.arange(len(xs)) % 3 == part)
        x = xs[ids]
        d = np.abs(x[:, None] - union[None]).min(1)
        c = ball_cover(L1, L1.load(x[:, None].tolist()), d, num, den, spec.eps, spec.beta)
        want = {(part, int(ids[k])): int((c.tau == k).sum()) for k in c.pivots}
        assert want == {k: w for k, w in got.items() if k[0] == part}


def test_pruned_rounds_equal_plain_ones_with_fewer_distances(spark):
    rng = np.random.default_rng(19)
    rows = [(i, [int(a), int(b)], 1) for i, (a, b) in enumerate(rng.integers(0, 3000, (400, 2)))]
    pts = by_modulo(spark.createDataFrame(rows, "id long, pt array<bigint>, w long"), 2)
    out = []
    for prune in (False, True):
        cs = C.two_round(pts, ClusterSpec(4, m=8, prune=prune), L1)
        out.append((sorted((r["part"], r["id"], r["w"]) for r in cs.rows.collect()), cs.stats.agg(F.sum("n_dist")).first()[0]))
    assert out[0][0] == out[1][0] and out[1][1] < out[0][1]


def test_memory_by_round(spark):
    pts = line(spark, range(0, 4000, 7), parts=4)
    first = C.one_round(pts, ClusterSpec(3), L1)
    second = C.two_round(pts, ClusterSpec(3), L1, first=first)
    m = {r["round"]: r for r in M.memory(first, second).collect()}
    n, c = 572, first.rows.count()
    assert m[1]["sum_rows"] == n and m[2]["sum_rows"] == n + 4 * c and m[3]["max_rows"] == second.rows.count()
    assert m[1]["max_rows"] == 143 + 3
    # more parts, smaller first-round tasks
    many = C.one_round(by_modulo(pts.drop("part"), 16), ClusterSpec(3), L1)
    assert M.memory(many, many).where("round = 1").first()["max_rows"] < m[1]["max_rows"]


def test_empty_input_gives_empty_output(spark):
    pts = line(spark, [1, 2]).where("id > 9")
    cs = C.one_round(pts, ClusterSpec(2), L1)
    assert cs.rows.count() == 0 and C.tolerance(cs) == (0, 1)
    with pytest.raises(CoreclustError):
        C.reduce_again(cs, ClusterSpec(2), L1, 10)


def test_angular_and_mixed_payloads_in_a_round(spark):
    from coreclust.functions.metrics import Angular, Mix

    rng = np.random.default_rng(20)
    v = spark.createDataFrame([(i, [float(a), float(b)], 1, 0) for i, (a, b) in enumerate(rng.normal(size=(60, 2)))], "id long, pt array<double>, w long, part int")
    assert C.one_round(v, ClusterSpec(3), Angular()).rows.agg(F.sum("w")).first()[0] == 60
    mixed = spark.createDataFrame([(i, ([i], ["a" if i % 2 else "b"]), 1, 0) for i in range(20)], "id long, pt struct<x:array<bigint>,c:array<string>>, w long, part int")
    metric = Mix([(1, "x", L1), (5, "c", Hamming())])
    cs = C.two_round(mixed, ClusterSpec(2), metric)
    assert cs.rows.agg(F.sum("w")).first()[0] == 20
