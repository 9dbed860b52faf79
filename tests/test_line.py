"""Pairs of centers on a line against enumeration, and the queries beyond the sizes that could be enumerated."""

from __future__ import annotations

import itertools

import duckdb
import numpy as np
import pytest

from coreclust import experiments as E
from coreclust.functions.metrics import Euclidean, Lp
from coreclust.operators import line as L
from coreclust.operators import solve as S

L1, SQ = Lp(1), Euclidean(exact=True)


def frame(spark, xs, w=None):
    return spark.createDataFrame([(3 * i + 1, [int(x)], int(1 if w is None else w[i])) for i, x in enumerate(xs)], "id long, pt array<bigint>, w long")


def enumerated(xs, w, centers):
    return {(a, b): int((np.minimum(np.abs(xs - xs[a]), np.abs(xs - xs[b])) * w).sum()) for a, b in itertools.combinations(centers, 2)}


@pytest.mark.parametrize("top, n", [(4, 9), (12, 10), (1000, 14), (1, 3), (1, 1)])
def test_pairs_on_a_line_equal_enumeration(spark, top, n):
    rng = np.random.default_rng(top + n)
    for _ in range(3):
        xs, w = rng.integers(-top + 1, top, n), rng.integers(1, 4, n)
        pts, cost = frame(spark, xs, w), enumerated(xs, w, range(n))
        best = min(((c, 3 * a + 1, 3 * b + 1) for (a, b), c in cost.items()), default=None)
        assert L.two_medians(pts) == (best and (best[1], best[2], best[0]))
        some = sorted(rng.choice(n, max(1, n // 2), replace=False).tolist())
        core = frame(spark, xs[some], rng.integers(1, 9, len(some)))
        at, few = L.places(pts), L.places(core)
        assert L.best_among(at, few) == min(enumerated(xs, w, some).values(), default=None)
        got = L.pair_errors(spark, at, few).first()
        light = np.array([r["w"] for r in core.orderBy("id").collect()])
        less = {s: int((np.minimum(np.abs(xs[some] - xs[s[0]]), np.abs(xs[some] - xs[s[1]])) * light).sum()) for s in cost}
        assert got["solutions"] == len(cost)
        assert got["error"] == pytest.approx(max((abs(c - less[s]) / c for s, c in cost.items() if c), default=0))


@pytest.mark.parametrize("p", [1, 2])
def test_line_optimum_of_many_places(p):
    """Levels at once and in pieces, and sums beyond 64 bits, give the optimum of plain dynamic programming."""
    rng = np.random.default_rng(31)
    x, w = rng.integers(0, 500, 60), rng.integers(1, 5, 60)
    cost = [[min(int((w[np.argsort(x)][a:j] * np.abs(np.sort(x)[a:j] - c) ** p).sum()) for c in np.sort(x)[a:j]) for j in range(a + 1, 61)] for a in range(60)]
    best = [0] + [10**12] * 60
    for _ in range(4):
        best = [0] + [min(best[a] + cost[a][j - a - 1] for a in range(j)) for j in range(1, 61)]
    assert S.exact_line(x, w, 4, p)[1] == best[60]
    far = x.astype(np.int64) * 10**7 + 10**9
    picks, value = S.exact_line(far, w * 10**4, 4, p)
    assert value == pytest.approx(best[60] * 10 ** (7 * p + 4)) and len(picks) == 4
    many = rng.integers(0, 10**9, 250_000)
    assert S.exact_line(many, np.ones(250_000, np.int64), 2, p)[1] > 0


@pytest.fixture(scope="module")
def larger(tmp_path_factory):
    """2,400 suppliers, some with equal balances."""
    d = tmp_path_factory.mktemp("larger")
    duckdb.sql(f"copy (select * replace (s_suppkey + 1000 * i as s_suppkey, s_acctbal + i * 0.37 * (s_suppkey % 7) as s_acctbal) from '/root/testdata/sf0.1/supplier.parquet', range(3) t(i) where s_suppkey < 800) to '{d}/supplier.parquet'")
    return str(d)


@pytest.mark.parametrize("name", ["bounded_supplier", "centroid_supplier", "distortion_supplier", "exact_supplier"])
def test_supplier_queries_beyond_enumeration(spark, larger, name):
    got = E.QUERIES[name](spark, larger).collect()
    assert len(got) == 1
    x = np.round(spark.read.parquet(f"{larger}/supplier.parquet").orderBy("s_suppkey").toPandas()["s_acctbal"].to_numpy() * 100).astype(np.int64)
    ids = spark.read.parquet(f"{larger}/supplier.parquet").select("s_suppkey").orderBy("s_suppkey").toPandas()["s_suppkey"].to_numpy()
    opt, r = int(S.exact_line(x, np.ones(len(x), np.int64), 2, 1)[1]), got[0]
    if name == "exact_supplier":
        a, b = (x[ids == r[c]][0] for c in ("s1", "s2"))
        assert r["cost"] == opt == np.minimum(np.abs(x - a), np.abs(x - b)).sum() and r["s1"] < r["s2"]
    elif name == "bounded_supplier":
        assert r["den"] == opt and r["num"] > 0
    elif name == "centroid_supplier":
        assert r["opt"] == opt and opt <= r["cost_best_in_e"] < 1.2 * opt
    else:
        assert r["solutions"] == len(x) * (len(x) - 1) // 2 and 0 < r["max_error"] < 0.5


def test_guarantee_with_more_customers_than_a_list_may_hold(spark, tmp_path):
    """210,000 customers of 1,500 balances: the line's optimum counts places, not rows."""
    duckdb.sql(f"copy (select * replace (c_custkey + 2000 * i as c_custkey) from '/root/testdata/sf0.01/customer.parquet', range(140) t(i)) to '{tmp_path}/customer.parquet'")
    got = E.QUERIES["guarantee_continuous_customer"](spark, str(tmp_path)).first()
    one = E._line(E.customer(spark, "/root/testdata/sf0.01"))
    assert got["holds"] and got["optimum"] == 140 * S.exact_line(*one, 5, 1)[1]
