"""Workloads against their SQL, and what the sweeps and comparisons must show."""

from __future__ import annotations

import duckdb
import pytest
from pyspark.sql import functions as F

from coreclust import experiments as E
from coreclust import workloads as W
from coreclust.api import cluster
from coreclust.functions.metrics import Lp
from coreclust.operators import baseline as B
from coreclust.operators import measure as M
from coreclust.operators.solve import solve

L1 = Lp(1)
SMALL, LARGE = "/root/testdata/sf0.01", "/root/testdata/sf0.1"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark".split()


def plain(rows):
    return sorted((tuple(round(float(x), 6) if isinstance(x, float) else x for x in r) for r in rows), key=repr)


@pytest.mark.parametrize("name", ["guarantee_median_customer", "guarantee_means_customer", "guarantee_fast_customer", "guarantee_fast_means_customer", "guarantee_continuous_customer", "multi_swap_supplier", "cover_given_part", "metric_mix_part", "metric_table_customer", "cogrouped_cost_part", "ranks_customer", "set_operations_nation", "shell_separation_customer", "metric_edit_benchmark"])
def test_query_equals_its_sql(spark, name):
    df = E.QUERIES[name](spark, SMALL)
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from '{SMALL}/{t}.parquet'")
    sql = con.sql(E.ORACLE_SQL[name])
    assert sorted(sql.columns) == sorted(df.columns)
    assert plain(df.select(*sql.columns).collect()) == plain(sql.fetchall())


@pytest.mark.parametrize("name", ["baseline_costs_customer", "baseline_costs_part"])
def test_every_method_keeps_its_row(spark, name):
    """No method is dropped for its size, the optimum is never beaten, and coresets stay near the best."""
    got = {r["method"]: r for r in E.QUERIES[name](spark, SMALL).collect()}
    assert len(got) == 10
    for r in got.values():
        assert (r["cost"] is None) == (r["ratio_to_best"] is None) and (r["cost"] is not None or r["note"])
        assert r["ratio_to_best"] is None or r["ratio_to_best"] >= 1
        assert r["ratio_to_optimum"] is None or r["ratio_to_optimum"] >= 1
    assert got["two rounds"]["ratio_to_best"] < 1.03 and got["one round"]["ratio_to_best"] < 1.03
    assert got["weighted local centers"]["cost"] >= got["two rounds"]["cost"]


def test_a_method_too_large_for_one_task_says_so(spark, monkeypatch):
    monkeypatch.setattr(E, "MOST_ROWS", 100)
    got = {r["method"]: r for r in E.QUERIES["baseline_costs_customer"](spark, SMALL).collect()}
    assert got["sequential on all points"]["cost"] is None and "one task" in got["sequential on all points"]["note"]
    assert got["exact optimum"]["cost"] is not None and len(got) == 10


def test_covers_grow_as_eps_falls_and_stay_under_the_bound(spark):
    rows = sorted(E.QUERIES["eps_sweep_orders"](spark, SMALL).collect(), key=lambda r: r["eps"])
    assert [r["n_core"] for r in rows] == sorted((r["n_core"] for r in rows), reverse=True)
    assert all(r["n_core"] <= r["bound"] and r["w_sum"] == 15_000 for r in rows)


def test_memory_grows_with_two_thirds_of_the_input(spark):
    rows = sorted(E.QUERIES["memory_law_orders"](spark, LARGE).collect(), key=lambda r: r["n"])
    assert rows[-1]["n"] == 150_000 and all(0.55 < r["exponent"] < 0.8 for r in rows[1:])


def test_parts_of_any_kind_cover_all(spark):
    got = {r["variant"]: r for r in E.QUERIES["parts_ablation_part"](spark, SMALL).collect()}
    assert got["equal parts"]["largest"] in (333, 334) and got["skewed parts"]["largest"] > 500
    assert got["m 10"]["one_round"] < got["m 20"]["one_round"] < got["m 40"]["one_round"]
    assert all(r["two_rounds"] >= r["one_round"] for r in got.values())


def test_one_round_is_no_worse_than_a_sample_of_its_size(spark):
    """All orders of the larger table: reductions and their solver against local search on as many uniformly drawn rows."""
    pts = W.orders(spark, LARGE)
    r = cluster(pts, W.spec(10, 20, seeder="dsample"), L1, rounds=1)
    report = {x["key"]: x for x in r.report().collect()}
    assert report["guarantee"]["value"] == 1
    sample = B.uniform_sample(pts, 40)
    assert report["cost"]["value"] <= 1.01 * M.cost(pts, solve(sample, 10, L1, 1), L1).first()["cost"]


def test_three_rounds_on_the_largest_table(spark):
    got = W.QUERIES["three_rounds_lineitem"](spark, "/root/testdata/sf0.001").agg(F.sum("w").alias("w"), F.count("*").alias("k")).first()
    assert got["w"] == spark.read.parquet("/root/testdata/sf0.001/lineitem.parquet").count() and got["k"] == 20
