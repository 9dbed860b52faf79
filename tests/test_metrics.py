from __future__ import annotations

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from coreclust.functions import metrics as X
from coreclust.operators import assign as A
from coreclust.operators.points import by_content, collapse, evenly
from coreclust.schema import CoreclustError

VECTORS = [[0, 0], [3, 4], [-2, 7], [3, 4], [10, -1]]
CASES = [
    (X.lp(1), VECTORS), (X.lp(float("inf")), VECTORS), (X.lp(3, exact=False), [[float(v) for v in x] for x in VECTORS]), (X.euclidean(True), VECTORS), (X.euclidean(), [[float(v) for v in x] for x in VECTORS]),
    (X.angular(), [[1.0, 2.0], [2.0, -1.0], [1.0, 2.5], [-3.0, 1.0], [0.5, 0.5]]), (X.jaccard(), [["a", "b"], ["b"], [], ["a", "b", "c"], []]), (X.edit(), ["kitten", "sitting", "", "mitten", "kit"]), (X.hamming(), [["a", "b"], ["a", "c"], ["b", "c"], ["a", "b"], ["x", "y"]]),
]


@pytest.mark.parametrize("metric,payload", CASES, ids=lambda x: getattr(x, "name", ""))
@pytest.mark.parametrize("p", [1, 2])
def test_columns_and_blocks_agree(spark, metric, payload, p):
    kind = {str: "string", int: "bigint", float: "double"}
    sample = payload[0]
    pt = "string" if isinstance(sample, str) else f"array<{kind[type(sample[0])]}>"
    df = spark.createDataFrame(list(enumerate(payload)), f"id long, pt {pt}")
    first = df.where("id = 0").select(F.col("pt").alias("o"))
    got = [r["d"] for r in df.crossJoin(first).orderBy("id").select(metric.power_column(F.col("pt"), F.col("o"), p).alias("d")).collect()]
    want = metric.one(metric.load(payload), 0, np.arange(len(payload)), p)
    assert np.allclose(np.array(got, float), want)


@given(st.lists(st.text("abcé", max_size=9), min_size=2, max_size=6))
@settings(max_examples=60, deadline=None)
def test_edit_distance_is_the_textbook_one(words):
    def plain(a, b):
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            new = [i]
            for j, y in enumerate(b, 1):
                new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
            row = new
        return row[-1]

    m = X.edit()
    assert m.one(m.load(words), 0, np.arange(len(words))).tolist() == [plain(words[0], w) for w in words]


def test_axioms_hold_for_metrics_and_fail_for_squares(spark):
    pts = spark.createDataFrame([(i, [v]) for i, v in enumerate([0, 1, 5, 9, 9])], "id long, pt array<bigint>")
    ok = {r["axiom"]: r["violations"] for r in X.verify(pts, X.lp(1)).collect()}
    assert ok == {"identity": 0, "symmetry": 0, "sign": 0, "triangle": 0}
    bad = {r["axiom"]: r["violations"] for r in X.verify(pts, X.lp(1), p=2).collect()}
    assert bad["triangle"] > 0


def test_mixed_and_graph_metrics(spark):
    m = X.mix([(2, "v", X.lp(1)), (1, "c", X.hamming())])
    data = m.load([{"v": [1], "c": ["a"]}, {"v": [4], "c": ["b"]}])
    assert m.one(data, 0, np.array([0, 1])).tolist() == [0, 7] and m.exact
    with pytest.raises(CoreclustError):
        X.mix([(-1, "v", X.lp(1))])
    g = X.shortest_paths(spark.createDataFrame([(1, 2, 1), (2, 3, 1), (1, 3, 5)], "u long, v long, d long"))
    assert g.one(g.load([1, 2, 3]), 0, np.arange(3)).tolist() == [0, 1, 2]
    t = X.Table.of(spark.createDataFrame([(1, 2, 4)], "u long, v long, d long"))
    assert t.one(t.load([1, 2]), 0, np.arange(2)).tolist() == [0, 4]
    with pytest.raises(CoreclustError):
        X.lp(0.5)


def test_assignment_forms_agree(spark):
    rng = np.random.default_rng(1)
    pts = spark.createDataFrame([(i, [int(a), int(b)]) for i, (a, b) in enumerate(rng.integers(0, 50, (200, 2)))], "id long, pt array<bigint>")
    centers = [(i, r["pt"]) for i, r in enumerate(pts.orderBy("id").limit(7).collect())]
    for m, p in ((X.lp(1), 1), (X.euclidean(True), 2)):
        a = sorted(map(tuple, A.assign(pts, centers, m, p).collect()))
        assert a == sorted(map(tuple, A.assign_sql(pts, centers, m, p).collect()))


def test_separation_ball_and_dimension(spark):
    rng = np.random.default_rng(2)
    xs = rng.integers(0, 10**6, 300)
    pts = spark.createDataFrame([(i, [int(x)]) for i, x in enumerate(xs)], "id long, pt array<bigint>")
    want = np.diff(np.sort(xs)).min()
    assert A.separation(pts, X.lp(1), block=64).first()["min_d"] == want
    assert A.is_separated(pts, want - 1, X.lp(1)) and not A.is_separated(pts, want, X.lp(1))
    assert A.ball(pts, [int(xs[0])], 1000, X.lp(1)).count() == (abs(xs - xs[0]) <= 1000).sum()
    flat = pts.withColumn("pt", F.array(F.col("pt")[0], F.lit(0)))
    assert A.separation(flat, X.lp(1), block=64).first()["min_d"] == want
    assert A.separation(pts.limit(1), X.lp(1)).first()["min_d"] is None and A.separation(pts.union(pts), X.lp(1)).first()["min_d"] == 0
    dims = A.doubling_dimension(pts, X.lp(1)).collect()
    assert all(0 <= r["d_hat"] <= 3 for r in dims)


def test_points_collapse_and_even_parts(spark):
    df = spark.createDataFrame([(i, [i % 3]) for i in range(30)], "id long, pt array<bigint>").withColumn("w", F.lit(1).cast("long"))
    assert sorted((r["id"], r["w"]) for r in collapse(df).collect()) == [(0, 10), (1, 10), (2, 10)]
    assert sorted(r["n"] for r in evenly(df, 4, buckets=5).groupBy("part").agg(F.count("*").alias("n")).collect()) == [7, 7, 8, 8]
    assert by_content(df, F.col("pt")).agg(F.sum("w")).first()[0] == 30
