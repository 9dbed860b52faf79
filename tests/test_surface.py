from __future__ import annotations

import shutil
import subprocess
import sys
from pathlib import Path

import numpy as np
from pyspark.sql import functions as F

import __spark_entry__ as entry
from coreclust import workloads as W
from coreclust.functions.metrics import Lp
from coreclust.functions.sqlfn import register
from coreclust.operators import baseline as B
from coreclust.operators import coreset as C
from coreclust.operators import measure as M
from coreclust.schema import ClusterSpec
from coreclust.sources.synthetic import MetricPoints
from coreclust.sources.tables import read, stream, with_event_time
from coreclust.streaming.windows import MergeTree, batch_coresets, keyed_summaries, window_coreset

L1 = Lp(1)


def test_entry_and_registered_queries(spark):
    assert entry.entry(spark).count() == 5
    assert set(W.ORACLE_SQL) <= set(W.QUERIES) <= set(entry.queries())


def test_queries_equal_their_sql(spark, sf):
    """A cross-section of the registered queries against the other engine."""
    import duckdb

    con = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "benchmark"):
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    for name in ("cover_means_customer", "two_round_median_customer", "two_round_median_part", "cover_order_orders", "cover_hamming_part", "shells_events", "memory_customer", "baseline_grid_part", "asof_purchase_events", "purity_documents"):
        df = W.QUERIES[name](spark, sf)
        cols = sorted(df.columns)
        got = sorted(tuple(r[c] for c in cols) for r in df.collect())
        r = con.execute(W.ORACLE_SQL[name])
        at = [[x[0] for x in r.description].index(c) for c in cols]
        assert got == sorted(tuple(x[i] for i in at) for x in r.fetchall()), name


def test_sql_surface(spark):
    register(spark)
    rows = [(i, [i * i % 97], i % 2) for i in range(60)]
    spark.createDataFrame(rows, "id long, pt array<bigint>, part int").createOrReplaceTempView("points_view")
    got = spark.sql("SELECT * FROM cover_points(TABLE(SELECT id, pt, part FROM points_view) PARTITION BY (part), 4, 0.5, 1.0)")
    pts = spark.table("points_view").withColumn("w", F.lit(1).cast("long"))
    want = C.one_round(pts, ClusterSpec(4), L1).rows
    assert sorted((r["id"], r["w"]) for r in got.collect()) == sorted((r["id"], r["w"]) for r in want.collect())
    assert spark.sql("SELECT l1_distance(array(1D, 2D), array(3D, 5D)) AS d, squared_distance(array(1D), array(4D)) AS q").first() == (5.0, 9.0)
    assert spark.sql("SELECT weighted_cost(d, w) AS c FROM VALUES (2D, 3D), (1D, 1D) t(d, w)").first()["c"] == 7.0


def test_estimator(spark, tmp_path):
    from coreclust.estimator import CoresetClustering, CoresetClusteringModel

    df = spark.createDataFrame([(i, [float(i % 3 * 100 + i % 5)]) for i in range(90)], "id long, features array<double>")
    model = CoresetClustering(k=3).fit(df)
    assert model.transform(df).select("prediction").distinct().count() == 3
    model.save(str(tmp_path / "model"))
    again = CoresetClusteringModel.load(spark, str(tmp_path / "model"))
    assert sorted(map(tuple, again.transform(df).select("id", "prediction").collect())) == sorted(map(tuple, model.transform(df).select("id", "prediction").collect()))


def test_baselines(spark):
    rng = np.random.default_rng(4)
    xs = np.concatenate([rng.integers(c, c + 40, 50) for c in (0, 2000)])
    pts = spark.createDataFrame([(i, [int(x)], 1, i % 2) for i, x in enumerate(xs)], "id long, pt array<bigint>, w long, part int")
    assert B.local_centers(pts, ClusterSpec(2), L1).agg(F.sum("w")).first()[0] == 100
    assert B.sequential(pts, 2, L1, 1).count() == 2
    centers = [(0, [20]), (1, [2020])]
    sample = B.importance_sample(pts, centers, L1, 1, 40).agg(F.sum("w").alias("w"), F.count("*").alias("n")).first()
    assert 0 < sample["n"] < 100 and 50 < sample["w"] < 170
    grid = B.shell_grid(pts, centers, L1, 5, 4)
    assert grid.agg(F.sum("w")).first()[0] == 100
    assert B.library_kmeans(pts, 2).groupBy("cluster").count().count() == 2
    assert B.farthest_on_parts(pts, ClusterSpec(2), L1).count() == 4
    assert B.euclidean_cost(pts, [(0, [20.0]), (1, [2020.0])], 1) > 0


def test_measures(spark):
    pts = spark.createDataFrame([(i, [i], 1, 0) for i in range(20)], "id long, pt array<bigint>, w long, part int")
    assert M.ratio(0, 0) == 1 and M.ratio(3, 2) == 1.5
    a = spark.createDataFrame([(0, "x"), (0, "x"), (0, "y"), (1, "y")], "center_id long, lang string")
    assert sorted(map(tuple, M.purity(a, "lang").collect())) == [(0, "x", 2), (1, "y", 1)]
    assert M.pair_agreement(a, "lang") == 0.5
    assert M.exchanges(pts.groupBy("part").count()) >= 1 and M.timed(pts) > 0
    size = M.size(C.one_round(pts, ClusterSpec(2), L1)).first()
    assert size["n"] == 20 and size["compression"] >= 1


def test_sources(spark, tmp_path):
    spark.dataSource.register(MetricPoints)
    df = spark.read.format("metric_points").option("n", "100").option("dim", "3").load()
    assert df.count() == 100 and len(df.first()["pt"]) == 3
    df.select("id", "w").write.orc(str(tmp_path / "o"))
    assert read(spark, str(tmp_path / "o"), "orc", columns=["id"], where="id < 10").count() == 10
    df.select("id", "w").write.json(str(tmp_path / "j"))
    assert read(spark, str(tmp_path / "j"), "json", "id long, w long").count() == 100


def test_scan_reads_only_what_is_asked(spark, sf):
    plan = W.customer(spark, sf).where("id < 10")._jdf.queryExecution().executedPlan().toString()
    assert "ReadSchema: struct<c_custkey:bigint,c_acctbal:double>" in plan and "c_custkey" in plan.split("PushedFilters")[1]


def _points(df):
    return with_event_time(df).select("ts", F.col("event_id").alias("id"), W._event_vector().alias("pt"), F.lit(1).cast("long").alias("w"), "event_type")


def test_streamed_windows_equal_batch_parts(spark, sf):
    day = {(r["day"], r["id"], r["w"]) for r in W.QUERIES["stream_day_coreset_events"](spark, sf).collect()}
    batch = {(r["day"], r["id"], r["w"]) for r in W.QUERIES["window_coreset_events"](spark, sf).collect()}
    assert day < batch and len({d for d, *_ in batch} - {d for d, *_ in day}) == 1  # the last day is open


def test_micro_batches_and_keyed_state(spark, sf, tmp_path):
    src = _points(stream(spark, sf, "events"))
    q = batch_coresets(src.select("id", "pt", "w"), str(tmp_path / "b"), str(tmp_path / "bc"), ClusterSpec(5), L1).trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.read.parquet(str(tmp_path / "b")).agg(F.sum("w")).first()[0] == 1000
    out = keyed_summaries(src.select("event_type", "id", "pt", "w"), "event_type", ClusterSpec(5), L1, 64)
    q = out.writeStream.outputMode("update").format("memory").queryName("kept").option("checkpointLocation", str(tmp_path / "kc")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.sql("SELECT sum(w) FROM kept").first()[0] == 1000


def test_sliding_windows(spark, sf):
    e = _points(spark.read.parquet(f"{sf}/events.parquet"))
    out = window_coreset(e.select("ts", "id", "pt", "w"), ClusterSpec(3), L1, window="2 days", slide="1 day")
    assert out.agg(F.sum("w")).first()[0] == 2000
    dealt = window_coreset(e.select("ts", "id", "pt", "w"), ClusterSpec(3), L1, tasks=3)
    assert dealt.agg(F.sum("w")).first()[0] == 1000 and dealt.count() > window_coreset(e.select("ts", "id", "pt", "w"), ClusterSpec(3), L1).count()


def test_merge_tree_keeps_weight_and_error():
    tree = MergeTree(ClusterSpec(3), L1, 32)
    for k in range(20):
        tree.add([(k * 40 + i, [(k * 37 + i * 11) % 500], 1) for i in range(40)])
    assert sum(r[2] for r in tree.rows()) == 800 and len(tree.rows()) < 800 and tree.moved > 0


def test_merge_tree_stays_small_and_knows_its_error():
    """A stream fifty times as long leaves no larger state, and no set of centers costs more or less than `moved` says."""
    rng, tree, seen, most = np.random.default_rng(4), MergeTree(ClusterSpec(3), L1, 64, most_levels=4), [], []
    for k in range(400):
        rows = [(k * 40 + i, [int(x)], 1) for i, x in enumerate(rng.integers(0, 100_000, 40))]
        seen += rows
        tree.add(rows)
        most.append(len(tree.rows()))
    assert max(most[8:]) <= 4 * max(most[:8]) + 64 and sum(r[2] for r in tree.rows()) == len(seen)
    for _ in range(20):
        c = rng.integers(0, 100_000, 3)
        cost = [sum(w * min(abs(x[0] - c)) for _, x, w in rows) for rows in (seen, tree.rows())]
        assert abs(cost[0] - cost[1]) <= tree.moved


def test_entry_without_the_corpus_operators(tmp_path):
    root = Path(__file__).resolve().parent.parent
    shutil.copytree(root, tmp_path / "repo", ignore=shutil.ignore_patterns("llm", "corpus_pipeline.py", ".git", "__pycache__"))
    code = "import __spark_entry__ as e; q = e.queries(); print(len(q), any(k.startswith('op') or k == 'pipeline' for k in q), set(e.oracle_sql()) <= set(q))"
    got = subprocess.run([sys.executable, "-c", code], cwd=tmp_path / "repo", capture_output=True, text=True, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": str(tmp_path / "repo")})
    n, found, covered = got.stdout.split()
    assert int(n) >= 70 and found == "False" and covered == "True", got.stderr


def test_entry_without_a_library_of_the_corpus_operators():
    """A missing library takes the corpus queries with it, and no other."""
    code = "import sys; sys.modules['zstandard'] = None; import __spark_entry__ as e; q = e.queries(); print(len(q), any(k.startswith('op') or k == 'pipeline' for k in q), set(e.oracle_sql()) <= set(q))"
    got = subprocess.run([sys.executable, "-c", code], cwd=Path(__file__).resolve().parent.parent, capture_output=True, text=True, check=True).stdout.split()
    assert int(got[0]) == len(W.QUERIES) and got[1:] == ["False", "True"]
