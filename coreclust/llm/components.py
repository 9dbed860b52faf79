"""Connected components of a distributed edge list, by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch

ROUNDS = 60
#: Pieces into which every node's neighbourhood is dealt for the joins; a larger hub's pieces are split further by the session's adaptive skew joins.
SALTS = 8


def _with_least(e: DataFrame) -> DataFrame:
    """Edges (u, v) with the smallest neighbour `m` of u.

    The hint keeps the join a merge join: the repeated rows compress so well that they would
    pass for small enough to broadcast.
    """
    least = e.groupBy("u").agg(F.min("v").alias("m")).withColumn("s", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return e.withColumn("s", F.pmod(F.hash("v"), F.lit(SALTS))).join(least.hint("merge"), ["u", "s"]).select("u", "v", "m")


def components(edges: DataFrame, scratch: Scratch) -> DataFrame:
    """(node, component) for every node of `edges` (a, b): the smallest node it can reach.

    Each round hangs a node's larger neighbours, then its smaller ones, on the smallest of its
    neighbourhood.  The edges end as stars.  Rounds are written tables; nothing is collected
    but a count and a checksum.
    """
    e = edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    e, before = scratch.write(e, "edges"), None
    for _ in range(ROUNDS):
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = _with_least(both).where("v > u").select(F.col("v").alias("u"), F.least("u", "m").alias("v")).distinct()
        small = _with_least(large).select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("x")).select("x.u", "x.v").where("u <> v").distinct()
        after, old = scratch.write(small, "edges"), e
        e = after
        now = e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first()
        scratch.drop(old)
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"no fixed point in {ROUNDS} rounds")
    roots = e.select("v").distinct().select(F.col("v").alias("node"), F.col("v").alias("component"))
    return e.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots)
