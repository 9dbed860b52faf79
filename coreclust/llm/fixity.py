"""Fixity audit of web archive replicas by hash trees.

Each record is written out as a WARC response and hashed.  Records are ordered by id; ranges of
16 records, of 16 ranges, and of 16 of those are hashed in turn, which gives a tree per stretch
of 4096 ids.  An audit joins the replicas' roots and goes down only below roots that differ, so
what it moves depends on the damage, not on the archive.

Edge cases.  Null ids count as -1, null urls and bodies as empty.  Repeated ids share a leaf,
which hashes all their records in order of digest.  A record on one side only is `missing` or
`extra`.  Empty replicas give no rows.  Ids are expected to be spread; a leaf is one id.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import Scratch

FANOUT, LEVELS = 16, 3
EOL = "\r\n"


def serialised(page_id: Column, url: Column, html: Column) -> Column:
    """The bytes of a record, as text."""
    head = F.concat(F.lit(f"WARC/1.1{EOL}WARC-Type: response{EOL}WARC-Record-ID: <urn:page:"), page_id.cast("string"), F.lit(f">{EOL}WARC-Target-URI: "), url, F.lit(f"{EOL}Content-Length: "), F.octet_length(html).cast("string"), F.lit(EOL * 2))
    return F.concat(head, html, F.lit(EOL * 2))


def _segment() -> Column:
    return F.floor(F.col("page_id") / FANOUT**2).cast("long")


def records(pages: DataFrame, page_id: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """(page_id, segment, start, length, digest): place of each record in its segment's file, and its SHA-256."""
    raw = pages.select(F.coalesce(F.col(page_id), F.lit(-1)).cast("long").alias("page_id"), F.coalesce(F.col(url), F.lit("")).alias("url"), F.coalesce(F.col(html), F.lit("")).alias("html"))
    body = serialised(F.col("page_id"), F.col("url"), F.col("html"))
    hashed = raw.select("page_id", _segment().alias("segment"), F.octet_length(body).cast("long").alias("length"), F.sha2(body, 256).alias("digest"))
    order = Window.partitionBy("segment").orderBy("page_id", "digest").rowsBetween(Window.unboundedPreceding, 0)
    return hashed.select("page_id", "segment", (F.sum("length").over(order) - F.col("length")).alias("start"), "length", "digest")


def tree(recs: DataFrame, levels: int = LEVELS) -> list[DataFrame]:
    """(node, hash) by level: 0 the ids, then ever wider ranges.  Up to a segment, all levels share one dealing of rows."""
    leaf = recs.groupBy("segment", F.col("page_id").alias("node")).agg(F.sha2(F.array_join(F.sort_array(F.collect_list("digest")), ""), 256).alias("hash"))
    out = [leaf]
    for k in range(1, levels + 1):
        up = F.floor(F.col("node") / FANOUT).cast("long").alias("node")
        keys = ["segment", up] if k <= 2 else [up]
        ordered = F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("node", "hash"))), lambda x: F.concat_ws(":", x["node"], x["hash"])), ",")
        out.append(out[-1].groupBy(*keys).agg(F.sha2(ordered, 256).alias("hash")))
    return [t.select("node", "hash") for t in out]


def mismatches(left: list[DataFrame], right: list[DataFrame]) -> DataFrame:
    """(node, in_left, in_right): ids whose leaves differ, found from the roots down."""

    def differ(a: DataFrame, b: DataFrame) -> DataFrame:
        both = a.withColumnRenamed("hash", "l").join(b.withColumnRenamed("hash", "r"), "node", "full_outer")
        return both.where(~F.col("l").eqNullSafe(F.col("r"))).select("node", F.col("l").isNotNull().alias("in_left"), F.col("r").isNotNull().alias("in_right"))

    bad = differ(left[-1], right[-1])
    for k in range(len(left) - 2, -1, -1):
        above = bad.select(F.col("node").alias("parent"))
        under = [t.withColumn("parent", F.floor(F.col("node") / FANOUT).cast("long")).join(above, "parent", "left_semi").select("node", "hash") for t in (left[k], right[k])]
        bad = differ(*under)
    return bad


def audit(left: DataFrame, right: DataFrame, scratch: Scratch) -> DataFrame:
    """Every record of `left` with its status against `right` (ok, altered, missing), and the extra ones of `right`."""
    left, right = (scratch.write(records(p), name) for p, name in ((left, "left"), (right, "right")))
    trees = [[scratch.write(t, "level") if k else t for k, t in enumerate(tree(r))] for r in (left, right)]
    bad = scratch.write(mismatches(*trees), "bad")
    known = left.join(bad.where("in_left").select(F.col("node").alias("page_id"), "in_right"), "page_id", "left")
    status = F.when(F.col("in_right").isNull(), "ok").when(F.col("in_right"), "altered").otherwise("missing")
    extra = right.join(bad.where("NOT in_left").select(F.col("node").alias("page_id")), "page_id", "left_semi").withColumn("status", F.lit("extra"))
    cols = ["page_id", "segment", "start", "length", "digest", "status"]
    return known.withColumn("status", status).select(*cols).unionByName(extra.select(*cols))


def roots(recs: DataFrame) -> DataFrame:
    return tree(recs)[-1]


def range_of(damage: DataFrame) -> DataFrame:
    """Damaged byte ranges per segment file, neighbours united."""
    order = Window.partitionBy("segment").orderBy("start")
    new = F.coalesce((F.col("start") != F.lag(F.col("start") + F.col("length")).over(order)).cast("int"), F.lit(1))
    runs = damage.withColumn("run", F.sum(new).over(order))
    return runs.groupBy("segment", "run").agg(F.min("start").alias("start"), F.max(F.col("start") + F.col("length")).alias("end"), F.count("*").alias("records")).drop("run")


def damaged(pages: DataFrame, rules: dict[str, Column]) -> DataFrame:
    """A replica with stated damage: rows where `lost` holds go, where `flipped` holds the body gets another first character."""
    html = F.when(F.coalesce(rules["flipped"], F.lit(False)), F.concat(F.lit("~"), F.coalesce("html", F.lit("")))).otherwise(F.col("html"))
    return reduce(lambda d, c: d.where(~F.coalesce(c, F.lit(False))), [rules["lost"]], pages).withColumn("html", html)
