"""Coresets of streams: any split of the points by time is a legal partition, so window coresets compose.

Rows later than the watermark are dropped, and what is proven holds for the rows accepted.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.metrics import Metric
from ..operators.coreset import Coreset, _arrow, first_round, one_round, reduce_again, tagged_schema
from ..schema import ClusterSpec


def batch_coresets(stream: DataFrame, path: str, checkpoint: str, spec: ClusterSpec, metric: Metric, parts: int = 4):
    """One coreset per micro-batch, appended under its batch id; a repeated batch overwrites itself.

    `stream` has id, pt and w.  Returns the writer, to be triggered and started.
    """

    def each(batch: DataFrame, batch_id: int) -> None:
        pts = batch.withColumn("part", F.pmod(F.xxhash64("id"), F.lit(parts)).cast("int"))
        one_round(pts, spec, metric).rows.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint)


def window_coreset(events: DataFrame, spec: ClusterSpec, metric: Metric, time: str = "ts", window: str = "1 day", delay: str = "1 hour", slide: str | None = None, tasks: int = 1) -> DataFrame:
    """(start, id, pt, w) of every closed window: the points of a window are gathered by an aggregate, then covered.

    A window's points are dealt by id to `tasks` groups, each a part of its own; choose so many
    that a group fits a task.
    """
    kind = events.schema["pt"].dataType.simpleString()
    when = F.window(time, window, slide) if slide else F.window(time, window)
    rows = events.withWatermark(time, delay).groupBy(when.alias("win"), F.pmod(F.xxhash64("id"), F.lit(tasks)).alias("group")).agg(F.collect_list(F.struct("id", "pt", "w")).alias("rows"))
    schema = tagged_schema(events.schema["pt"].dataType, metric)
    arrow = _arrow(schema)

    def cover(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for start, points in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                t = pa.table({"id": pa.array([x["id"] for x in points], pa.int64()), "pt": pa.array([x["pt"] for x in points], arrow.field("pt").type), "w": pa.array([x["w"] for x in points], pa.int64())})
                core = first_round(t, 0, metric, spec, arrow, False)
                core = core.filter(pa.compute.equal(core.column("kind"), "core")).select(["id", "pt", "w"])
                yield from pa.table({"start": pa.array([start] * core.num_rows, b.schema.field(0).type), **{c: core.column(c) for c in core.column_names}}).to_batches()

    return rows.select(F.col("win.start").alias("start"), "rows").mapInArrow(cover, f"start timestamp, id long, pt {kind}, w long")


def by_window_parts(events: DataFrame, spec: ClusterSpec, metric: Metric, time: str = "ts") -> Coreset:
    """Day windows as the parts of one batch coreset."""
    day = F.unix_date(F.col(time).cast("date"))
    return one_round(events.withColumn("part", day), spec, metric)


def merged(windows: list[Coreset], spec: ClusterSpec, metric: Metric) -> Coreset:
    from ..operators.coreset import union

    return reduce_again(union(windows), spec, metric)


class MergeTree:
    """Bounded state of a stream: buckets of doubling size, reduced again when two of a size meet.

    There are at most `most_levels` levels; what reaches the top is merged into it again and again,
    so the state holds at most that many covers, however long the stream.  `moved` is the weighted
    distance (to the power p) by which points have been moved so far, each reduction added: for
    medians the cost of no set of centers differs between stream and summary by more than it.  For
    means its root per reduction adds up, which `moved` does too.
    """

    def __init__(self, spec: ClusterSpec, metric: Metric, bucket_rows: int = 512, levels: dict[int, list[tuple]] | None = None, moved: float = 0.0, most_levels: int = 12):
        self.spec, self.metric, self.bucket_rows, self.most_levels = spec, metric, bucket_rows, most_levels
        self.levels: dict[int, list[tuple]] = levels or {}
        self.moved = moved

    def _reduced(self, rows: list[tuple]) -> list[tuple]:
        from ..operators.cover import ball_cover
        from ..operators.seed import SEEDERS

        rows, spec = sorted(rows, key=lambda r: r[0]), self.spec
        w = np.array([r[2] for r in rows], np.int64)
        data = self.metric.load([r[1] for r in rows])
        _, d = SEEDERS[spec.seeder](self.metric, data, w, spec.m, spec.p, np.random.default_rng(spec.seed))
        cost = int((w * d).sum()) if self.metric.exact else float((w * d).sum())
        c = ball_cover(self.metric, data, d, cost, int(w.sum()), spec.eps, spec.beta, spec.p)
        step = float((w * c.d).sum())
        self.moved = self.moved + step if spec.p == 1 else (self.moved**0.5 + step**0.5) ** 2
        mass = np.bincount(c.tau, w, len(rows)).astype(np.int64)
        return [(rows[k][0], rows[k][1], int(mass[k])) for k in np.sort(c.pivots)]

    def add(self, rows: list[tuple]) -> None:
        """Takes rows of unique ids; a bucket of level 0 is reduced once it is full."""
        rows = self.levels.pop(0, []) + rows
        if len(rows) < self.bucket_rows:
            self.levels[0] = rows
            return
        rows, level = self._reduced(rows), 1
        while level in self.levels:
            rows = self._reduced(self.levels.pop(level) + rows)
            level = min(level + 1, self.most_levels)
        self.levels[level] = rows

    def rows(self) -> list[tuple]:
        return [r for level in sorted(self.levels) for r in self.levels[level]]


def keyed_summaries(events: DataFrame, key: str, spec: ClusterSpec, metric: Metric, bucket_rows: int = 512):
    """A merge tree per key as streaming state; every trigger sends the key's summary anew (id, w, level by level).

    `events` has the key, id, pt (array<bigint> or array<double>) and w.
    """
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def update(k: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        import json

        levels, moved = json.loads(state.get[0]) if state.exists else ({}, 0.0)
        tree = MergeTree(spec, metric, bucket_rows, {int(a): [tuple(r) for r in b] for a, b in levels.items()}, moved)
        for f in frames:
            if len(f):
                tree.add([(int(i), [x.item() if hasattr(x, "item") else x for x in p], int(w)) for i, p, w in zip(f["id"], f["pt"], f["w"], strict=True)])
        state.update((json.dumps((tree.levels, tree.moved)),))
        rows = tree.rows()
        yield pd.DataFrame({"key": [str(k[0])] * len(rows), "id": [r[0] for r in rows], "w": [r[2] for r in rows]})

    return events.groupBy(key).applyInPandasWithState(update, "key string, id long, w long", "levels string", "update", GroupStateTimeout.NoTimeout)
