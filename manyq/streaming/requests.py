"""Fork requests as a stream: each micro-batch of source vertices is one fork batch; edges as windows of a stream."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.streaming.query import StreamingQuery

from manyq.operators.blocks import BlockedGraph
from manyq.plans.engine import fork
from manyq.plans.kernels import Kernel
from manyq.plans.policy import Policy
from manyq.sources.tables import epoch


def serve_requests(requests: DataFrame, bg: BlockedGraph, kernel: Kernel, out: str, checkpoint: str, policy: Policy | None = None) -> StreamingQuery:
    """A stream of (src) against a graph at rest: results (batch_id, query_id, src, v, num) are appended to a Parquet folder, a batch at a time."""

    def batch(rows: DataFrame, batch_id: int) -> None:
        known = rows.select("src").distinct().join(bg.vparts.select(F.col("id").alias("src")), "src", "left_semi")
        sources = known.select((F.row_number().over(Window.orderBy("src")) - 1).cast("int").alias("query_id"), "src")
        if sources.isEmpty():
            return
        found = fork(bg, sources, kernel, policy).state.join(F.broadcast(sources), "query_id")
        # One folder per batch, written over on a retry: each batch counts once.
        found.select(F.lit(batch_id).alias("batch_id"), "query_id", "src", "v", "num").write.mode("overwrite").parquet(f"{out}/batch={batch_id}")

    return requests.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def edge_windows(events: DataFrame, size: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """(window, event_type, users, n) of a stream or table of events with ts: who is active together in a window; late events beyond the watermark are dropped."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", size), "event_type").agg(F.approx_count_distinct("user_id").alias("users"), F.count("*").alias("n"))


def admit(requests: DataFrame, late: str = "10 minutes") -> DataFrame:
    """A stream of (src, ts) with each source once within the watermark."""
    return requests.withWatermark("ts", late).dropDuplicatesWithinWatermark(["src"])


def co_activity(events: DataFrame, size: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """(src, dst, win, event_type): users with events of one type in one window become edges both ways, an edge for each pair of such events; a table, or a stream joined with itself.

    In a stream both sides carry the watermark, so the join's state is let go with it.
    """
    active = events.withWatermark("ts", late).select(F.window("ts", size).alias("win"), "ts", "event_type", "user_id")
    a = active.select("win", "event_type", F.col("user_id").alias("src"), "ts")
    b = active.select(F.col("win").alias("win_b"), F.col("event_type").alias("type_b"), F.col("user_id").alias("dst"), F.col("ts").alias("ts_b"))
    return a.join(b, (F.col("win") == F.col("win_b")) & (F.col("event_type") == F.col("type_b")) & (F.col("src") != F.col("dst"))).select("src", "dst", "win", "event_type")


def co_activity_counts(events: DataFrame, size: str = "1 hour", task_pairs: int = 2_000_000) -> DataFrame:
    """(src, dst, windows, n) of a table: in how many windows a pair of users is active together, and by how many pairs of events; co_activity's edges, grouped.

    The edges are many more than the events and never leave their task: events are dealt by src, each meets the users of its
    window and type, who are sent to all executors as one list, and a pair of users has all its edges in one task.
    """
    placed = events.where("user_id IS NOT NULL").select(F.window("ts", size).alias("w"), "event_type", F.col("user_id").alias("user"))
    active = placed.groupBy(F.col("w.start").alias("win"), "event_type", "user").agg(F.count("*").alias("c"))
    active = epoch(active, "active")
    total = active.groupBy("win", "event_type").count().agg(F.coalesce(F.sum(F.col("count").cast("double") * F.col("count")), F.lit(0.0))).first()[0]
    tasks = max(1, min(20_000, math.ceil(total / task_pairs)))
    others = active.groupBy("win", "event_type").agg(F.collect_list(F.struct("user", "c")).alias("others"))
    met = active.repartition(tasks, "user").join(F.broadcast(others), ["win", "event_type"]).select(F.col("user").alias("src"), "win", "c", F.explode("others").alias("o"))
    pairs = met.select("src", F.col("o.user").alias("dst"), "win", (F.col("c") * F.col("o.c")).alias("n")).where("src <> dst")
    return pairs.groupBy("src", "dst", "win").agg(F.sum("n").alias("n")).groupBy("src", "dst").agg(F.count("*").alias("windows"), F.sum("n").alias("n"))


def matched_requests(requests: DataFrame, events: DataFrame, within: str = "5 minutes", late: str = "10 minutes") -> DataFrame:
    """Two streams: requests (src, ts) with the events of their user in the time before, an interval join under watermarks."""
    r = requests.withWatermark("ts", late).select("src", F.col("ts").alias("asked"))
    e = events.withWatermark("ts", late).select("user_id", "event_id", F.col("ts").alias("seen"))
    near = (F.col("src") == F.col("user_id")) & (F.col("seen") <= F.col("asked")) & (F.col("seen") >= F.col("asked") - F.expr(f"INTERVAL {within}"))
    return r.join(e, near).select("src", "asked", "event_id")


class BufferProcessor(StatefulProcessor):
    """Keyed state as a part's buffer: the best operation of each (query, vertex) is kept, and passed on only where it improves."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.best = handle.getMapState("best", "query_id long, v long", "num double")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        out = []
        for frame in rows:
            for q, v, num in frame[["query_id", "v", "num"]].itertuples(index=False):
                at = (int(q), int(v))
                if not self.best.containsKey(at) or num < self.best.getValue(at)[0]:
                    self.best.updateValue(at, (float(num),))
                    out.append((int(key[0]), int(q), int(v), float(num)))
        yield pd.DataFrame(out, columns=["part_id", "query_id", "v", "num"])

    def close(self) -> None:
        pass


def buffered_stream(ops: DataFrame, processor: Callable[[], StatefulProcessor] = BufferProcessor) -> DataFrame:
    """A stream of operations (part_id, query_id, v, num) through keyed buffers."""
    return ops.groupBy("part_id").transformWithStateInPandas(statefulProcessor=processor(), outputStructType="part_id long, query_id long, v long, num double", outputMode="append", timeMode="none")
