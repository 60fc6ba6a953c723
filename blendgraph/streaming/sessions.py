"""Sessions as walks, and pair counts that grow with a stream. Counts are additive, so a batch adds its own."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from ..config import WalkConfig
from ..cooccur import count_pairs, merge_counts


def _watermarked(events: DataFrame, watermark: str | None) -> DataFrame:
    """With a watermark, ts is read as a time of the session's zone: the engine has none on times without a zone."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark) if watermark else events


def session_walks(events: DataFrame, gap: str = "30 minutes", node: str = "node", watermark: str | None = None) -> DataFrame:
    """events(user_id, ts, event_id, node) -> walks(walk_id, user_id, start, path): a user's nodes in order, cut at gaps.

    Works on tables and, with a watermark, on streams: rows later than it are dropped by the engine and counted in its
    progress reports.
    """
    e = _watermarked(events, watermark)
    s = e.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.sort_array(F.collect_list(F.struct("ts", "event_id", node))).alias("l"))
    start = F.col("w.start")
    return s.select(F.xxhash64("user_id", start).alias("walk_id"), "user_id", start.alias("start"), F.expr(f"transform(l, x -> x.{node})").alias("path"))


def window_counts(events: DataFrame, width: str = "1 hour", slide: str | None = None, watermark: str | None = None) -> DataFrame:
    """Events and sum of value of each type in tumbling, or with slide sliding, windows."""
    e = _watermarked(events, watermark)
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    g = e.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return g.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "event_type", "n", "total")


class CountSink:
    """foreachBatch target that keeps counts in a folder, a part for each batch. A batch that comes again overwrites its own
    part, so a replay adds nothing; parts are summed when read, and compact() makes them one."""

    def __init__(self, path: str, cfg: WalkConfig = WalkConfig()):
        self.path, self.cfg = path, cfg

    def __call__(self, walks: DataFrame, batch: int) -> None:
        count_pairs(walks.select("walk_id", "path"), self.cfg).write.mode("overwrite").parquet(f"{self.path}/batch={batch}")

    def read(self, spark: SparkSession) -> DataFrame:
        try:
            return merge_counts(spark.read.parquet(self.path).select("node", "context", "cnt"))
        except AnalysisException:
            return spark.createDataFrame([], "node long, context long, cnt long")

    def compact(self, spark: SparkSession, target: str) -> None:
        self.read(spark).write.mode("overwrite").parquet(f"{target}/batch=0")


class WindowTail(StatefulProcessor):
    """Keeps a user's last nodes, window of them, and gives the pairs that each new node makes with them. State is bounded by
    users × window."""

    def __init__(self, window: int = 5):
        self.window = window

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.tail = handle.getValueState("tail", "nodes array<long>")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values) -> Iterator[pd.DataFrame]:  # noqa: N802
        found = self.tail.get() if self.tail.exists() else None
        last = list(found[0]) if found else []
        out = []
        batch = pd.concat(list(rows)).sort_values(["ts", "event_id"])
        for node in batch["node"]:
            out += [(int(a), int(node), len(last) - i) for i, a in enumerate(last)]
            last = [*last, int(node)][-self.window :]
        self.tail.update((last,))
        yield pd.DataFrame(out, columns=["node", "context", "gap"])

    def close(self) -> None:
        pass


def stream_pairs(events: DataFrame, window: int = 5) -> DataFrame:
    """(node, context, gap) of each user's events as they come, across batches."""
    grouped = events.select("user_id", "ts", "event_id", "node").groupBy("user_id")
    return grouped.transformWithStateInPandas(WindowTail(window), "node long, context long, gap int", outputMode="Append", timeMode="None")
