"""Edges from event streams: counts, sessions, consecutive events, dedupe, re-ranking."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from levelrank.operators.model import build_graph
from levelrank.operators.rank import levelwise_rank, update_rank

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, folder: str, late: str = "1 hour") -> DataFrame:
    """Events of a folder of Parquet files, with an event-time watermark; later rows drop out of stateful operators."""
    return spark.readStream.schema(EVENTS).parquet(folder).withWatermark("ts", late)


def type_edges(events: DataFrame) -> DataFrame:
    """user -> key of the event's properties: an edge per event."""
    return events.select("ts", F.col("user_id").alias("src"), (F.lit(1_000_000_000) + F.get_json_object("props", "$.k").cast("long")).alias("dst")).where("src is not null and dst is not null")


def windowed_counts(edges: DataFrame, size: str = "1 day", slide: str | None = None) -> DataFrame:
    """(start, src, dst, n) by tumbling or sliding window; batch or stream."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return edges.groupBy(w.alias("w"), "src", "dst").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "src", "dst", "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """(user_id, start, end, n) by session window; batch or stream."""
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def deduplicated(edges: DataFrame) -> DataFrame:
    """One row per edge within the watermark."""
    return edges.dropDuplicatesWithinWatermark(["src", "dst"])


def weighted(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """Stream-static join with start weights (id, weight)."""
    return edges.join(vertices.withColumnRenamed("id", "src"), "src", "left").fillna(0.0, ["weight"])


def consecutive(events: DataFrame, expire: str = "1 day") -> DataFrame:
    """(user_id, src, dst): an edge between a user's consecutive events' keys; the last key is state that expires."""
    keyed = events.select("ts", "user_id", "event_id", F.get_json_object("props", "$.k").cast("long").alias("k")).where("k is not null and user_id is not null")
    wait = int(pd.Timedelta(expire).total_seconds() * 1000)

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        last, out, newest = (state.get[0] if state.exists else None), [], None
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        for ts, k in zip(rows["ts"], rows["k"]):
            if last is not None:
                out.append((key[0], last, int(k)))
            last, newest = int(k), ts
        state.update((last,))
        state.setTimeoutTimestamp(max(int(newest.timestamp() * 1000), state.getCurrentWatermarkMs()) + wait)
        yield pd.DataFrame(out, columns=["user_id", "src", "dst"])

    return keyed.groupBy("user_id").applyInPandasWithState(step, "user_id long, src long, dst long", "last long", "append", GroupStateTimeout.EventTimeTimeout)


class Reranker:
    """``foreachBatch`` sink: adds a batch's edges to the written edge table and ranks what they reach again."""

    def __init__(self, spark: SparkSession, folder: str, c: float = 0.85):
        self.spark, self.folder, self.c, self.graph, self.ranks, self.done = spark, folder, c, None, None, -1

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id <= self.done:  # a batch that is sent again is not added twice
            return
        batch.select("src", "dst").write.mode("overwrite").parquet(f"{self.folder}/edges/batch={batch_id}")
        edges = self.spark.read.schema("src long, dst long").parquet(*[f"{self.folder}/edges/batch={i}" for i in range(batch_id + 1)])
        new = build_graph(edges)
        ranks = levelwise_rank(new, self.c, 1e-12) if self.graph is None else update_rank(self.graph, self.ranks, new, self.c)
        path = f"{self.folder}/ranks/{batch_id}"
        ranks.write.mode("overwrite").parquet(path)
        self.graph, self.ranks, self.done = new, self.spark.read.parquet(path), batch_id
