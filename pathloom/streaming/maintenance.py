"""Streams of edges: views maintained by micro-batch, chains from keyed state, windows and repeats under watermarks."""

from __future__ import annotations

import threading
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.engine import GraphUpdate, ViewStore


def maintain_stream(feed: DataFrame, store: ViewStore, checkpoint: str, **trigger):
    """Apply each micro-batch of a change feed (op, label, src, dst) as one update; replayed batches count once.

    A stream is known by the id that its checkpoint keeps, so other streams into the same store are not its replays.
    """
    started, ids = threading.Event(), []

    def apply(batch: DataFrame, number: int) -> None:
        started.wait()
        store.apply(GraphUpdate.from_feed(batch), ids[0], number)

    query = feed.writeStream.foreachBatch(apply).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()
    ids.append(query.id)
    started.set()
    return query


@contextmanager
def rocksdb_state(spark: SparkSession):
    """Streams started in the block keep their state in RocksDB, which state of arbitrary keys needs."""
    key = "spark.sql.streaming.stateStore.providerClass"
    own = spark.conf.get(key, None)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        yield
    finally:
        if own is None:
            spark.conf.unset(key)
        else:
            spark.conf.set(key, own)


def timed(events: DataFrame) -> DataFrame:
    """Event time as a timestamp with zone, which watermarks need; the session's zone should be UTC."""
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def distinct_edges(edges: DataFrame, late: str = "1 hour") -> DataFrame:
    """A stream's edges (ts, label, src, dst) once each within the watermark: sets, not bags."""
    return edges.withWatermark("ts", late).dropDuplicatesWithinWatermark(["label", "src", "dst"])


def tumbling(events: DataFrame, width: str = "1 day", late: str | None = None) -> DataFrame:
    rows = events.withWatermark("ts", late) if late else events
    return rows.groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, width: str = "2 days", step: str = "1 day", late: str | None = None) -> DataFrame:
    rows = events.withWatermark("ts", late) if late else events
    return rows.groupBy(F.window("ts", width, step), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "6 hours", late: str | None = None) -> DataFrame:
    rows = events.withWatermark("ts", late) if late else events
    return rows.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select(F.col("session_window.start").alias("start"), "user_id", "n")


def chain_stream(events: DataFrame) -> DataFrame:
    """(label, src, dst) links from each event of a type and community to the next, by state of one event a key.

    Events are linked in order of arrival between batches and of (ts, event_id) within one; self-links are left out.
    """
    from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

    class Chain(StatefulProcessor):
        def init(self, handle: StatefulProcessorHandle) -> None:
            self.last = handle.getValueState("last", "user long, event long")

        def handleInputRows(self, key, rows: Iterator, timerValues) -> Iterator:
            import pandas as pd

            own = pd.concat(list(rows)).sort_values(["ts", "event_id"])
            before = self.last.get() if self.last.exists() else None
            users, ids = own["user_id"].tolist(), own["event_id"].tolist()
            before_user, before_id = before if before is not None else (None, None)
            out = []
            for u, e in zip(users, ids, strict=True):
                if before_user is not None and before_id % 20 == 0 and before_user != u:
                    out.append((f"relay_{key[0]}", 11 * 10**12 + before_user, 11 * 10**12 + u))
                before_user, before_id = u, e
            self.last.update((int(before_user), int(before_id)))
            yield pd.DataFrame(out, columns=["label", "src", "dst"]).astype({"label": "object", "src": "int64", "dst": "int64"})

        def close(self) -> None:
            pass

    keyed = events.withColumn("community", F.floor(F.col("user_id") / 25).cast("long"))
    return keyed.groupBy("event_type", "community").transformWithStateInPandas(statefulProcessor=Chain(), outputStructType="label string, src long, dst long", outputMode="append", timeMode="none")
