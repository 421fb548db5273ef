"""Mobile objects as a stream: late data, windows, latest positions as state, and the join over each micro-batch."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle, StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from netjoin.operators.network import Network
from netjoin.operators.objects import closest_objects, latest_positions

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, folder: str, *, files_per_batch: int = 1) -> DataFrame:
    """Events of a Parquet folder as a stream; the time becomes a timestamp so that it can carry a watermark."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_batch).parquet(folder)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def rate_events(spark: SparkSession, rows_per_second: int, *, users: int = 1000) -> DataFrame:
    """Generated events at a rate, for load tests: every user moves in turn."""
    r = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    return r.select(F.col("value").alias("event_id"), F.col("timestamp").alias("ts"), F.pmod("value", F.lit(users)).alias("user_id"), F.when(F.col("value") % 2 == 0, "view").otherwise("purchase").alias("event_type"))


def late_rows(query: StreamingQuery) -> int:
    """Rows that a finished query's state operators dropped as later than the watermark."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])


def positions_of(events: DataFrame, edges: DataFrame, n_vertices: int) -> DataFrame:
    """event_id, ts, oid, kind, eid, off: views (r) and purchases (s) of a user as objects on the first edge of a vertex. Batch or stream."""
    first = edges.groupBy("src").agg(F.min(F.struct("dst", "eid", "w")).alias("e")).select(F.col("src").alias("at"), "e.eid", "e.w")
    kept = events.where("event_type IN ('view', 'purchase')").withColumn("kind", F.when(F.col("event_type") == "view", "r").otherwise("s"))
    spot = kept.withColumn("at", F.pmod(F.col("event_id") * 37 + F.col("user_id"), F.lit(n_vertices))).withColumn("oid", F.col("user_id") * 2 + F.when(F.col("kind") == "s", 1).otherwise(0))
    return spot.join(first, "at").select("event_id", "ts", "oid", "kind", "eid", F.pmod(F.col("event_id") * 13, F.col("w") + 1).alias("off"))


def deduplicated(events: DataFrame, delay: str = "10 minutes") -> DataFrame:
    """Events once each within the watermark; later ones are dropped and counted by Spark."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def windowed_counts(events: DataFrame, *, length: str = "1 hour", slide: str | None = None, delay: str = "10 minutes") -> DataFrame:
    """Events for each type and window, tumbling or sliding."""
    return events.withWatermark("ts", delay).groupBy(F.window("ts", length, slide), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def session_counts(events: DataFrame, *, gap: str = "30 minutes", delay: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", delay).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("session_window.start").alias("start"), "user_id", "n")


def tracked_positions(positions: DataFrame, *, delay: str = "10 minutes", silent: str = "2 hours") -> DataFrame:
    """Latest position of each object as keyed state; one row whenever it changes. State of silent objects expires by event time."""
    limit_ms = int(pd.Timedelta(silent).total_seconds() * 1000)

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        last = state.get if state.exists else None
        for rows in batches:
            for r in rows.itertuples(index=False):
                now = (int(r.ts.value // 1000), int(r.event_id), int(r.eid), int(r.off))
                last = max(last, now) if last else now
        if last and (not state.exists or tuple(state.get) != last):
            state.update(last)
            state.setTimeoutTimestamp(max(last[0] // 1000 + limit_ms, state.getCurrentWatermarkMs() + 1))
            yield pd.DataFrame({"oid": [key[0]], "micros": [last[0]], "eid": [last[2]], "off": [last[3]]})

    return positions.withWatermark("ts", delay).groupBy("oid").applyInPandasWithState(update, "oid long, micros long, eid long, off long", "micros long, event_id long, eid long, off long", "update", GroupStateTimeout.EventTimeTimeout)


class LatestPosition(StatefulProcessor):
    """Value state of each object: its latest (micros, event_id, eid, off)."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.last = handle.getValueState("last", "micros long, event_id long, eid long, off long")

    def handleInputRows(self, key: tuple, rows: Iterator[pd.DataFrame], timerValues: object) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        before = tuple(self.last.get()) if self.last.exists() else None
        now = before
        for batch in rows:
            for r in batch.itertuples(index=False):
                seen = (int(r.ts.value // 1000), int(r.event_id), int(r.eid), int(r.off))
                now = max(now, seen) if now else seen
        if now and now != before:
            self.last.update(now)
            yield pd.DataFrame({"oid": [key[0]], "micros": [now[0]], "eid": [now[2]], "off": [now[3]]})

    def close(self) -> None:
        pass


def positions_by_processor(positions: DataFrame) -> DataFrame:
    """The rows of ``tracked_positions`` through a stateful processor; needs the RocksDB state store (spark.sql.streaming.stateStore.providerClass)."""
    return positions.groupBy("oid").transformWithStateInPandas(statefulProcessor=LatestPosition(), outputStructType="oid long, micros long, eid long, off long", outputMode="Update", timeMode="None")


def meetings_stream(left: DataFrame, right: DataFrame, minutes: int) -> DataFrame:
    """Stream-stream join of two event streams of one type key within an interval."""
    a = left.withWatermark("ts", "10 minutes").select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("ts").alias("ta"))
    b = right.withWatermark("ts", "10 minutes").select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("ts").alias("tb"))
    return a.join(b, F.expr(f"ua = ub AND tb BETWEEN ta - INTERVAL {int(minutes)} MINUTES AND ta + INTERVAL {int(minutes)} MINUTES")).select("a", "b")


def stream_closest_objects(events: DataFrame, net: Network, n_vertices: int, k: int, theta: int, store: str, publish: Callable[[DataFrame, int], None], *, checkpoint: str, delay: str = "10 minutes") -> StreamingQuery:
    """Keep the latest positions under ``store`` and hand the k closest object pairs after each micro-batch to ``publish(pairs, epoch)``.

    The iteration runs in foreachBatch, where plans may loop. State is one Parquet version for each epoch: replaying an epoch rewrites it.
    """
    spark = net.vertices.sparkSession

    def batch(rows: DataFrame, epoch: int) -> None:
        new = positions_of(rows, net.edges, n_vertices)
        if epoch:
            new = new.unionByName(spark.read.parquet(f"{store}/epoch={epoch - 1}"))
        last = new.groupBy("oid").agg(F.max(F.struct("ts", "event_id", "kind", "eid", "off")).alias("m")).select("m.event_id", "m.ts", "oid", "m.kind", "m.eid", "m.off")
        last.write.mode("overwrite").parquet(f"{store}/epoch={epoch}")
        now = latest_positions(spark.read.parquet(f"{store}/epoch={epoch}"))
        publish(closest_objects(net, now.where("kind = 'r'"), now.where("kind = 's'"), k, theta), epoch)

    return deduplicated(events, delay).writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
