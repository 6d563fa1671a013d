"""Link streams: events to windowed links, late and repeated ones, and covers kept up to date."""

from __future__ import annotations

from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.percolation import percolate, update_cover
from ..session import written


def stream_events(spark: SparkSession, path: str, schema, late: str = "1 hour", files: int = 1) -> DataFrame:
    """Events of a folder of parquet files, `files` a batch, with event time as TIMESTAMP and a watermark."""
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def windowed_activity(events: DataFrame, size: str = "1 day", slide: str | None = None) -> DataFrame:
    """(start, event_type, n, value): counts a tumbling or sliding window; the same plan serves batch and stream."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """(user_id, start, n): runs of a user's events with gaps below `gap`."""
    w = F.session_window("ts", gap)
    return events.groupBy(w.alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def once(events: DataFrame, key: str = "event_id") -> DataFrame:
    """Each event once, within the watermark."""
    return events.dropDuplicatesWithinWatermark([key]) if events.isStreaming else events.dropDuplicates([key])


def follow_stream(a: DataFrame, b: DataFrame, seconds: int = 120) -> DataFrame:
    """Links of users of one event type within an interval, from two watermarked streams."""
    x, y = a.alias("x"), b.alias("y")
    near = F.expr(f"x.event_type = y.event_type AND y.ts >= x.ts AND y.ts < x.ts + INTERVAL {seconds} SECONDS AND x.user_id <> y.user_id")
    return x.join(y, near).select(F.col("x.user_id").alias("src"), F.col("y.user_id").alias("dst"), F.col("x.ts").alias("ts"))


def enriched(events: DataFrame, static: DataFrame, on: str) -> DataFrame:
    """Events with the columns of a static table; events without a match stay."""
    return events.join(static, on, "left")


def link_weights(links: DataFrame, half_life: float = 3600.0, idle: str = "1 day") -> DataFrame:
    """(src, dst, ts, weight): each link's weight after each of its batches, decaying by half in half_life seconds.

    links: (src, dst, ts), as a watermarked stream. A link's state is one number and its time, and goes once the
    watermark is `idle` past it. Rows of a batch may come in any order.
    """
    import pandas as pd

    gap = int(pd.Timedelta(idle).total_seconds() * 1000)

    def step(key, frames: Iterator, state: GroupState):
        if state.hasTimedOut:
            state.remove()
            return
        weight, last = state.get if state.exists else (0.0, None)
        for at in sorted(t for f in frames for t in f["ts"].astype("datetime64[us]").astype("int64").tolist()):
            # A row from before the last one counts by what is left of it, not the other way round.
            away = abs(at - last) / 1e6 if last is not None else 0.0
            left = 0.5 ** (away / half_life)
            weight, last = (weight * left + 1, at) if last is None or at >= last else (weight + left, last)
        state.update((weight, last))
        state.setTimeoutTimestamp(max(state.getCurrentWatermarkMs() + 1, last // 1000 + gap))
        yield pd.DataFrame({"src": [key[0]], "dst": [key[1]], "ts": [pd.Timestamp(last, unit="us")], "weight": [weight]})

    return links.select("src", "dst", "ts").groupBy("src", "dst").applyInPandasWithState(step, "src long, dst long, ts timestamp, weight double", "weight double, last long", "update", GroupStateTimeout.EventTimeTimeout)


def late_rows(query) -> int:
    """How many rows a finished or running query has dropped for being behind the watermark."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])


class CoverState:
    """A cover that link batches keep up to date; every version is a table in the shared folder.

    step is a foreachBatch function: rows (src, dst, op) with op add or remove.
    """

    def __init__(self, edges: DataFrame, k: int):
        self.k = k
        self.edges = written(edges.select("src", "dst"), "edges")
        self.cover = written(percolate(self.edges, k), "cover")

    def step(self, batch: DataFrame, epoch: int) -> None:
        pair = batch.where("src <> dst").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "op").distinct()
        add, drop = (pair.where(F.col("op") == op).select("src", "dst") for op in ("add", "remove"))
        edges, cover = update_cover(self.edges, self.cover, self.k, add, drop)
        self.edges, self.cover = written(edges, "edges"), written(cover, "cover")


def run_to_end(stream: DataFrame, each: Callable[[DataFrame, int], None], checkpoint: str, mode: str = "append"):
    """Runs a stream over all that is there, batch by batch, and returns the finished query."""
    q = stream.writeStream.outputMode(mode).foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return q
