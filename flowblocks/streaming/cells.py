"""Cells kept current from a stream of events or trips."""
from __future__ import annotations

import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..durable import durable, shared_folder


def _windowed(trips: DataFrame, late: str, *window: str) -> DataFrame:
    w = F.window("ts", *window)
    return trips.withWatermark("ts", late).groupBy(w, "o", "d").agg(F.sum("pax").alias("flow")).select(F.col("window.start").alias("start"), "o", "d", "flow")


def tumbling(trips: DataFrame, width: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Flow by origin, destination and half hour; rows later than the watermark are dropped and counted by Spark."""
    return _windowed(trips, late, width)


def sliding(trips: DataFrame, width: str = "2 hours", step: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    return _windowed(trips, late, width, step)


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """First and last region of a user's session: one trip."""
    s = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id")
    return s.agg(F.min_by("k", F.struct("ts", "event_id")).alias("o"), F.max_by("k", F.struct("ts", "event_id")).alias("d"), F.count("*").alias("n")).select(F.col("session_window.start").alias("start"), "user_id", "o", "d", "n")


def hops(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Consecutive events of a user as trips (o, d, ts, pax), on a stream: (user_id, event_id, ts, k, pax).

    A user's events wait in the state until the watermark has passed them, so they pair in order of (ts, event_id) however
    they arrive; the last one released stays, as the origin of the next trip."""
    import pandas as pd

    def pair(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if key[0] is None:  # a row that only moves the watermark; a filter would go below it
            return
        held = [tuple(x) for x in zip(*state.get)] if state.exists else []
        for f in frames:
            held += list(zip(f.us.tolist(), f.event_id.tolist(), f.k.tolist(), f.pax.tolist(), [False] * len(f)))
        mark = state.getCurrentWatermarkMs() * 1000
        held.sort(key=lambda x: x[:2])
        done = [x for x in held if x[4] or x[0] < mark]
        left = [(*x[:4], True) for x in done[-1:]] + [x for x in held if not x[4] and x[0] >= mark]
        waiting = [x[0] for x in left if not x[4]]
        if left:
            state.update(tuple(list(c) for c in zip(*left)))
        if waiting:
            state.setTimeoutTimestamp(max(min(waiting) // 1000 + 1, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame([(a[2], b[2], a[0], a[3]) for a, b in zip(done, done[1:])], columns=["o", "d", "us", "pax"])

    held = "us array<bigint>, event_id array<bigint>, k array<int>, pax array<bigint>, released array<boolean>"
    rows = events.withWatermark("ts", late).select("user_id", "event_id", "ts", F.unix_micros("ts").alias("us"), "k", "pax")
    out = rows.groupBy("user_id").applyInPandasWithState(pair, "o int, d int, us bigint, pax bigint", held, "append", "EventTimeTimeout")
    return out.select("o", "d", F.timestamp_micros("us").alias("ts"), "pax")


def replay(rows: DataFrame, files: int, per_trigger: int = 1) -> DataFrame:
    """rows (with ts, a timestamp) as a stream of files in order of time, and a last one, a day after all of them, whose only
    row has nothing but ts: it moves the watermark past every row."""
    root, spark = f"{shared_folder(rows.sparkSession)}/replay-{uuid.uuid4().hex}", rows.sparkSession
    ends = rows.agg(F.unix_micros(F.min("ts")).alias("a"), F.unix_micros(F.max("ts")).alias("b")).first()
    if ends.a is not None:
        part = F.least(F.floor((F.unix_micros("ts") - ends.a) * files / (ends.b - ends.a + 1)), F.lit(files - 1))
        for i in range(files):
            rows.where(part == i).coalesce(1).write.mode("append").parquet(root)
        last = [F.timestamp_micros(F.lit(ends.b + 86_400_000_000)).alias(c) if c == "ts" else F.lit(None).cast(rows.schema[c].dataType).alias(c) for c in rows.columns]
        spark.range(1).select(*last).coalesce(1).write.mode("append").parquet(root)
    else:
        rows.write.parquet(root)
    return spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", per_trigger).parquet(root)


def merged(cells: DataFrame | None, delta: DataFrame) -> DataFrame:
    """The cell table after a delta of trips (o, d, t, pax): one full merge on the key."""
    new = delta.groupBy("o", "d", "t").agg(F.sum("pax").alias("flow"))
    if cells is None:
        return new.where("flow > 0")
    return cells.unionByName(new).groupBy("o", "d", "t").agg(F.sum("flow").alias("flow")).where("flow > 0")


class CellStore:
    """Cells kept by batches of a stream; each batch writes a new version and a repeated batch is not added again."""

    def __init__(self, spark: SparkSession):
        self.spark, self.now, self.last = spark, None, -1

    def add(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id > self.last:
            self.now, self.last = durable(merged(self.now, batch)), batch_id


def run(stream: DataFrame, mode: str = "append") -> tuple[DataFrame, dict]:
    """Run a stream over what is there; its table and the sums of its progress counters."""
    root = f"{shared_folder(stream.sparkSession)}/stream-{uuid.uuid4().hex}"
    q = stream.writeStream.format("parquet").outputMode(mode).option("checkpointLocation", f"{root}/log").trigger(availableNow=True).start(f"{root}/rows")
    q.awaitTermination()
    late = sum(op.get("numRowsDroppedByWatermark", 0) for p in q.recentProgress for op in (dict(p)["stateOperators"] if isinstance(p, dict) else []))
    return stream.sparkSession.read.schema(stream.schema).parquet(f"{root}/rows"), {"late": late, "batches": len(q.recentProgress)}
