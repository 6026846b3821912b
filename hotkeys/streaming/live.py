"""The engine on live streams: owners as keyed state, queries as reads of committed snapshots.

Each micro-batch combines its arrivals, hands them to the owners' state, and is committed with
nothing pending, so a reader sees exactly the first N arrivals of some N. Readers never block the writer.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window as W
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from hotkeys.kernels.minmax import MinMaxSummary
from hotkeys.operators.owner_split import frequent_by, handover
from hotkeys.spec import SupportSpec

STATUS = "owner int, m int, n_seen long, f_min long, slots array<struct<e:string,est:bigint,over:bigint>>"


class OwnerProcessor(StatefulProcessor):
    """Keeps one owner's summary; each batch's combined pairs go in, the owner's status comes out.

    With ttl_ms an owner that gets nothing for so long starts anew.
    """

    def __init__(self, m: int, stamp: str, ttl_ms: int | None = None):
        self.m, self.stamp, self.ttl_ms = m, stamp, ttl_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        schema = T.StructType([T.StructField("stamp", T.StringType()), T.StructField("summary", T.BinaryType()), T.StructField("n_seen", T.LongType())])
        self.state = handle.getValueState("summary", schema, self.ttl_ms)

    def handleInputRows(self, key: Any, rows: Iterator[pd.DataFrame], timerValues: Any) -> Iterator[pd.DataFrame]:
        if self.state.exists():
            stamp, packed, _ = self.state.get()
            if stamp != self.stamp:
                raise ValueError(f"the state was made with {stamp}, not {self.stamp}")
            own = MinMaxSummary.from_rows(self.m, pickle.loads(packed)[0])
            own.n = pickle.loads(packed)[1]
        else:
            own = MinMaxSummary(self.m)
        for part in rows:
            sums = part.groupby("e", sort=False)["w"].sum()
            own.update_batch(sums.index.tolist(), sums.tolist())
        held = own.to_rows()
        self.state.update((self.stamp, pickle.dumps((held, own.n)), own.n))
        yield pd.DataFrame({"owner": [int(key[0])], "m": [own.m], "n_seen": [own.n], "f_min": [own.f_min], "slots": [[{"e": e, "est": c, "over": o} for e, c, o in held]]})

    def close(self) -> None:
        pass


def with_event_time(stream: DataFrame, column: str) -> DataFrame:
    """Event time as a timestamp: one without a zone can't carry a watermark."""
    return stream.withColumn(column, F.col(column).cast("timestamp"))


def deduplicated(stream: DataFrame, columns: list[str], time: str, watermark: str) -> DataFrame:
    """A live stream without arrivals that repeat the columns of one within the watermark."""
    return with_event_time(stream, time).withWatermark(time, watermark).dropDuplicatesWithinWatermark(columns)


def maintain(stream: DataFrame, spec: SupportSpec, ttl_ms: int | None = None) -> DataFrame:
    """Streaming (owner, m, n_seen, f_min, slots): the status of every owner that a batch reached.

    stream: (e, w), elements as text. The spec is kept in the state; another one is refused. ttl_ms: how long an idle owner's state lasts.
    """
    stamp = f"m={spec.per_owner()} owners={spec.owners} seed={spec.seed}"
    given = stream.select(F.col("e").cast("string").alias("e"), F.col("w").cast("long").alias("w")).filter("e IS NOT NULL")
    pairs = handover(given, spec).select("owner", "e", "w")  # combined in bounded buffers before they are dealt to owners
    return pairs.groupBy("owner").transformWithStateInPandas(OwnerProcessor(spec.per_owner(), stamp, ttl_ms), outputStructType=STATUS, outputMode="Update", timeMode="ProcessingTime" if ttl_ms else "None")


def publish(status: DataFrame, checkpoint: str, path: str, **trigger):
    """Write each batch's owner statuses as parquet rows stamped with the batch; returns the query."""

    def put(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number).cast("long")).write.mode("append").parquet(path)

    return status.writeStream.outputMode("update").option("checkpointLocation", checkpoint).foreachBatch(put).trigger(**(trigger or {"availableNow": True})).start()


def snapshot(spark: SparkSession, path: str, batch: int | None = None) -> DataFrame:
    """Owner summaries as of a published batch: each owner's latest status up to it."""
    rows = spark.read.parquet(path)
    if batch is not None:
        rows = rows.filter(F.col("batch") <= batch)
    latest = rows.groupBy("owner").agg(F.max_by(F.struct("m", "n_seen", "f_min", "slots"), "batch").alias("s"))
    return latest.select("owner", "s.*", F.coalesce(F.array_max(F.transform("s.slots", lambda x: x["est"])), F.lit(0)).alias("f_max"))


def live_length(spark: SparkSession, checkpoint: str, batch: int | None = None) -> DataFrame:
    """(owner, n_seen) read from the committed state store itself, at a batch or the latest."""
    reader = spark.read.format("statestore").option("stateVarName", "summary")
    if batch is not None:
        reader = reader.option("batchId", batch)
    rows = reader.load(checkpoint)
    return rows.select(F.col("key.owner").alias("owner"), F.col("value.n_seen").alias("n_seen"))


def windowed_counts(stream: DataFrame, time: str, window: str, slide: str | None = None, watermark: str | None = None) -> DataFrame:
    """(window, e, w): arrivals combined per event-time window; also for streams."""
    timed = with_event_time(stream, time)
    if watermark:
        timed = timed.withWatermark(time, watermark)
    span = F.window(time, window, slide) if slide else F.window(time, window)
    return timed.groupBy(span.alias("window"), "e").agg(F.sum("w").alias("w"))


def frequent_windowed(stream: DataFrame, time: str, phi, window: str, slide: str | None = None, m: int = 1_000, owners: int = 8) -> DataFrame:
    """(start, e, est, lower) of the elements frequent in each window, owners of m counters each for every window."""
    timed = with_event_time(stream, time)
    span = F.window(time, window, slide) if slide else F.window(time, window)
    return frequent_by(timed.select(span.alias("span"), "e", "w").select(F.col("span.start").alias("start"), "e", "w"), ["start"], phi, m, owners=owners)


def frequent_sessions(stream: DataFrame, time: str, by: str, gap: str, phi, m: int = 1_000, owners: int = 1) -> DataFrame:
    """(by, start, e, est, lower) of the elements frequent within each session of a key; sessions end after a gap.

    A key's arrivals are walked in order of time, spilling if they are many; each session then has summaries as a group has.
    """
    timed = with_event_time(stream, time)
    order = W.partitionBy(by).orderBy(time)
    fresh = F.lag(time).over(order) + F.expr(f"interval {gap}") <= F.col(time)
    marked = timed.withColumn("fresh", F.when(F.coalesce(fresh, F.lit(True)), F.col(time)))
    started = marked.withColumn("start", F.last("fresh", ignorenulls=True).over(order.rowsBetween(W.unboundedPreceding, 0)))
    return frequent_by(started.select(by, "start", "e", "w"), [by, "start"], phi, m, owners=owners)
