"""Live streams: state equals batch, snapshots stay readable, specs can't change under the state."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from hotkeys.operators import owner_split as engine
from hotkeys.operators.exact import exact_counts
from hotkeys.sources import streams
from hotkeys.spec import SupportSpec
from hotkeys.streaming import live


@pytest.fixture
def files(spark, sf, tmp_path):
    events = streams.read(spark, sf, "events").select("event_id", "ts", "user_id", "event_type")
    path = str(tmp_path / "in")
    for k in range(3):
        events.filter(F.col("event_id") % 3 == k).coalesce(1).write.mode("append").parquet(path)
    return path, events


def live_stream(spark, path, events):
    given = streams.stream_files(spark, path, "*.parquet", events.schema)
    return given.select(F.concat_ws("/", "user_id", "event_type").alias("e"), F.lit(1).alias("w"))


def test_live_summary_equals_batch_and_old_snapshots_stay(spark, files, tmp_path):
    path, events = files
    spec = SupportSpec("0.01", owners=3, counters=500)
    checkpoint, out = str(tmp_path / "check"), str(tmp_path / "out")
    live.publish(live.maintain(live_stream(spark, path, events), spec), checkpoint, out).awaitTermination()
    now = live.snapshot(spark, out)
    got = {r["e"]: r["est"] for r in engine.slots(now).collect()}
    batch = events.select(F.concat_ws("/", "user_id", "event_type").alias("e"), F.lit(1).cast("long").alias("w"))
    assert got == {r["e"]: r["f"] for r in exact_counts(batch).collect()}
    first = live.snapshot(spark, out, 0).agg(F.sum("n_seen")).first()[0]
    assert 0 < first < 1000 and now.agg(F.sum("n_seen")).first()[0] == 1000
    assert live.live_length(spark, checkpoint).agg(F.sum("n_seen")).first()[0] == 1000
    frequent = {r["e"] for r in engine.query(now, "0.015").collect()}
    assert frequent == {r["e"] for r in exact_counts(batch).filter("f > 15").collect()}


def test_a_changed_spec_is_refused(spark, files, tmp_path):
    path, events = files
    checkpoint, out = str(tmp_path / "check"), str(tmp_path / "out")
    live.publish(live.maintain(live_stream(spark, path, events), SupportSpec("0.01", owners=3, counters=500)), checkpoint, out).awaitTermination()
    events.limit(10).coalesce(1).write.mode("append").parquet(path)
    with pytest.raises(Exception, match="the state was made with"):
        live.publish(live.maintain(live_stream(spark, path, events), SupportSpec("0.01", owners=3, counters=900)), checkpoint, out).awaitTermination()


def test_windows_in_a_stream_with_a_watermark(spark, files, tmp_path):
    path, events = files
    given = streams.stream_files(spark, path, "*.parquet", events.schema).select(F.col("event_type").alias("e"), F.lit(1).alias("w"), "ts")
    counts = live.windowed_counts(given, "ts", "7 days", watermark="60 days")
    query = counts.writeStream.format("memory").queryName("live_windows").outputMode("update").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "c")).start()
    query.awaitTermination()
    last = spark.table("live_windows").groupBy("window", "e").agg(F.max("w").alias("w")).agg(F.sum("w")).first()[0]
    assert last == 1000


def test_repeats_within_the_watermark_and_idle_owners(spark, files, tmp_path):
    path, events = files
    twice = events.select("event_id", "user_id", "event_type", "ts").unionAll(events.select("event_id", "user_id", "event_type", "ts"))
    folder = str(tmp_path / "twice")
    twice.coalesce(1).write.parquet(folder)
    given = streams.stream_files(spark, folder, "*.parquet", twice.schema)
    once = live.deduplicated(given, ["event_id"], "ts", "9999 days").select(F.col("event_type").alias("e"), F.lit(1).cast("long").alias("w"))
    out = str(tmp_path / "out")
    live.publish(live.maintain(once, SupportSpec("0.01", owners=2, counters=63), ttl_ms=3_600_000), str(tmp_path / "check"), out).awaitTermination()
    assert live.snapshot(spark, out).agg(F.sum("n_seen")).first()[0] == events.select("event_id").distinct().count()
