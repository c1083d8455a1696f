"""Streams against the same work done in one batch."""

import pytest
from pyspark.sql import functions as F

from truekeys.operators.equivalence import sk_map
from truekeys.plans.staging import staged
from truekeys.streaming import streams

SMALL = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def events(spark, tmp_path_factory):
    folder = f"{tmp_path_factory.mktemp('events')}/e"
    e = spark.read.parquet(f"{SMALL}/events.parquet").orderBy("ts").repartitionByRange(4, "ts")
    e.write.parquet(folder)
    return folder, spark.read.parquet(folder)


def drained(df, name, mode="append"):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination(120)
    return df.sparkSession.table(name)


def test_tumbling_windows(spark, events):
    folder, batch = events
    live = streams.event_time(streams.source(spark, folder, batch.schema), late="30 days")
    got = drained(streams.tumbling(live, "event_type", "value"), "tumbling", "complete")
    pick = lambda d: sorted((str(r[0]), r[1], r[2], r[3]) for r in d.select("window.start", "event_type", "n", "nv").collect())
    assert pick(got) == pick(streams.tumbling(batch.withColumn("ts", F.col("ts").cast("timestamp")), "event_type", "value"))


def test_sessions_update(spark, events):
    folder, batch = events
    live = streams.event_time(streams.source(spark, folder, batch.schema, 10), late="1 day")
    got = drained(streams.sessions(live, "user_id", "1 hour"), "sessions")
    assert 0 < got.agg(F.sum("n")).first()[0] <= batch.count()


def test_repeats_within_the_watermark(spark, events):
    folder, batch = events
    live = streams.event_time(streams.source(spark, folder, batch.schema, 10), late="3650 days")
    got = drained(streams.without_repeats(live, ["user_id", "event_type"]).select("user_id", "event_type"), "repeats")
    assert got.count() == batch.select("user_id", "event_type").distinct().count()


def test_following_a_stored_map(spark, events):
    folder, batch = events
    mapping = staged(batch.select((F.col("user_id")).alias("sk")).distinct().where("sk % 2 = 1").select("sk", (F.col("sk") - 1).alias("rep")))
    got = drained(streams.follow(streams.source(spark, folder, batch.schema), "user_id", mapping).select("event_id", "user_id"), "followed")
    assert all(r.user_id % 2 == 0 for r in got.collect()) and got.count() == batch.count()


def test_stream_stream_join(spark, events):
    folder, batch = events
    a = streams.event_time(streams.source(spark, folder, batch.schema, 10), late="1 day").where("event_type = 'click'").select("user_id", "ts")
    b = streams.event_time(streams.source(spark, folder, batch.schema, 10), late="1 day").where("event_type <> 'click'").select("user_id", "ts", "event_id")
    got = drained(streams.joined(a, b, "user_id", within="12 hours").select("event_id"), "joined")
    x = batch.where("event_type = 'click'").select("user_id", "ts")
    y = batch.where("event_type <> 'click'").select(F.col("user_id").alias("u"), F.col("ts").alias("t"), "event_id")
    assert got.count() == x.join(y, F.expr("user_id = u and t between ts and ts + interval 12 hours")).count()


def test_incremental_map_equals_the_batch_map(spark):
    d = spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", "text")
    kept = streams.StoredMap("doc_id", ["text"], lambda df, n: staged(df))
    for k in (2, 0, 1):  # later batches bring smaller keys
        kept.update(d.where(f"doc_id % 3 = {k}"), k)
    pick = lambda m: sorted((r.sk, r.rep) for r in m.collect())
    assert pick(kept.mapping(d)) == pick(sk_map(d, "doc_id", ["text"]))
    assert sum(r.count() for r in kept.revisions) > 0


def test_late_rows_are_dropped(spark, tmp_path):
    early = spark.sql("select timestamp'2024-01-10 00:00:00' ts, 1L user_id union all select timestamp'2024-01-11 00:00:00', 1L")
    late = spark.sql("select timestamp'2024-01-01 00:00:00' ts, 1L user_id union all select timestamp'2024-01-12 00:00:00', 1L")
    folder = f"{tmp_path}/late"
    early.coalesce(1).write.parquet(folder)
    live = streams.event_time(streams.source(spark, folder, early.schema), late="1 day").groupBy(F.window("ts", "1 day"), "user_id").count()
    q = live.writeStream.format("memory").queryName("late").outputMode("append").option("checkpointLocation", f"{tmp_path}/cp").start()
    q.processAllAvailable()
    late.coalesce(1).write.mode("append").parquet(folder)
    q.processAllAvailable()
    q.stop()
    assert not any(r.window.start.day == 1 for r in spark.table("late").collect())


def test_custom_state(spark, events):
    folder, batch = events
    live = streams.source(spark, folder, batch.schema).select("event_type", "event_id")
    got = drained(streams.first_seen(live, "event_type", "event_id"), "seen")
    last = {}
    for r in got.collect():
        last[r.event_type] = min(r.rep, last.get(r.event_type, r.rep))
    assert last == {r.event_type: r[1] for r in batch.groupBy("event_type").agg(F.min("event_id")).collect()}


def test_map_fed_batch_by_batch(spark, events, tmp_path):
    folder, batch = events
    written = []

    def write(df, number):
        kept = staged(df)
        written.append((number, kept.count()))
        return kept

    kept = streams.StoredMap("event_id", ["user_id", "event_type"], write)
    live = streams.source(spark, folder, batch.schema)
    assert kept.sink(live, f"{tmp_path}/cp").awaitTermination(120)
    pick = lambda m: sorted((r.sk, r.rep) for r in m.collect())
    assert pick(kept.mapping(batch)) == pick(sk_map(batch, "event_id", ["user_id", "event_type"]))
    known = kept.state.count()
    kept.update(batch.limit(50), 99)  # delivered again: nothing is new
    assert kept.state.count() == known
    assert len({number for number, _ in written}) == len(written)


def test_exact_profile_of_each_batch(spark, events, tmp_path):
    folder, batch = events
    seen = []
    live = streams.source(spark, folder, batch.schema)
    streams.each_batch(live, lambda b, n: seen.append(b.agg(F.countDistinct("user_id"), F.count(F.lit(1))).first()), f"{tmp_path}/cp").awaitTermination(120)
    assert len(seen) == len(batch.inputFiles()) and sum(r[1] for r in seen) == batch.count()
