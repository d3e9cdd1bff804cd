"""Streams against batch results."""

from pyspark.sql import functions as F

from veilwalk.plans.lineage import Store
from veilwalk.sources.tables import load
from veilwalk.streaming import edges as streams


def batches(spark, sf, tmp_path, parts=3):
    events = load(spark, sf, "events")
    path = f"file://{tmp_path}/events"
    events.repartitionByRange(parts, "ts").write.parquet(path)
    return events, streams.event_stream(spark, path, events.schema)


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_bin_counts_equal_batch(spark, sf):
    got = streams.bin_counts_of_events(spark, sf)
    events = load(spark, sf, "events")
    want = events.select(F.col("user_id").alias("v"), (F.pmod(F.pmod("event_id", F.lit(97)), F.lit(4)) + 1).cast("int").alias("bin")).groupBy("v", "bin").count()
    assert rows(got.select("v", "bin", "n")) == rows(want.select("v", "bin", "count"))


def test_windows_and_sessions_equal_batch(spark, sf, tmp_path):
    events, stream = batches(spark, sf, tmp_path, 1)
    got = streams.drain(streams.windowed_activity(stream), "activity", "complete", Store(spark, "s"))
    want = events.groupBy(F.window(F.col("ts").cast("timestamp"), "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"))
    assert sum(r["n"] for r in got.collect()) == events.count() and got.count() == want.count()
    sessions = streams.drain(streams.sessions(stream), "sessions", "complete", Store(spark, "s"))
    assert sum(r["n"] for r in sessions.collect()) == events.count()


def test_succession_edges_are_symmetric(spark, sf, tmp_path):
    _, stream = batches(spark, sf, tmp_path)
    got = streams.drain(streams.succession_edges(stream), "succession", "append", Store(spark, "s"))
    found = {(r["w"], r["v"], r["u"]) for r in got.collect()}
    assert all((w, u, v) in found for w, v, u in found)


def test_distinct_edges_and_budgets(spark, sf, tmp_path):
    events, stream = batches(spark, sf, tmp_path)
    pairs = stream.select("ts", F.col("user_id").alias("v"), F.pmod("event_id", F.lit(3)).alias("u"))
    once = streams.drain(streams.distinct_edges(pairs, late="3000 days"), "once", "append", Store(spark, "s"))
    want = events.select(F.least("user_id", F.pmod("event_id", F.lit(3))), F.greatest("user_id", F.pmod("event_id", F.lit(3)))).distinct()
    assert once.count() == want.count()
    spent = streams.drain(streams.budgets(stream.select(F.col("user_id").alias("v")), 0.5, 20.0), "spent", "update", Store(spark, "s"))
    last = {r["v"]: r["n"] for r in spent.groupBy("v").agg(F.max("emissions").alias("n")).collect()}
    assert last == {r["user_id"]: r["count"] for r in events.groupBy("user_id").count().collect()}


def test_interval_join_and_merged_counts(spark, sf, tmp_path):
    events, stream = batches(spark, sf, tmp_path, 1)
    got = streams.drain(streams.purchases_after_clicks(stream, "1 day", "3000 days"), "joined", "append", Store(spark, "s"))
    e = events.withColumn("ts", F.col("ts").cast("timestamp"))
    c = e.where("event_type = 'click'").select(F.col("user_id").alias("cu"), F.col("ts").alias("ct"), F.col("event_id").alias("click_id"))
    want = e.where("event_type = 'purchase'").join(c, (F.col("cu") == F.col("user_id")) & (F.col("ct") <= F.col("ts")) & (F.col("ct") >= F.col("ts") - F.expr("interval 1 day")))
    assert got.count() == want.count()
    write = streams.merge_counts(f"file://{tmp_path}/counts")
    batch = spark.createDataFrame([(1, 2, 3)], "a long, b long, n long")
    for _ in range(2):
        write(batch, 0)
    write(batch, 1)
    assert rows(streams.merged_counts(spark, f"file://{tmp_path}/counts")) == [(1, 2, 6)]
