"""Incremental forms: succession edges, windowed activity, bin counts, deduplication, joins and budgets over streams."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from veilwalk.plans.lineage import Store
from veilwalk.sources.tables import load


def event_stream(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    """Events read from Parquet files as they come; times become instants."""
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def windowed_activity(events: DataFrame, late: str = "2 hours", size: str = "1 day", slide: str | None = None) -> DataFrame:
    """Events by type in tumbling or sliding windows; events later than the watermark are dropped and counted by Spark."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.withWatermark("ts", late).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"))


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    return events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))


def succession_edges(events: DataFrame, size: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """(w, v, u): users that follow one another within a tumbling window, both directions, each once."""
    held = events.withWatermark("ts", late).groupBy(F.window("ts", size).alias("w")).agg(F.sort_array(F.collect_list(F.struct("ts", "event_id", "user_id"))).alias("s"))
    pairs = F.transform(F.sequence(F.lit(1), F.size("s") - 1), lambda i: F.struct(F.element_at("s", i)["user_id"].alias("v"), F.element_at("s", i + 1)["user_id"].alias("u")))
    one = held.where(F.size("s") > 1).select("w", F.explode(F.array_distinct(pairs)).alias("p")).where("p.v <> p.u")
    both = F.array(F.struct("p.v", "p.u"), F.struct(F.col("p.u").alias("v"), F.col("p.v").alias("u")))
    return one.select("w", F.explode(both).alias("e")).select("w", "e.v", "e.u")


def distinct_edges(edges: DataFrame, time: str = "ts", late: str = "2 hours") -> DataFrame:
    """Undirected edges, each once within the watermark."""
    keyed = edges.withColumn("a", F.least("v", "u")).withColumn("b", F.greatest("v", "u"))
    return keyed.withWatermark(time, late).dropDuplicatesWithinWatermark(["a", "b"])


def purchases_after_clicks(events: DataFrame, within: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Interval join of a stream with itself: purchases and the user's clicks of the hour before."""
    clicks = events.where("event_type = 'click'").select(F.col("user_id").alias("cu"), F.col("ts").alias("ct"), F.col("event_id").alias("click_id")).withWatermark("ct", late)
    bought = events.where("event_type = 'purchase'").select("user_id", "ts", "event_id").withWatermark("ts", late)
    on = (F.col("cu") == F.col("user_id")) & (F.col("ct") <= F.col("ts")) & (F.col("ct") >= F.col("ts") - F.expr(f"interval {within}"))
    return bought.join(clicks, on).select("event_id", "click_id", "user_id")


def bin_counts(edges: DataFrame, bins: DataFrame) -> DataFrame:
    """Running neighbour counts by bin of a stream of edges; noise is added once per release, never per batch."""
    placed = edges.join(bins.select(F.col("v").alias("u"), "bin"), "u")
    return placed.groupBy("v", "bin").agg(F.count("*").alias("n"))


def merge_counts(target: str):
    """foreachBatch writer of co-occurrence counts (a, b, n): a batch that comes again replaces its own part."""

    def write(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{target}/batch={batch_id}")

    return write


def merged_counts(spark: SparkSession, target: str) -> DataFrame:
    return spark.read.parquet(target).groupBy("a", "b").agg(F.sum("n").alias("n"))


BUDGET = "v long, emissions long, spent double, over boolean"


def budgets(emissions: DataFrame, eps: float, limit: float) -> DataFrame:
    """Running privacy budget of each device over a stream of emissions (v), and whether it is over its limit."""

    def spend(key, batches, state):
        n = state.get[0] if state.exists else 0
        for pdf in batches:
            n += len(pdf)
        state.update((n,))
        yield pd.DataFrame({"v": [key[0]], "emissions": [n], "spent": [n * eps], "over": [n * eps > limit]})

    return emissions.groupBy("v").applyInPandasWithState(spend, BUDGET, "n long", "update", "NoTimeout")


def drain(stream: DataFrame, name: str, mode: str, store: Store) -> DataFrame:
    """Run a stream over all that is there and return its memory table."""
    query = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"{store.base}/{name}").trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.table(name)


def latest(stream: DataFrame, keys: list[str], store: Store) -> DataFrame:
    """Run a stream in update mode over all that is there; its rows go to Parquet, one folder for each batch, and of each key the last batch counts.

    A batch that comes again replaces its own folder; nothing passes through the driver.
    """
    target = f"{store.base}/latest"

    def write(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{target}/batch={batch_id}")

    query = stream.writeStream.foreachBatch(write).outputMode("update").option("checkpointLocation", f"{store.base}/progress").trigger(availableNow=True).start()
    query.awaitTermination()
    rest = [c for c in stream.columns if c not in keys]
    rows = stream.sparkSession.read.parquet(target)
    return rows.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch").alias("x")).select(*keys, "x.*")


def bin_counts_of_events(spark: SparkSession, sf_dir: str, k: int = 4) -> DataFrame:
    """Neighbour counts by bin from a stream of event pairs (user, kind of event), equal to the batch counts."""
    batch = load(spark, sf_dir, "events")
    store = Store(spark, "stream")
    events = spark.readStream.schema(batch.schema).parquet(f"{sf_dir}/events*.parquet")
    edges = events.select(F.col("user_id").alias("v"), F.pmod("event_id", F.lit(97)).alias("u"))
    bins = spark.range(97).select(F.col("id").alias("v"), (F.pmod("id", F.lit(k)) + 1).cast("int").alias("bin"))
    return latest(bin_counts(edges, bins), ["v", "bin"], store)
