"""Graphs built from the given tables: directed edge rows (v, u) in both directions, distinct, without self-loops."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from veilwalk.sources.tables import load


def symmetrize(pairs: DataFrame) -> DataFrame:
    """Both directions of pairs (v, u), each once; self-loops and nulls are no links. Ids may have any sign."""
    good = pairs.where("v is not null and u is not null and v <> u").select("v", "u")
    return good.union(good.select(F.col("u").alias("v"), F.col("v").alias("u"))).distinct()


def roster(edges: DataFrame, extra: DataFrame | None = None) -> DataFrame:
    """All vertices of the edges, and isolated ones of extra (v)."""
    found = edges.select("v")
    return (found if extra is None else found.union(extra.select("v"))).distinct()


def copurchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts ordered together."""
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    other = lines.select("l_orderkey", F.col("l_partkey").alias("u"))
    return lines.join(other, "l_orderkey").where("l_partkey <> u").select(F.col("l_partkey").alias("v"), "u").distinct()


def document_terms(spark: SparkSession, sf_dir: str, shared: int = 8, low: int = 2, high: int = 20) -> DataFrame:
    """Documents with at least that many words in common, among words in low to high documents.

    The document frequency bounds what one word can pair up.
    """
    words = F.explode(F.array_distinct(F.split(F.lower("text"), r"[^\p{L}]+")))
    held = load(spark, sf_dir, "documents").select("doc_id", words.alias("w")).where(F.length("w") >= 4).distinct()
    rare = held.groupBy("w").count().where(F.col("count").between(low, high)).select("w")
    kept = held.join(rare, "w")
    pairs = kept.select("w", F.col("doc_id").alias("v")).join(kept.select("w", F.col("doc_id").alias("u")), "w").where("v < u")
    edges = pairs.groupBy("v", "u").count().where(F.col("count") >= shared).select("v", "u")
    return edges.union(edges.select(F.col("u").alias("v"), F.col("v").alias("u")))


def buys_from(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers (even ids) and suppliers (odd ids) joined by an order."""
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    pairs = orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey")).select((F.col("o_custkey") * 2).alias("v"), (F.col("l_suppkey") * 2 + 1).alias("u"))
    return symmetrize(pairs.distinct())


def succession(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users of consecutive events, by time and then event id."""
    events = load(spark, sf_dir, "events").select("event_id", "ts", "user_id")
    return symmetrize(_consecutive(events))


def _consecutive(events: DataFrame) -> DataFrame:
    """Each event's user and the next event's: within hours by a window, within days and across days by the ends of hours and days."""
    events = events.withColumn("slot", F.date_trunc("hour", F.col("ts")))
    w = Window.partitionBy("slot").orderBy("ts", "event_id")
    out = events.select(F.col("user_id").alias("v"), F.lead("user_id").over(w).alias("u"))
    at = F.struct("ts", "event_id")
    ends = events.groupBy("slot").agg(F.min_by("user_id", at).alias("first"), F.max_by("user_id", at).alias("last"))
    for unit in ("day", "year"):  # the ends of hours meet within days, those of days within years, those of years at last
        ends = ends.withColumn("span", F.date_trunc(unit, F.col("slot")))
        spans = Window.partitionBy("span").orderBy("slot")
        out = out.union(ends.select(F.col("last").alias("v"), F.lead("first").over(spans).alias("u")))
        ends = ends.groupBy(F.col("span").alias("slot")).agg(F.min_by("first", "slot").alias("first"), F.max_by("last", "slot").alias("last"))
    years = ends.agg(F.array_sort(F.collect_list(F.struct("slot", "first", "last"))).alias("y"))  # one row for each year
    pairs = F.transform(F.sequence(F.lit(1), F.size("y") - 1), lambda i: F.struct(F.element_at("y", i)["last"].alias("v"), F.element_at("y", i + 1)["first"].alias("u")))
    return out.union(years.where(F.size("y") > 1).select(F.explode(pairs).alias("p")).select("p.v", "p.u"))


HREF = r'href="(/[^"/]*)"'


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages (even ids) and navigation targets (odd ids, from a digest of the target)."""
    pages = load(spark, sf_dir, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit(HREF), 1)).alias("href"))
    target = F.conv(F.substring(F.md5("href"), 1, 13), 16, 10).cast("long") * 2 + 1
    return symmetrize(pages.select((F.col("page_id") * 2).alias("v"), target.alias("u")).distinct())


def geo_star(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers, suppliers, nations and regions as a forest; ids are four times the key plus the kind."""
    arms = [("customer", "c_custkey", "c_nationkey", 0), ("supplier", "s_suppkey", "s_nationkey", 1)]
    pairs = load(spark, sf_dir, "nation").select((F.col("n_nationkey").cast("long") * 4 + 2).alias("v"), (F.col("n_regionkey").cast("long") * 4 + 3).alias("u"))
    for name, key, nation, kind in arms:
        pairs = pairs.union(load(spark, sf_dir, name).select((F.col(key) * 4 + kind).alias("v"), (F.col(nation).cast("long") * 4 + 2).alias("u")))
    return symmetrize(pairs)


def vector_knn(spark: SparkSession, sf_dir: str, neighbours: int = 10, block: int = 1024) -> DataFrame:
    """Nearest neighbours by cosine: blocks of vectors meet in pairs, each task keeps its best."""
    import numpy as np
    import pandas as pd

    rows = load(spark, sf_dir, "embeddings").where("vec_id is not null and embedding is not null").select("vec_id", "embedding")
    if (sizes := rows.agg(F.count_distinct(F.size("embedding"))).first()[0]) > 1:
        raise ValueError(f"vectors of {sizes} different lengths")
    blocks = rows.withColumn("b", F.pmod(F.xxhash64("vec_id"), F.lit(max(1, rows.count() // block))))
    n = blocks.agg(F.max("b")).first()[0]
    if n is None:
        return spark.createDataFrame([], "v long, u long")
    one = blocks.groupBy("b").agg(F.collect_list(F.struct("vec_id", "embedding")).alias("rows"))
    meet = one.withColumn("q", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n).cast("long"))))
    left = meet.select("q", F.col("b").alias("i"), F.col("rows").alias("known"))
    right = one.select(F.col("b").alias("q"), F.col("rows").alias("asked"))

    def best(batches):
        for pdf in batches:
            out = []
            for known, asked in zip(pdf["known"], pdf["asked"], strict=True):
                x, y = (np.array([r["embedding"] for r in part], np.float64) for part in (asked, known))
                x, y = (m / np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-300) for m in (x, y))
                ids = np.array([r["vec_id"] for r in known])
                for r, sims in zip(asked, x @ y.T, strict=True):
                    sims[ids == r["vec_id"]] = -2
                    top = np.lexsort((ids, -np.round(sims, 9)))[:neighbours]
                    out += [(r["vec_id"], int(ids[t]), float(sims[t])) for t in top if sims[t] > -2]
            yield pd.DataFrame(out, columns=["v", "u", "s"])

    found = left.join(right, "q").select("known", "asked").mapInPandas(best, "v long, u long, s double")
    w = Window.partitionBy("v").orderBy(F.round("s", 9).desc(), "u")
    return symmetrize(found.withColumn("r", F.row_number().over(w)).where(F.col("r") <= neighbours).select("v", "u"))


def statistics(edges: DataFrame) -> DataFrame:
    """Vertices, undirected edges, and least, mean and largest degree, in one row."""
    deg = edges.groupBy("v").agg(F.count("*").alias("d"))
    out = deg.agg(F.count("*").alias("n_vertices"), (F.sum("d") / 2).cast("long").alias("n_edges"), F.min("d").alias("min_degree"), F.round(F.avg("d"), 6).alias("mean_degree"), F.max("d").alias("max_degree"))
    return out


def core(edges: DataFrame, min_degree: int, rounds: int = 50) -> DataFrame:
    """The part in which each vertex keeps at least min_degree neighbours."""
    from veilwalk.plans.lineage import Store

    store, before = Store(edges.sparkSession, "core"), -1
    for _ in range(rounds):
        enough = edges.groupBy("v").count().where(F.col("count") >= min_degree).select("v")
        edges = store.keep(edges.join(enough, "v", "left_semi").join(enough.withColumnRenamed("v", "u"), "u", "left_semi").select("v", "u"))
        now = edges.count()
        if now == before:
            break
        before = now
    return edges


def adjacency(edges: DataFrame) -> DataFrame:
    """One row for each device: its sorted neighbours and their number."""
    return edges.groupBy("v").agg(F.sort_array(F.collect_list("u")).alias("nbrs")).withColumn("deg", F.size("nbrs"))


def labels_of_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(v, label): language, known quality and toxicity, and length third."""
    docs = load(spark, sf_dir, "documents")
    marks = load(spark, sf_dir, "labels")
    sized = docs.where("n_chars is not null").select(F.col("doc_id").alias("v"), "n_chars")
    cuts = sized.agg(F.percentile("n_chars", F.array(F.lit(1 / 3), F.lit(2 / 3))).alias("cut"))  # one row
    third = F.when(F.col("n_chars") <= F.col("cut")[0], "length:short").when(F.col("n_chars") <= F.col("cut")[1], "length:medium").otherwise("length:long")
    length = sized.crossJoin(F.broadcast(cuts)).select("v", third.alias("label"))
    lang = docs.where("lang is not null").select(F.col("doc_id").alias("v"), F.concat(F.lit("lang:"), "lang").alias("label"))
    known: list[Column] = [F.concat(F.lit(f"{c}:"), F.col(c).cast("string")) for c in ("quality", "toxic")]
    return lang.union(length).union(marks.select(F.col("doc_id").alias("v"), F.explode(F.array(*known)).alias("label")))


def labels_of_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(v, label): brand, first word of the type, and size band of ten."""
    band = F.ceil(F.col("p_size") / 10).cast("string")
    kinds = F.array(F.concat(F.lit("brand:"), "p_brand"), F.concat(F.lit("type:"), F.substring_index("p_type", " ", 1)), F.concat(F.lit("size:"), band))
    rows = load(spark, sf_dir, "part").select(F.col("p_partkey").alias("v"), F.explode(kinds).alias("label"))
    return rows.where("label is not null")


def labels_of_users(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(v, label): event types of which a user has more events than users have on average."""
    n = load(spark, sf_dir, "events").groupBy(F.col("user_id").alias("v"), "event_type").agg(F.count("*").alias("n"))
    users = n.agg(F.count_distinct("v").alias("users"))
    mean = n.groupBy("event_type").agg(F.sum("n").alias("all")).crossJoin(users)  # one row of users
    return n.join(F.broadcast(mean), "event_type").where("n * users > all").select("v", F.concat(F.lit("event:"), "event_type").alias("label"))
