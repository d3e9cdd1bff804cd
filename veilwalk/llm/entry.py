"""Queries of the training-data operators for __spark_entry__.py, with production parameters over whole tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from veilwalk.llm import decontaminate, embeddings, language, licenses, packing, pii, simhash, suffixes, tokenfile, warc
from veilwalk.llm.common import Scratch, shared_root, table


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Licence of every document. Its path is made of source and id: folders of a hundred documents, whose first one stands for the folder's licence file."""
    docs = table(spark, sf_dir, "documents")
    number = F.col("doc_id").cast("string")
    name = F.when(F.col("doc_id") % 100 == 0, "LICENSE.txt").otherwise(F.concat(number, F.lit(".txt")))
    folder = F.concat_ws("/", F.coalesce("source", F.lit("unknown")), F.floor(F.col("doc_id") / 1000).cast("string"), (F.floor(F.col("doc_id") / 100) % 10).cast("string"))
    path = F.when(F.col("doc_id").isNotNull(), F.concat_ws("/", folder, name))
    files = docs.select("doc_id", path.alias("path"), "text")
    return licenses.scan(files).select("doc_id", "path", "license", F.round("score", 6).alias("score"), "origin")


def op2_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.detect(table(spark, sf_dir, "documents"))


def op3_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every pair of a document and a benchmark item that it holds within the item's error budget."""
    return decontaminate.matches(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op4_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = language.fit(docs.where(~language.held_out()))
    rows = docs.select("doc_id", language.held_out().alias("held_out"), "text")
    return language.predict(rows, model).drop("text")


def op5_pack(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.packed(table(spark, sf_dir, "documents"))


def op6_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embeddings.near_duplicates(table(spark, sf_dir, "embeddings"))


def op7_token_file(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark, "tokens")
    tokenfile.write(table(spark, sf_dir, "documents"), scratch.path("files"), scratch)
    return tokenfile.read(spark, scratch.path("files"))


def op8_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffixes.removed(table(spark, sf_dir, "documents"))


def op9_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    uri = Scratch(spark, "warc").path("archives")
    warc.write(table(spark, sf_dir, "pages"), uri)
    rows = warc.read(spark, uri, payload=False, verify=True).where(F.col("record_type").isin("response", "revisit"))
    number = lambda c: F.regexp_extract(c, r"^<urn:page:(-?\d+)>$", 1).cast("long")
    return rows.select(number("record_id").alias("page_id"), "payload_bytes", "payload_digest", "record_type", number("refers_to").alias("refers_to"))


def op10_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.components(table(spark, sf_dir, "documents"))
    return found.select("doc_id", simhash.fingerprint_hex(F.col("fp")).alias("fingerprint"), "component_id")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    ops = (op1_license_scan, op2_pii, op3_decontaminate, op4_language, op5_pack, op6_embeddings, op7_token_file, op8_suffix_dedup, op9_warc, op10_simhash)
    return {f.__name__: f for f in ops}


def oracle_sql() -> dict[str, str]:
    from veilwalk.llm import oracles

    return oracles.SQL
