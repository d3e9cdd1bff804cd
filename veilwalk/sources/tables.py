"""Scans of the given tables with checked columns, edge-list files, and SQL views."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Columns that each table must have.
COLUMNS = {
    "region": "r_regionkey r_name", "nation": "n_nationkey n_name n_regionkey", "customer": "c_custkey c_name c_nationkey c_acctbal c_mktsegment",
    "supplier": "s_suppkey s_name s_nationkey s_acctbal", "part": "p_partkey p_name p_brand p_type p_size p_retailprice",
    "orders": "o_orderkey o_custkey o_orderstatus o_totalprice o_orderdate o_orderpriority",
    "lineitem": "l_orderkey l_partkey l_suppkey l_linenumber l_quantity l_extendedprice l_discount l_tax l_returnflag l_linestatus l_shipdate",
    "events": "event_id ts user_id event_type value props", "documents": "doc_id text lang source n_chars", "labels": "doc_id quality toxic",
    "embeddings": "vec_id embedding label", "pages": "page_id url html", "benchmark": "item_id text", "conversations": "conv_id turn role text",
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    missing = set(COLUMNS[name].split()) - set(df.columns)
    if missing:
        raise ValueError(f"{name} lacks {sorted(missing)}")
    return df


def register_views(spark: SparkSession, frames: dict[str, DataFrame]) -> None:
    for name, df in frames.items():
        df.createOrReplaceTempView(name)


def read_edge_list(spark: SparkSession, path: str, sep: str = " ") -> DataFrame:
    """(v, u) pairs of a text file; lines that do not hold two whole numbers are dropped."""
    parts = F.split(F.trim("value"), r"\s+" if sep == " " else sep)
    rows = spark.read.text(path).select(F.try_element_at(parts, F.lit(1)).alias("v"), F.try_element_at(parts, F.lit(2)).alias("u"))
    return rows.where("v rlike '^[0-9]+$' and u rlike '^[0-9]+$'").select(F.col("v").cast("long"), F.col("u").cast("long"))


def write_edge_list(edges: DataFrame, path: str, sep: str = " ") -> None:
    edges.where("v < u").select(F.concat_ws(sep, "v", "u").alias("value")).write.mode("overwrite").text(path)
