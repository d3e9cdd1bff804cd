"""Writers and readers of the method's tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def write_walks(walks: DataFrame, path: str) -> None:
    """Parquet by repetition, walks in order of their starts, so readers of a few repetitions skip the rest."""
    walks.repartition("rep").sortWithinPartitions("rep", "start").write.mode("overwrite").partitionBy("rep").parquet(path)


def read_walks(spark: SparkSession, path: str, reps: list[int] | None = None) -> DataFrame:
    df = spark.read.parquet(path)
    return df if reps is None else df.where(F.col("rep").isin(reps))


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int) -> None:
    """A managed table bucketed by key: joins on the key deal only the other side."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).format("parquet").saveAsTable(table)


def write_ledger(ledger: DataFrame, path: str) -> None:
    """One JSON line for each kind of message."""
    ledger.write.mode("overwrite").json(path)


def read_ledger(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("phase string, kind string, src_role string, dst_role string, n long, bytes double").json(path)


def write_orc(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").orc(path)
