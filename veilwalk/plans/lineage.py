"""Tables in the shared folder that cut lineage, and global row numbers without a one-task window."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_root(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir. Only a local session may go without it and gets a temporary one."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root and not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    return (root or "file://" + os.path.join(tempfile.gettempdir(), "veilwalk-shared")).rstrip("/")


class Store:
    """A folder of intermediate tables; a lost executor costs a read, not a recomputation."""

    def __init__(self, spark: SparkSession, label: str = "store"):
        self.spark, self.base, self.n = spark, f"{shared_root(spark)}/{label}-{uuid.uuid4().hex}", 0

    def keep(self, df: DataFrame) -> DataFrame:
        self.n += 1
        path = f"{self.base}/{self.n}"
        df.write.parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)


def positions(df: DataFrame, store: Store, *order: Column | str, name: str = "ordinal") -> DataFrame:
    """Rows numbered from 0 in a global order: ranges are sorted apart and the driver adds up one count per range."""
    kept = store.keep(df)  # range partitioning reads its input twice
    ranged = kept.repartitionByRange(*order).sortWithinPartitions(*order)
    ranged = store.keep(ranged.withColumn("_part", F.spark_partition_id()).withColumn("_row", F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1)))
    before, total = [], 0
    for r in sorted(ranged.groupBy("_part").count().collect()):
        before.append((r["_part"], total))
        total += r["count"]
    starts = df.sparkSession.createDataFrame(before or [(0, 0)], "_part int, _start long")
    return ranged.join(F.broadcast(starts), "_part").withColumn(name, F.col("_start") + F.col("_row")).drop("_part", "_row", "_start")
