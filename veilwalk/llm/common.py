"""Shared parts of the training-data operators: cluster-visible scratch tables, global row numbers, components."""

from __future__ import annotations

import ctypes
import json
import os
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def shared_root(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir. Only a local session may go without it and gets a temporary one."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root and not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    return (root or "file://" + os.path.join(tempfile.gettempdir(), "veilwalk-shared")).rstrip("/")


class Scratch:
    """Tables written once to the shared folder, so that lineage is cut and lost executors cost no recomputation."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        self.base = f"{shared_root(spark)}/{label}-{uuid.uuid4().hex}"

    def path(self, name: str) -> str:
        return f"{self.base}/{name}"

    def save(self, df: DataFrame, name: str) -> DataFrame:
        path = self.path(name)
        df.write.mode("overwrite").option("compression", "zstd").parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, name: str) -> None:
        """Delete a scratch table that nothing reads any more."""
        jvm = self.spark._jvm
        path = jvm.org.apache.hadoop.fs.Path(self.path(name))
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of a string column and its n+1 offsets, without Python strings; nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    column = column.cast(pa.large_utf8())
    n = len(column)
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + n + 1]
    data = column.buffers()[2]
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def texts(column: pa.Array) -> list[str]:
    """Python strings of a column, nulls as empty."""
    return ["" if t is None else t for t in column.to_pylist()]


def release() -> None:
    """Give freed memory back to the system: workers outlive their tasks and serve those of all later stages."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc alone has it
    if trim:
        trim(0)


def arrow_map(df: DataFrame, batch: Callable[[pa.RecordBatch], Iterator[pa.RecordBatch]], schema: T.StructType) -> DataFrame:
    """mapInArrow with a function of one batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield from batch(b)
        release()

    return df.mapInArrow(run, schema)


def numbered(df: DataFrame, scratch: Scratch, name: str, keys: list[str], out: str = "pos") -> DataFrame:
    """Global position of each row in the order of keys: range partitions, written once, then offsets per file.

    No window over the whole input: each task numbers its own rows, and the driver sees one count per task.
    """
    ordered = df.repartitionByRange(*keys).sortWithinPartitions(*keys)
    ordered = ordered.withColumn("_part", F.spark_partition_id()).withColumn(
        "_row", F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1)
    )
    saved = scratch.save(ordered, name)
    counts = {r["_part"]: r["n"] for r in saved.groupBy("_part").agg(F.count("*").alias("n")).collect()}
    before, total = {}, 0
    for part in sorted(counts):
        before[part], total = total, total + counts[part]
    starts = saved.sparkSession.createDataFrame([(p, s) for p, s in before.items()] or [(0, 0)], "_part int, _start long")
    return saved.join(F.broadcast(starts), "_part").withColumn(out, F.col("_start") + F.col("_row")).drop("_part", "_row", "_start")


#: Keys with more rows than this are hot; a hot key's rows are dealt over so many tasks.
HOT_ROWS, SPREAD = 1 << 20, 64


def spread_join(left: DataFrame, right: DataFrame, key: str, by: list[str], how: str = "inner") -> DataFrame:
    """left joined to right, which has one row for each key; rows of a hot key or a null one are dealt by a hash of the columns by.

    Hot keys are at most left's rows / HOT_ROWS, which bounds what is broadcast: 16 MB of keys for 10^12 rows.
    """
    heavy = left.where(F.col(key).isNotNull()).groupBy(key).agg(F.count("*").alias("_n")).where(F.col("_n") > HOT_ROWS).select(key, F.lit(True).alias("_hot"))
    salt = F.when(F.col("_hot") | F.col(key).isNull(), F.pmod(F.xxhash64(*by), F.lit(SPREAD))).otherwise(0)
    dealt = left.join(F.broadcast(heavy), key, "left").withColumn("_salt", salt).drop("_hot")
    copies = F.when(F.col("_hot"), F.sequence(F.lit(0).cast("long"), F.lit(SPREAD - 1).cast("long"))).otherwise(F.array(F.lit(0).cast("long")))
    many = right.join(F.broadcast(heavy), key, "left").withColumn("_salt", F.explode(copies)).drop("_hot")
    return dealt.join(many, [key, "_salt"], how).drop("_salt")


class Forest:
    """Components of the links that one task finds; it hands on one link for each node, to its smallest companion.

    Tasks that see the same group name few different smallest companions, so their links coincide.
    """

    def __init__(self) -> None:
        self.parent: dict[int, int] = {}

    def find(self, x: int) -> int:
        parent = self.parent
        while (up := parent.setdefault(x, x)) != x:
            parent[x] = parent[up]
            x = up
        return x

    def add(self, edges: list) -> None:
        for x, y in edges:
            a, b = self.find(x), self.find(y)
            if a < b:
                self.parent[b] = a
            elif b < a:
                self.parent[a] = b

    def stars(self) -> np.ndarray:
        """Rows (node, smallest node of its component) of all nodes but those."""
        rows = [(x, self.find(x)) for x in list(self.parent)]
        return np.array([r for r in rows if r[0] != r[1]], np.int64).reshape(-1, 2)


def connected_components(edges: DataFrame, scratch: Scratch, rounds: int = 60) -> DataFrame:
    """(node, root) of every node that has an edge (a, b); root is the smallest node of its component.

    Alternating star contraction: every node is tied to its smallest neighbour until each component is one star.
    Each round is a table in the shared folder; edges never reach the driver. Joins have one side
    with a row for each node, so adaptive execution splits a hub's partition. Null ends are ignored.
    """
    spark = edges.sparkSession

    def stamp(e: DataFrame) -> tuple[int, int]:
        row = e.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("s")).first()
        return row["n"], row["s"]

    e = edges.where("a is not null and b is not null and a <> b").select(
        F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")
    )
    e = scratch.save(e.distinct(), "edges0")
    last = stamp(e)
    for k in range(1, rounds + 1):
        if not last[0]:
            break
        both = e.select("u", "v").union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        merged = small.union(low.select("u", F.col("m").alias("v"))).where("u <> v")
        e2 = scratch.save(merged.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), f"edges{k}")
        now = stamp(e2)
        scratch.drop(f"edges{k - 1}")
        e = e2
        if now == last:
            break
        last = now
    else:
        raise RuntimeError("components did not settle")
    leaves = e.select(F.col("u").alias("node"), F.col("v").alias("root"))
    if not last[0]:
        return spark.createDataFrame([], leaves.schema)
    return leaves.union(e.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())


def as_json(value: object) -> str:
    return json.dumps(value, sort_keys=True)
