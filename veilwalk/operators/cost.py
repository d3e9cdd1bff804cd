"""Messages, bytes and privacy budgets of the method."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from veilwalk.functions.vectors import messages_protocol, messages_published

NUMBER, IDENTIFIER = 8, 8


def walk_messages(walks: DataFrame) -> DataFrame:
    """Walks, messages between devices, jumps, empty pools, and mean messages of a walk, in one row."""
    return walks.agg(
        F.count("*").alias("walks"), F.sum("hops").cast("long").alias("messages"), F.sum("jumps").cast("long").alias("jumps"),
        F.sum("pool_empty").cast("long").alias("pool_empty"), F.round(F.avg("hops"), 6).alias("mean_messages"),
    )


def expected_messages(spark: SparkSession, lengths: list[int], jumps: list[float]) -> DataFrame:
    """(length, p, protocol, published, saved, fall): both closed forms, what jumps save, and the relative fall."""
    return messages_of(spark.createDataFrame([(n, float(p)) for n in lengths for p in jumps], "length int, p double"))


def messages_of(grid: DataFrame) -> DataFrame:
    """expected_messages() of given rows (length, p)."""
    a, b = messages_protocol(F.col("length"), F.col("p")), messages_published(F.col("length"), F.col("p"))
    base = F.col("length") - 1.0
    return grid.select("length", "p", F.round(a, 6).alias("protocol"), F.round(b, 6).alias("published"), F.round(base - b, 6).alias("saved"), F.round(F.when(base > 0, (base - b) / base).otherwise(0.0), 6).alias("fall"))


def total_saving(vertices: int, per_vertex: int, length: int, p: float, spark: SparkSession) -> DataFrame:
    grid = expected_messages(spark, [length], [p])
    return grid.select("length", "p", (F.lit(vertices) * per_vertex * F.col("saved")).alias("total_saved"))


def message_ledger(edges: DataFrame, walks: DataFrame, k: int) -> DataFrame:
    """(phase, kind, src_role, dst_role, n, bytes) of everything that devices and the server send."""
    size = edges.agg(F.countDistinct("v").alias("nv"), F.count("*").alias("ne"))
    walked = walks.agg(F.count("*").alias("nw"), F.sum("hops").alias("hops"), F.sum(F.size("seq")).alias("seen"))
    n, e, w = F.col("nv"), F.col("ne"), F.col("nw")
    events = [
        ("tree", "bin plan", "server", "device", n, n * n * (IDENTIFIER + 4)), ("tree", "degree vector", "device", "server", n, n * k * NUMBER),
        ("tree", "vector table", "server", "device", n, n * n * k * NUMBER), ("tree", "degree matrix", "device", "server", n, e * k * NUMBER),
        ("walk", "tree and dissimilarity", "server", "device", n, n * n * n * NUMBER), ("walk", "start", "server", "device", w, w * 3 * NUMBER),
        ("walk", "step", "device", "device", F.col("hops"), F.col("hops") * 3 * NUMBER), ("walk", "sequence", "device", "server", w, F.col("seen") * IDENTIFIER),
    ]
    cells = F.array(*[F.struct(F.lit(p).alias("phase"), F.lit(kind).alias("kind"), F.lit(a).alias("src_role"), F.lit(b).alias("dst_role"), m.cast("long").alias("n"), z.cast("double").alias("bytes")) for p, kind, a, b, m, z in events])
    return size.crossJoin(walked).select(F.inline(cells))  # one row each


def ledger_cube(ledger: DataFrame) -> DataFrame:
    """Messages and bytes for all groupings by phase and roles."""
    return ledger.cube("phase", "src_role", "dst_role").agg(F.sum("n").alias("n"), F.sum("bytes").alias("bytes"), F.grouping_id().alias("level"))


def privacy_ledger(walks: DataFrame, eps_degree: float | None, eps_walk: float | None, k: int, sensitivity: float = 1.0) -> DataFrame:
    """(v, emissions, eps): basic composition over the counts a device releases and the walk elements it emits; no tighter claim is made.

    An element is emitted by the device that holds the walk, so devices that many walks pass spend more. Counts of one vertex lie in disjoint bins, so adding a link spends the noise budget once; exchanging one for another
    touches two bins.
    """
    del k
    spent = walks.select(F.explode("emitters").alias("v")).groupBy("v").agg(F.count("*").alias("emissions"))
    fixed = 0.0 if eps_degree is None else eps_degree * max(1.0, 1.0 / sensitivity)
    return spent.select("v", "emissions", (F.lit(fixed) + F.col("emissions") * F.lit(eps_walk or 0.0)).alias("eps"))


def row_linkability(matrices: DataFrame, vectors: DataFrame) -> DataFrame:
    """Share of matrix rows that equal the vector of one vertex only: what a server can read back from them."""
    owners = vectors.groupBy("c").agg(F.count("*").alias("owners"))
    rows = matrices.where(F.size("nbr_order") > 0).select(F.explode("m").alias("c")).groupBy("c").agg(F.count("*").alias("n"))
    both = rows.join(owners, "c", "left")
    return both.agg(F.sum("n").alias("rows"), F.round(F.sum(F.when(F.col("owners") == 1, F.col("n")).otherwise(0)) / F.sum("n"), 6).alias("linkable"))


def dp_ratio(one: DataFrame, other: DataFrame, value: str) -> DataFrame:
    """Largest absolute log-ratio of output frequencies of two samples, over outputs that both have."""
    a = one.groupBy(value).agg(F.count("*").alias("a"))
    b = other.groupBy(value).agg(F.count("*").alias("b"))
    n = one.agg(F.count("*").alias("na")).crossJoin(other.agg(F.count("*").alias("nb")))  # one row
    both = a.join(b, value).crossJoin(F.broadcast(n))
    return both.agg(F.max(F.abs(F.log(F.col("a") / F.col("na")) - F.log(F.col("b") / F.col("nb")))).alias("max_log_ratio"))
