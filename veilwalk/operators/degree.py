"""What devices tell about their neighbours: noisy counts per bin, and matrices of their neighbours' counts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veilwalk.functions.draws import laplace, number
from veilwalk.functions.vectors import total


def bin_counts(edges: DataFrame, bins: DataFrame, k: int) -> DataFrame:
    """(v, n): an array of neighbour counts by bin, zeros included; isolated vertices of the plan have zeros."""
    placed = edges.join(bins.select(F.col("v").alias("u"), "bin"), "u")
    counts = placed.groupBy("v").agg(F.array(*[F.count_if(F.col("bin") == j) for j in range(1, k + 1)]).alias("n"))
    zeros = F.array(*[F.lit(0).cast("long")] * k)
    return bins.select("v").join(counts, "v", "left").select("v", F.coalesce("n", zeros).alias("n"))


def degree_vectors(counts: DataFrame, eps: float | None, k: int, sensitivity: float = 1.0, seed: str = "1", rng: str = "md5") -> DataFrame:
    """(v, c): counts plus Laplace noise of scale sensitivity / eps for each bin; eps None adds none."""
    cells = [F.element_at("n", j).cast("double") for j in range(1, k + 1)]
    if eps is not None:
        cells = [c + laplace(number(seed, "laplace", "v", F.lit(j), rng=rng), sensitivity / eps) for j, c in enumerate(cells, 1)]
    return counts.select("v", F.array(*cells).alias("c"))


def long_form(frame: DataFrame, column: str, name: str) -> DataFrame:
    """(v, bin, name) from an array column."""
    return frame.select("v", F.posexplode(column).alias("bin", name)).withColumn("bin", F.col("bin") + 1)


def estimated_degree(vectors: DataFrame) -> DataFrame:
    return vectors.select("v", total(F.col("c")).alias("est"))


def ordered_matrices(edges: DataFrame, vectors: DataFrame, eps_rows: float | None = None, seed: str = "1") -> DataFrame:
    """(v, nbr_order, m): neighbours by ascending noisy degree, and their vectors as rows; ties go by id.

    Vertices without neighbours get one row of zeros. eps_rows adds noise of a device's own to the rows it hands on.
    """
    cell = F.col("c")
    if eps_rows is not None:
        cell = F.transform("c", lambda x, j: x + laplace(number(seed, "row", F.col("v"), F.col("u"), j), 1.0 / eps_rows))
    told = vectors.select(F.col("v").alias("u"), "c", total(F.col("c")).alias("est"))
    rows = edges.join(told, "u").select("v", F.struct("est", "u", cell.alias("c")).alias("r"))
    held = rows.groupBy("v").agg(F.sort_array(F.collect_list("r")).alias("rows"))
    full = vectors.select("v", F.transform("c", lambda _: F.lit(0.0)).alias("zero")).join(held, "v", "left")
    return full.select(
        "v",
        F.coalesce(F.transform("rows", lambda r: r["u"]), F.array().cast("array<long>")).alias("nbr_order"),
        F.coalesce(F.transform("rows", lambda r: r["c"]), F.array("zero")).alias("m"),
    )


def cap_rows(matrices: DataFrame, r: int) -> DataFrame:
    """Matrices of more than r rows reduced to r at even places of their order."""
    n = F.size("m")
    at = F.transform(F.sequence(F.lit(0), F.lit(r - 1)), lambda i: F.element_at("m", (F.floor(i * (n - 1) / F.lit(max(r - 1, 1))) + 1).cast("int")))
    return matrices.withColumn("m", F.when(n > r, at).otherwise(F.col("m")))


def degree_lists(edges: DataFrame) -> DataFrame:
    """Matrices of one column: the sorted degrees of the neighbours."""
    deg = edges.groupBy("v").agg(F.count("*").cast("double").alias("d"))
    return ordered_matrices(edges, deg.select("v", F.array("d").alias("c")))
