"""Co-occurrence of vertices within a window of walks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def walk_pairs(walks: DataFrame, window: int) -> DataFrame:
    """(a, b): ordered pairs of positions at most window apart, both directions."""
    n = F.size("seq")
    pairs = F.flatten(F.transform(F.sequence(F.lit(1), n), lambda i: F.transform(
        F.slice("seq", F.greatest(F.lit(1), i - window).cast("int"), (i - F.greatest(F.lit(1), i - window)).cast("int")),
        lambda x: F.struct(F.element_at("seq", i).alias("a"), x.alias("b")),
    )))
    one = walks.where(n > 1).select(F.explode(pairs).alias("p")).select("p.a", "p.b")
    return one.union(one.select(F.col("b").alias("a"), F.col("a").alias("b")))


def cooccurrence(walks: DataFrame, window: int) -> DataFrame:
    """(a, b, n); counts are combined before they are dealt."""
    return walk_pairs(walks, window).groupBy("a", "b").agg(F.count("*").alias("n"))


def with_probability(cooc: DataFrame) -> DataFrame:
    """cooc with p, the share of all pairs."""
    total = cooc.agg(F.sum("n").alias("t"))
    return cooc.crossJoin(F.broadcast(total)).select("a", "b", "n", (F.col("n") / F.col("t")).alias("p"))  # one row


def walk_dissimilarity(cooc: DataFrame) -> DataFrame:
    """(a, b, dissim): how likely a pair is to miss one another."""
    return with_probability(cooc).select("a", "b", (1 - F.col("p")).alias("dissim"))


def pmi(cooc: DataFrame, shift: float = 1.0) -> DataFrame:
    """(a, b, pmi): pointwise mutual information less the logarithm of shift."""
    left = cooc.groupBy("a").agg(F.sum("n").alias("na"))
    right = cooc.groupBy("b").agg(F.sum("n").alias("nb"))
    total = cooc.agg(F.sum("n").alias("t"))
    both = cooc.join(left, "a").join(right, "b").crossJoin(F.broadcast(total))
    return both.select("a", "b", (F.log(F.col("n") * F.col("t") / (F.col("na") * F.col("nb"))) - F.log(F.lit(float(shift)))).alias("pmi"))
