"""Contrasts to the method: exact two-hop knowledge, randomized response, neighbour majority, chance."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from veilwalk.functions.draws import unit


def exact_two_hop(edges: DataFrame) -> DataFrame:
    """(v, w): vertices two links away that are not neighbours."""
    two = edges.join(edges.select(F.col("v").alias("u"), F.col("u").alias("w")), "u").where("v <> w").select("v", "w").distinct()
    return two.exceptAll(edges.select("v", F.col("u").alias("w")))


def shared_neighbours(edges: DataFrame, a: int, b: int) -> DataFrame:
    """Common neighbours of two vertices."""
    of = lambda v: edges.where(F.col("v") == v).select("u")
    return of(a).intersect(of(b))


def randomized_response(pairs: DataFrame, edges: DataFrame, eps: float, seed: str = "1") -> DataFrame:
    """(v, u, linked, told): each device tells the truth about a pair with probability e^eps / (1 + e^eps)."""
    keep = math.exp(eps) / (1 + math.exp(eps))
    both = pairs.select("v", "u").join(edges.select("v", "u", F.lit(1).alias("linked")), ["v", "u"], "left").na.fill(0)
    return both.withColumn("told", F.when(unit(seed, "response", "v", "u") < keep, F.col("linked")).otherwise(1 - F.col("linked")))


def neighbour_majority(edges: DataFrame, truth: DataFrame) -> DataFrame:
    """(v, label): the most frequent label of each vertex's neighbours; ties go to the label that sorts first."""
    votes = edges.join(truth.select(F.col("v").alias("u"), "label"), "u").groupBy("v", "label").agg(F.count("*").alias("n"))
    w = Window.partitionBy("v").orderBy(F.desc("n"), "label")
    return votes.withColumn("r", F.row_number().over(w)).where("r = 1").select("v", "label")


def majority_label(truth: DataFrame, vertices: DataFrame) -> DataFrame:
    """(v, label): the most frequent label for every vertex."""
    top = truth.groupBy("label").count().orderBy(F.desc("count"), "label").limit(1).select("label")
    return vertices.select("v").crossJoin(F.broadcast(top))  # one row


def random_label(truth: DataFrame, vertices: DataFrame, seed: str = "1") -> DataFrame:
    """(v, label): a label drawn evenly from those there are."""
    names = truth.agg(F.sort_array(F.collect_set("label")).alias("names"))  # one row of distinct labels
    pick = F.floor(unit(seed, "label", "v") * F.size("names")).cast("int") + 1
    return vertices.select("v").crossJoin(F.broadcast(names)).select("v", F.element_at("names", pick).alias("label"))
