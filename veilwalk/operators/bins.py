"""Random numbering of the roster and its split into bins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veilwalk.functions.draws import number, unit
from veilwalk.plans.lineage import Store, positions


def number_vertices(vertices: DataFrame, seed: str = "1", rng: str = "md5") -> DataFrame:
    """(v, ordinal): a random order of the roster from 0."""
    drawn = vertices.select("v", number(seed, "number", "v", rng=rng).alias("_n"))
    return positions(drawn, Store(vertices.sparkSession, "number"), "_n", "v").select("v", "ordinal")


def assign_bins(ordinals: DataFrame, k: int, sizes: str = "equal", seed: str = "1") -> DataFrame:
    """(v, ordinal, bin): bins 1 to k. 'random' draws a bin for each vertex but lets the first k fill all bins."""
    by_rank = F.pmod("ordinal", F.lit(k)) + 1
    if sizes == "random":
        drawn = F.floor(unit(seed, "bin", "v") * k) + 1
        by_rank = F.when(F.col("ordinal") < k, by_rank).otherwise(drawn)
    elif sizes != "equal":
        raise ValueError(sizes)
    return ordinals.select("v", "ordinal", by_rank.cast("int").alias("bin"))
