"""Guessed two-hop neighbours: for each vertex, tree-near vertices of each bin, as many as its noisy count there."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from veilwalk.functions.draws import unit
from veilwalk.functions.vectors import pool_size
from veilwalk.operators.align import Held, stacks_of
from veilwalk.operators.tree import LeafOrder, common_depth, lca_sizes, shared_depth, shared_leaves, square


def demand(vectors: DataFrame, bins: DataFrame, rounding: str = "round", seed: str = "1") -> DataFrame:
    """(u, bin, m): how many vertices of each bin u's pool takes, u itself never counted."""
    sizes = bins.groupBy("bin").agg(F.count("*").alias("size"))
    long = vectors.select(F.col("v").alias("u"), F.posexplode("c").alias("b", "c")).select("u", (F.col("b") + 1).alias("bin"), "c")
    own = bins.select(F.col("v").alias("u"), F.col("bin").alias("own"))
    room = F.col("size") - F.when(F.col("own") == F.col("bin"), 1).otherwise(0)
    c = F.col("c")
    if rounding == "stochastic":
        c, rounding = F.floor(c + unit(seed, "round", "u", "bin")).cast("double"), "floor"
    return long.join(F.broadcast(sizes), "bin").join(own, "u").select("u", "bin", pool_size(c, room, rounding).alias("m"))


def jump_pool(candidates: DataFrame, wanted: DataFrame) -> DataFrame:
    """(u, pool): from candidates (u, w, bin, near, delta), the nearest m of each bin by near, then delta, then id."""
    w = Window.partitionBy("u", "bin").orderBy("near", "delta", "w")
    ranked = candidates.where("u <> w").join(wanted, ["u", "bin"]).withColumn("r", F.row_number().over(w)).where("r <= m")
    return ranked.groupBy("u").agg(F.sort_array(F.collect_list("w")).alias("pool"))


def tree_pool(dissim: DataFrame, leaves: DataFrame, bins: DataFrame, wanted: DataFrame, near: str = "leaves", block: Column | None = None) -> DataFrame:
    """(u, pool) in the order of a tree, block by block of the tree (one block by default), then of dissimilarity to nine places, then of id.

    near: 'leaves' of the lowest common subtree, 'hops' along the tree, or 'depth' of the common ancestor.
    """
    at = leaves.join(bins.select("v", "bin"), "v").select("v", "path", "bin", (F.lit(0) if block is None else block).alias("block"))
    need = wanted.groupBy("u").agg(F.map_from_entries(F.collect_list(F.struct("bin", "m"))).alias("need"))
    own = at.join(need.withColumnRenamed("u", "v"), "v").select("block", F.col("v").alias("u"), "v", "path", "bin", F.lit(0.0).alias("delta"), F.transform(F.sort_array(F.map_keys("need")), lambda b: F.col("need")[b]).alias("need"))
    sides = at.select("v", "block")
    inner = dissim.select("u", "v", "delta").join(sides, "v").join(sides.withColumnsRenamed({"v": "u", "block": "other"}), "u").where("block = other")
    none = {"path": F.lit(None), "bin": F.lit(None), "need": F.array()}  # null arrays take Spark's Arrow writer many times as long as empty ones
    rows = own.unionByName(inner.select("block", "u", "v", "delta", *[x.cast(own.schema[c].dataType).alias(c) for c, x in none.items()]))

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        one = pdf[pdf["path"].notna()].sort_values("v")
        ids, pairs = one["v"].to_numpy(), pdf[pdf["path"].isna()]
        d = square(ids, pairs["u"].to_numpy(), pairs["v"].to_numpy(), pairs["delta"].to_numpy())
        paths = one["path"].tolist()
        rank = lca_sizes(paths)
        if near != "leaves":
            depth = common_depth(paths)
            lengths = np.array([len(p) for p in paths])
            rank = -depth if near == "depth" else lengths[:, None] + lengths[None, :] - 2 * depth
        kinds, pools = one["bin"].to_numpy(), []
        for i, need in enumerate(one["need"]):
            order = np.lexsort((ids, np.round(d[i], 9), rank[i]))
            order = order[order != i]
            pools.append(np.sort(np.concatenate([ids[order[kinds[order] == b][: int(m)]] for b, m in enumerate(need, 1)])))
        return pd.DataFrame({"u": ids, "pool": pools})

    return rows.groupBy("block").applyInPandas(work, "u long, pool array<long>").where(F.size("pool") > 0)


def held_pool(held: Held, leaves: DataFrame, bins: DataFrame, wanted: DataFrame, near: str = "leaves") -> DataFrame:
    """(u, pool) as tree_pool() has them for one block, at any size and without pairs: only those that tie for a bin's last places are aligned."""
    shared, order, spark = held.shared, LeafOrder(leaves, held).shared, held.spark
    kinds = spark.sparkContext.broadcast(bins.select("v", F.col("bin").cast("long").alias("bin")).toArrow().sort_by("v")["bin"].to_numpy())
    need = wanted.groupBy("u").agg(F.transform(F.array_sort(F.collect_list(F.struct("bin", "m"))), lambda x: x["m"]).alias("need"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, stacks, tree, kind = shared.value[0], stacks_of(shared), order.value, kinds.value
        length = tree[3]
        for b in batches:
            places = np.searchsorted(ids, b.column(0).to_numpy()).tolist()
            for i, m in zip(places, b.column(1).to_pylist(), strict=True):
                rank = shared_leaves(tree, i) if near == "leaves" else -shared_depth(tree, i)
                if near == "hops":
                    rank = length[i] + length + 2 * rank
                chosen, tied, asked = [], [], np.zeros(len(ids), bool)
                for x, n in enumerate(m, 1):
                    own = np.flatnonzero(kind == x)
                    own = own[own != i]
                    if 0 < n < len(own):
                        last = np.partition(rank[own], n - 1)[n - 1]
                        sure, edge = own[rank[own] < last], own[rank[own] == last]
                        chosen.append(sure)
                        tied.append((edge, n - len(sure)))
                        asked[edge] = len(edge) > n - len(sure)
                    elif n > 0:
                        chosen.append(own)
                delta = np.round(stacks.row(i, asked), 9)
                chosen += [edge[np.argsort(delta[edge], kind="stable")[:n]] for edge, n in tied]  # places are in the order of ids
                pool = ids[np.sort(np.concatenate(chosen))] if chosen else ids[:0]
                if len(pool):
                    yield pa.RecordBatch.from_arrays([pa.array([ids[i]]), pa.ListArray.from_arrays(pa.array([0, len(pool)], pa.int32()), pa.array(pool))], names=["u", "pool"])

    return need.repartition(held.parts, "u").mapInArrow(run, "u long, pool array<long>")


def fill_pools(pools: DataFrame, leaves: DataFrame, bins: DataFrame, wanted: DataFrame) -> DataFrame:
    """(u, pool) of pools made within blocks, filled from the parent subtrees of the block until each bin's demand is met.

    leaves has v, path and block, the path of v's block. Members outside the block come by the deepest common subtree, then by
    id: dissimilarities are known within blocks only. All of a block's vertices share one list for each bin.
    """
    at = leaves.select("v", "path", "block").join(bins.select("v", "bin"), "v")
    inside = at.groupBy("block", "bin").agg(F.count("*").alias("inside"))
    own = F.when(F.col("own") == F.col("bin"), 1).otherwise(0)
    short = wanted.join(at.select(F.col("v").alias("u"), "block", F.col("bin").alias("own")), "u").join(inside, ["block", "bin"], "left")
    short = short.select("u", "block", "bin", (F.col("m") - F.coalesce("inside", F.lit(0)) + own).cast("int").alias("r")).where("r > 0")
    most = short.groupBy("block", "bin").agg(F.max("r").alias("most")).join(inside, ["block", "bin"], "left").na.fill(0, ["inside"])
    prefixes = lambda c: F.transform(F.sequence(F.lit(0), F.length(c)), lambda i: F.col(c).substr(F.lit(1), i))
    up = at.select("v", "path", "bin", F.explode(prefixes("path")).alias("up"))
    room = up.groupBy("up", "bin").agg(F.count("*").alias("n"))
    above = most.select("block", "bin", "most", "inside", F.explode(prefixes("block")).alias("up")).where("up <> block")
    chosen = above.join(room, ["up", "bin"]).where("n - inside >= most or up = ''").groupBy("block", "bin", "most").agg(F.max_by("up", F.length("up")).alias("up"))
    found = chosen.join(up, ["up", "bin"]).where("not startswith(path, block)")
    common = F.size(F.filter(F.sequence(F.lit(1), F.length("block")), lambda i: F.col("path").substr(F.lit(1), i) == F.col("block").substr(F.lit(1), i)))
    ordered = found.select("block", "bin", "most", F.struct((-common).alias("near"), "v").alias("w")).groupBy("block", "bin", "most").agg(F.sort_array(F.collect_list("w")).alias("w"))
    lists = ordered.select("block", "bin", F.slice(F.transform("w", lambda x: x["v"]), F.lit(1), F.col("most")).alias("w"))
    more = short.join(lists, ["block", "bin"]).select("u", F.slice("w", F.lit(1), F.col("r")).alias("w")).groupBy("u").agg(F.flatten(F.collect_list("w")).alias("more"))
    none = F.array().cast("array<long>")
    return pools.join(more, "u", "full").select("u", F.sort_array(F.concat(F.coalesce("pool", none), F.coalesce("more", none))).alias("pool"))


def exact_pool(adjacency: DataFrame) -> DataFrame:
    """(u, pool) of true neighbours: what a perfect guess would hold."""
    return adjacency.select(F.col("v").alias("u"), F.col("nbrs").alias("pool"))


def jump_precision(pools: DataFrame, edges: DataFrame) -> DataFrame:
    """Pooled and mean precision and recall of pools against true neighbours, and vertices without a pool, in one row."""
    held = pools.select("u", F.explode("pool").alias("w"))
    right = held.join(edges.select(F.col("v").alias("u"), F.col("u").alias("w")), ["u", "w"], "left_semi").groupBy("u").agg(F.count("*").alias("hit"))
    deg = edges.groupBy(F.col("v").alias("u")).agg(F.count("*").alias("deg"))
    each = deg.join(pools.select("u", F.size("pool").alias("n")), "u", "left").join(right, "u", "left").na.fill(0)
    mean = F.avg(F.when(F.col("n") > 0, F.col("hit") / F.col("n")))
    return each.agg(
        F.round(F.sum("hit") / F.sum("n"), 6).alias("precision"), F.round(F.sum("hit") / F.sum("deg"), 6).alias("recall"),
        F.round(mean, 6).alias("mean_precision"), F.count_if(F.col("n") == 0).alias("empty_pools"),
    )
