"""The law and the jump pools of the rank tree, whose dissimilarity is the L1 distance of degree vectors.

All ordered pairs are computed, a tile of rows against all vertices at a time, and none is written. Every task holds the
vertices in rank order: an id, a bin and k counts each.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veilwalk.operators.align import wide

#: Pairs of a tile.
TILE = 1 << 20


class Ranks:
    """(v, ordinal, c) of all vertices in the order of ordinals, dealt and held by every task."""

    def __init__(self, ranked: DataFrame, vectors: DataFrame):
        spark = ranked.sparkSession
        t = ranked.join(vectors, "v").select("v", F.col("ordinal").cast("long").alias("ordinal"), F.col("c").cast("array<double>").alias("c")).toArrow()
        order = np.argsort(t["ordinal"].to_numpy())
        self.n = len(order)
        ids = t["v"].to_numpy()[order]
        counts = t["c"].combine_chunks()
        c = counts.flatten().to_numpy(zero_copy_only=False).reshape(self.n, -1)[order] if self.n else np.zeros((0, 1))
        self.shared = spark.sparkContext.broadcast((ids, np.ascontiguousarray(c.T)))
        self.parts = max(1, min(wide(spark), self.n))
        self.spark = spark

    def rows(self) -> DataFrame:
        return self.spark.range(0, self.n, 1, self.parts)


def leaves_of(i: np.ndarray, j: np.ndarray, n: int) -> np.ndarray:
    """Leaves under the lowest common ancestor of ordinals in the rank tree of n leaves."""
    span = np.int64(1) << np.frexp((i ^ j).astype(np.float64))[1].astype(np.int64)
    low = i // span * span
    return np.where(i == j, 1, np.minimum(n, low + span) - low)


def distances(c: np.ndarray, mine: np.ndarray, lo: int = 0, hi: int | None = None) -> np.ndarray:
    """L1 distances of the vertices mine to those from lo to hi, bins added in their order."""
    delta = np.zeros((len(mine), c[0, lo:hi].size))
    for row in c:
        delta += np.abs(row[mine, None] - row[None, lo:hi])
    return delta


def tiles(batches: Iterator[pa.RecordBatch], shared, factor: float) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(ordinals, score, pr) of tiles: probabilities proportional to exp(factor * score), by rows; score is minus distance times leaves."""
    ids, c = shared.value
    n, every = len(ids), np.arange(len(ids))
    step = max(1, TILE // max(1, n))
    for b in batches:
        own = b.column(0).to_numpy()
        for at in range(0, len(own), step):
            mine = own[at : at + step]
            score = -distances(c, mine) * leaves_of(mine[:, None], every[None, :], n)
            w = np.exp(factor * score)  # the largest score is that of a vertex and itself, 0
            yield mine, score, w / w.sum(1, keepdims=True)


def law_rows(ranks: Ranks, factor: float, least: float) -> DataFrame:
    """(v, w, pr) of all pairs of at least that probability."""
    shared = ranks.shared

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = shared.value[0]
        for mine, _, pr in tiles(batches, shared, factor):
            i, j = np.nonzero(pr >= least)
            yield pa.RecordBatch.from_arrays([pa.array(ids[mine[i]]), pa.array(ids[j]), pa.array(pr[i, j])], names=["v", "w", "pr"])

    return ranks.rows().mapInArrow(run, "v long, w long, pr double")


def law_table(ranks: Ranks, factor: float) -> DataFrame:
    """(v, targets, cdf) in the order of targets, without those that no draw can hit: the sum does not grow there."""
    shared = ranks.shared

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = shared.value[0]
        by_id = np.argsort(ids)
        for mine, _, pr in tiles(batches, shared, factor):
            cdf = np.cumsum(pr[:, by_id], axis=1)
            grows = np.diff(cdf, axis=1, prepend=0.0) > 0
            grows[:, -1] = True  # stands for draws above all sums
            i, j = np.nonzero(grows)
            ends = pa.array(np.r_[0, np.cumsum(grows.sum(1))].astype(np.int32))
            targets = pa.ListArray.from_arrays(ends, pa.array(ids[by_id[j]]))
            yield pa.RecordBatch.from_arrays([pa.array(ids[mine]), targets, pa.ListArray.from_arrays(ends, pa.array(cdf[i, j]))], names=["v", "targets", "cdf"])

    return ranks.rows().mapInArrow(run, "v long, targets array<long>, cdf array<double>")


def utility(ranks: Ranks, factor: float) -> DataFrame:
    """Mean probability of keeping a vertex, and of changing it, and the mean score under the law, in one row."""
    shared = ranks.shared

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for mine, score, pr in tiles(batches, shared, factor):
            yield pa.RecordBatch.from_arrays([pa.array(pr[np.arange(len(mine)), mine]), pa.array((pr * score).sum(1))], names=["kept", "score"])

    each = ranks.rows().mapInArrow(run, "kept double, score double")
    kept = F.avg("kept")
    return each.agg(F.round(kept, 6).alias("kept"), F.round(1 - kept, 6).alias("changed"), (F.round(F.sum("score") / F.count("*"), 6) + F.lit(0.0)).alias("mean_score"))


def audit(ranks: Ranks, factor: float) -> DataFrame:
    """(w, held, missing, log_ratio) as encoder_audit() has them."""
    shared = ranks.shared

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = shared.value[0]
        held, top, low = np.zeros(len(ids), np.int64), np.zeros(len(ids)), np.full(len(ids), np.inf)
        for _, _, pr in tiles(batches, shared, factor):
            possible = pr > 1e-300
            held += possible.sum(0)
            np.maximum(top, pr.max(0), out=top)
            np.minimum(low, np.where(possible, pr, np.inf).min(0), out=low)
        some = held > 0
        yield pa.RecordBatch.from_arrays([pa.array(x[some]) for x in (ids, held, top, low)], names=["w", "held", "top", "low"])

    parts = ranks.rows().mapInArrow(run, "w long, held long, top double, low double")
    found = parts.groupBy("w").agg(F.sum("held").alias("held"), F.max("top").alias("top"), F.min("low").alias("low"))
    return found.select("w", "held", (F.lit(ranks.n).cast("long") - F.col("held")).alias("missing"), F.round(F.log("top") - F.log("low"), 6).alias("log_ratio"))


def pools(ranks: Ranks, bins: DataFrame, ranked: DataFrame, wanted: DataFrame) -> DataFrame:
    """(u, pool): of each bin the m nearest by leaves of the common subtree, then distance to nine places, then id, as jump_pool() has them.

    Only the smallest subtree above u whose bins all hold what is wanted is looked at: all beyond it are farther.
    """
    shared = ranks.shared
    kinds = ranked.join(bins.select("v", "bin"), "v").select(F.col("ordinal").cast("long").alias("ordinal"), F.col("bin").cast("long").alias("bin")).toArrow()
    kind = kinds["bin"].to_numpy()[np.argsort(kinds["ordinal"].to_numpy())] - 1
    placed = ranks.spark.sparkContext.broadcast(kind)
    need = wanted.groupBy("u").agg(F.transform(F.array_sort(F.collect_list(F.struct("bin", "m"))), lambda x: x["m"]).alias("need"))
    asked = ranked.select(F.col("v").alias("u"), F.col("ordinal").cast("long").alias("ordinal")).join(need, "u").repartition(ranks.parts, "u")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        (ids, c), kind = shared.value, placed.value
        n, k = len(ids), len(c)
        before = np.zeros((k, n + 1), np.int64)  # vertices of each bin ahead of an ordinal
        for b in range(k):
            np.cumsum(kind == b, out=before[b, 1:])
        for b in batches:
            out, size = [], np.zeros(b.num_rows, np.int64)
            for at, (i, need) in enumerate(zip(b.column(1).to_numpy(), b.column(2).to_pylist(), strict=True)):
                need = np.array(need, np.int64)
                full, span = need + (np.arange(k) == kind[i]) * (need > 0), 1
                while True:
                    lo = i // span * span
                    hi = min(n, lo + span)
                    if hi - lo == n or (before[:, hi] - before[:, lo] >= full).all():
                        break
                    span *= 2
                near = np.arange(lo, hi)
                near = near[near != i]
                delta = np.round(distances(c, np.array([i]), lo, hi)[0][near - lo], 9)
                near = near[np.lexsort((ids[near], delta, leaves_of(np.int64(i), near, n)))]
                chosen = [near[kind[near] == x][: need[x]] for x in np.flatnonzero(need)]
                pool = np.sort(ids[np.concatenate(chosen)]) if chosen else ids[:0]
                out.append(pool)
                size[at] = len(pool)
            some = size > 0
            ends = pa.array(np.r_[0, np.cumsum(size[some])].astype(np.int32))
            yield pa.RecordBatch.from_arrays([b.column(0).filter(pa.array(some)), pa.ListArray.from_arrays(ends, pa.array(np.concatenate(out) if out else np.zeros(0, np.int64)))], names=["u", "pool"])

    return asked.mapInArrow(run, "u long, pool array<long>")
