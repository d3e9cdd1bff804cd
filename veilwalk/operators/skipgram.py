"""Vertex vectors from walks by skip-gram."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veilwalk.functions.vectors import cosine
from veilwalk.operators.align import wide
from veilwalk.plans.lineage import Store

#: Numbers that MLlib's trainer can hold.
DRIVER_FLOATS = 1 << 31
#: Numbers of one block of vectors in block training, and occurrences of pairs laid out at once.
BLOCK_FLOATS, EVENTS = 1 << 22, 1 << 22


def skipgram(walks: DataFrame, dim: int, window: int, seed: int = 1, iterations: int = 1, partitions: int = 1) -> DataFrame:
    """(v, vec) by MLlib's trainer, which keeps all vectors on the driver; larger vocabularies need skipgram_blocks."""
    from pyspark.ml.feature import Word2Vec
    from pyspark.ml.functions import vector_to_array

    words = walks.select(F.transform("seq", lambda x: x.cast("string")).alias("seq"))
    n = walks.select(F.explode("seq").alias("v")).agg(F.approx_count_distinct("v")).first()[0]
    if n * dim > DRIVER_FLOATS // 2:
        raise ValueError("too many vertices for the driver; use skipgram_blocks")
    trainer = Word2Vec(vectorSize=dim, windowSize=window, minCount=0, seed=seed, maxIter=iterations, numPartitions=partitions, inputCol="seq", outputCol="vec", stepSize=0.05)
    found = trainer.fit(words).getVectors()
    return found.select(F.col("word").cast("long").alias("v"), vector_to_array("vector", "float32").alias("vec"))


def block_count(vertices: int, dim: int) -> int:
    """Blocks of at most BLOCK_FLOATS numbers, four at least."""
    return max(4, -(-vertices * dim // BLOCK_FLOATS))


def skipgram_blocks(cooc: DataFrame, dim: int, blocks: int | None = None, epochs: int = 3, negatives: int = 5, rate: float = 0.1, seed: int = 1) -> DataFrame:
    """(v, vec) from co-occurrence counts (a, b, n), by block-parallel training with negative samples.

    Source and context vectors are tables of blocks. In each of an epoch's rounds every task trains one source block
    against one context block, none of which another task holds; blocks are written between epochs. A pair is trained on
    as often as it occurs. The number of blocks follows from that of vertices unless given.
    """
    store = Store(cooc.sparkSession, "skipgram")
    if blocks is None:
        n = cooc.select("a").union(cooc.select("b")).agg(F.approx_count_distinct("a")).first()[0]
        blocks = block_count(n, dim)
    place = lambda c: F.pmod(F.xxhash64(c), F.lit(blocks)).cast("int")
    pairs = store.keep(cooc.select("a", "b", "n", place("a").alias("i"), place("b").alias("j")))
    ids = pairs.select(F.col("a").alias("v")).union(pairs.select(F.col("b").alias("v"))).distinct()

    def fresh(side: int):
        def make(batches):
            for pdf in batches:
                vecs = [((np.random.default_rng([seed, side, int(v)]).random(dim) - 0.5) / dim) for v in pdf["v"]]
                yield pd.DataFrame({"v": pdf["v"], "vec": vecs})

        return ids.mapInPandas(make, "v long, vec array<double>").withColumn("b", place("v"))

    source, context = store.keep(fresh(0)), store.keep(fresh(1))
    none = F.array().cast("array<double>")  # null arrays take Spark's Arrow writer many times as long as empty ones
    for epoch in range(epochs):
        for shift in range(blocks):
            meets = (F.col("i") + shift) % blocks
            todo = pairs.where(F.col("j") == meets).select("i", F.lit(0).alias("kind"), "a", "b", F.col("n").cast("double").alias("n"), none.alias("vec"))
            s = source.select(F.col("b").alias("i"), F.lit(1).alias("kind"), F.col("v").alias("a"), F.lit(0).cast("long").alias("b"), F.lit(0.0).alias("n"), "vec")
            c = context.select(F.pmod(F.col("b") - shift, F.lit(blocks)).alias("i"), F.lit(2).alias("kind"), F.col("v").alias("a"), F.lit(0).cast("long").alias("b"), F.lit(0.0).alias("n"), "vec")
            train = _trainer(rate / (1 + epoch), [seed, epoch, shift], dim, negatives)
            met = todo.union(s).union(c).repartition(wide(cooc.sparkSession), "i")  # few rows, which Spark would else gather in one task
            moved = store.keep(met.groupBy("i").applyInArrow(train, "kind int, v long, vec array<double>"))
            source = moved.where("kind = 1").select("v", "vec").withColumn("b", place("v"))
            context = moved.where("kind = 2").select("v", "vec").withColumn("b", place("v"))
    return source.select("v", F.transform("vec", lambda x: x.cast("float")).alias("vec"))


def _trainer(step: float, seeds: list[int], dim: int, negatives: int):
    """Trains the vectors of one source and one context block on the pairs between them."""

    def vectors(t: pa.Table) -> tuple[np.ndarray, np.ndarray]:
        """Sorted ids, and their vectors as rows."""
        t = t.sort_by("a").combine_chunks()
        return t["a"].to_numpy(), t["vec"].combine_chunks().flatten().to_numpy().reshape(-1, dim).copy()

    def train(t: pa.Table) -> pa.Table:
        (sid, x), (cid, y) = (vectors(t.filter(pc.equal(t["kind"], k))) for k in (1, 2))
        p = t.filter(pc.equal(t["kind"], 0)).sort_by([("a", "ascending"), ("b", "ascending")])
        if len(p) and len(x) and len(y):
            i, j, n = np.searchsorted(sid, p["a"].to_numpy()), np.searchsorted(cid, p["b"].to_numpy()), p["n"].to_numpy()
            rng, cells = np.random.default_rng([*seeds, len(p)]), np.arange(dim)
            flat = lambda rows: (rows[:, None] * dim + cells).ravel()  # noqa: E731 - numpy adds at single cells many times faster than at rows
            for part in _events(n.astype(np.int64), rng, min(256, max(8, len(x) // 2))):
                for target, cols in [(1.0, j[part]), *[(0.0, rng.integers(0, len(y), len(part))) for _ in range(negatives)]]:
                    a, b = x[i[part]], y[cols]
                    g = step * (target - 1 / (1 + np.exp(-np.clip((a * b).sum(1), -30, 30))))
                    np.add.at(x.reshape(-1), flat(i[part]), (g[:, None] * b).ravel())
                    np.add.at(y.reshape(-1), flat(cols), (g[:, None] * a).ravel())
        kinds, ends = np.repeat([1, 2], [len(sid), len(cid)]).astype(np.int32), np.arange(len(sid) + len(cid) + 1, dtype=np.int32) * dim
        vecs = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([x, y]).ravel()))
        return pa.table([pa.array(kinds), pa.array(np.r_[sid, cid].astype(np.int64)), vecs], names=["kind", "v", "vec"])

    return train


def _events(n: np.ndarray, rng: np.random.Generator, size: int):
    """Batches of pair indices in random order, each pair as often as it counts; only EVENTS of them are laid out at once."""
    order = rng.permutation(len(n))
    ends = np.cumsum(n[order])
    at = 0
    while at < len(order):
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + EVENTS, "right")))
        held = n[order[at:to]].copy()
        while held.any():  # a pair of more than EVENTS occurrences is laid out in several turns
            now = np.minimum(held, max(1, EVENTS // len(held)) if held.sum() > EVENTS else held)
            events = rng.permutation(np.repeat(order[at:to], now))
            yield from (events[k : k + size] for k in range(0, len(events), size))
            held -= now
        at = to


def lookup(embedding: DataFrame, vertices: DataFrame) -> DataFrame:
    return vertices.join(embedding, "v")


def most_similar(embedding: DataFrame, v: int, n: int = 10) -> DataFrame:
    """(v, similarity): the n vertices most alike to v, by a top-k that each task cuts down first."""
    one = embedding.where(F.col("v") == v).select(F.col("vec").alias("_q")).limit(1)
    both = embedding.where(F.col("v") != v).crossJoin(F.broadcast(one))
    return both.select("v", F.round(cosine(F.col("vec"), F.col("_q")), 6).alias("similarity")).orderBy(F.desc("similarity"), "v").limit(n)


def distance_fit(embedding: DataFrame, dissim: DataFrame) -> DataFrame:
    """Mean absolute and mean signed difference of vector distance and walk dissimilarity, in one row."""
    e = embedding.select("v", "vec")
    both = dissim.join(e.withColumnsRenamed({"v": "a", "vec": "x"}), "a").join(e.withColumnsRenamed({"v": "b", "vec": "y"}), "b")
    dist = F.sqrt(F.aggregate(F.zip_with("x", "y", lambda p, q: (p - q).cast("double") * (p - q)), F.lit(0.0), lambda s, t: s + t))
    gap = dist - F.col("dissim")
    return both.agg(F.avg(F.abs(gap)).alias("mean_abs"), F.avg(gap).alias("mean_signed"))
