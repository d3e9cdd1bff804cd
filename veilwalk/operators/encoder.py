"""Substitution of emitted vertices by an exponential mechanism scored by dissimilarity and tree distance."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from veilwalk.functions.draws import unit
from veilwalk.operators.align import Held, stacks_of
from veilwalk.operators.tree import PAIRS_LIMIT, LeafOrder, lca_sizes, shared_leaves, square
from veilwalk.plans.lineage import Store, positions

LAW = "v long, w long, pr double"


def walk_score(delta: Column, leaves: Column) -> Column:
    """Minus dissimilarity times the leaves of the lowest common subtree; 0 for a vertex and itself."""
    return -delta * leaves


def exponential_mechanism(df: DataFrame, group: str, score: str, eps: float, base: str | None = None, scale: float = 1.0, calibrated: float | None = None) -> DataFrame:
    """df with pr: within each group, proportional to base times exp(eps * score / scale).

    calibrated is a sensitivity: the textbook factor eps / (2 * sensitivity) then takes the place of eps.
    """
    factor = eps / scale if calibrated is None else eps / (2.0 * calibrated)
    top = Window.partitionBy(group)
    w = F.exp(F.lit(factor) * (F.col(score) - F.max(score).over(top)))
    if base is not None:
        w = w * F.col(base)
    weighted = df.withColumn("_w", w)
    return weighted.withColumn("pr", F.col("_w") / F.sum("_w").over(top)).drop("_w")


def encoder_table(dissim: DataFrame, leaves: DataFrame, eps: float, scale: float = 1.0, calibrated: float | None = None, exact_limit: int = PAIRS_LIMIT) -> DataFrame:
    """(v, targets, cdf): the exact law over all vertices from their pairs, one array row for each vertex; refuses large graphs."""
    if leaves.count() > exact_limit:
        raise ValueError("too many vertices for the exact law; use held_table or pruned_table")
    return _tables(dissim, leaves, F.lit(0), eps, scale, calibrated, None).drop("lost_mass")


#: exp(-x) is 0 from 745.14 on.
NOTHING = 750.0


def _held_laws(batches: Iterator[pa.RecordBatch], held, order, factor: float) -> Iterator[tuple[int, np.ndarray]]:
    """(place, pr) for the places in batches: the exact law over all vertices in the order of ids.

    Alignments whose weight is 0 by a bound below them are not made.
    """
    stacks = stacks_of(held)
    for b in batches:
        for i in b.column(0).to_pylist():
            leaves = shared_leaves(order.value, i)
            far = factor * stacks.floor(i) * leaves > NOTHING
            w = np.where(far, 0.0, np.exp(-factor * stacks.row(i, ~far) * leaves))
            yield i, w / w.sum()


def held_law(held: Held, leaves: DataFrame, factor: float, least: float) -> DataFrame:
    """(v, w, pr) of at least that probability under the exact law, at any size and without a table of pairs."""
    shared, order = held.shared, LeafOrder(leaves, held).shared

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = shared.value[0]
        for i, pr in _held_laws(batches, shared, order, factor):
            some = np.flatnonzero(pr >= least)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(some), ids[i])), pa.array(ids[some]), pa.array(pr[some])], names=["v", "w", "pr"])

    return held.rows().mapInArrow(run, "v long, w long, pr double")


def held_table(held: Held, leaves: DataFrame, factor: float) -> DataFrame:
    """(v, targets, cdf) of the exact law, without targets that no draw can hit: the sum does not grow there."""
    shared, order = held.shared, LeafOrder(leaves, held).shared

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = shared.value[0]
        for i, pr in _held_laws(batches, shared, order, factor):
            cdf = np.cumsum(pr)
            grows = np.diff(cdf, prepend=0.0) > 0
            grows[-1] = True  # stands for draws above all sums
            one = lambda x: pa.ListArray.from_arrays(pa.array([0, len(x)], pa.int32()), pa.array(x))
            yield pa.RecordBatch.from_arrays([pa.array([ids[i]]), one(ids[grows]), one(cdf[grows])], names=["v", "targets", "cdf"])

    return held.rows().mapInArrow(run, "v long, targets array<long>, cdf array<double>")


def pruned_table(dissim: DataFrame, leaves: DataFrame, block: Column, n: int, eps: float, scale: float = 1.0, calibrated: float | None = None, matrices: DataFrame | None = None) -> DataFrame:
    """(v, targets, cdf, lost_mass): the law within blocks of the tree (equal values of block, a prefix of path).

    lost_mass is at least what the exact law gives to vertices outside the block. With matrices it follows from
    outside_weight, which bounds every dissimilarity to the outside from below; without them nothing is known of the
    outside and it is the bound for outside vertices at no distance at all. Vertices outside have no probability here, so
    this law has no bound on its ratios between vertices of different blocks; with_outside gives it one.
    """
    outside = None
    if matrices is not None:
        outside = outside_weight(matrices, leaves.select("v", "path", block.alias("block")), factor_of(eps, scale, calibrated))
    return _tables(dissim, leaves, block, eps, scale, calibrated, n, outside)


def factor_of(eps: float, scale: float = 1.0, calibrated: float | None = None) -> float:
    return eps / scale if calibrated is None else eps / (2.0 * calibrated)


def outside_weight(matrices: DataFrame, leaves: DataFrame, factor: float) -> DataFrame:
    """(v, outside): no less than the sum, over vertices outside v's block, of what the exact law weighs them with.

    leaves has v, path and block. The outside of a block is the siblings of the nodes above it. All vertices of a sibling
    share their lowest common subtree with v, the sibling's parent. Their dissimilarity to v is bounded from below by boxes
    around the rows of their matrices: an alignment pairs first rows, last rows, and each row of v with some row.
    """
    first, last = F.element_at("m", 1), F.element_at("m", -1)
    bound = lambda pick: F.aggregate("m", first, lambda s, r: F.zip_with(s, r, lambda x, y: pick(x, y)))
    boxes = matrices.select("v", F.posexplode(F.arrays_zip(first.alias("f"), last.alias("l"), bound(F.least).alias("lo"), bound(F.greatest).alias("hi"))).alias("bin", "x"))
    placed = leaves.join(boxes, "v").select("block", "bin", "x.*")
    spans = [F.min("f").alias("f0"), F.max("f").alias("f1"), F.min("l").alias("l0"), F.max("l").alias("l1"), F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.count("*").alias("n")]
    per_block = placed.groupBy("block", "bin").agg(*spans)
    prefixes = F.transform(F.sequence(F.lit(0), F.length("block")), lambda i: F.col("block").substr(F.lit(1), i))
    merged = [F.min("f0").alias("f0"), F.max("f1").alias("f1"), F.min("l0").alias("l0"), F.max("l1").alias("l1"), F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.sum("n").alias("n")]
    node = per_block.select("bin", "f0", "f1", "l0", "l1", "lo", "hi", "n", F.explode(prefixes).alias("node")).groupBy("node", "bin").agg(*merged)
    node = node.groupBy("node").agg(F.sort_array(F.collect_list(F.struct("bin", "f0", "f1", "l0", "l1", "lo", "hi"))).alias("box"), F.max("n").alias("n"))
    turn = F.when(F.expr("substr(block, d, 1)") == "0", "1").otherwise("0")
    beside = per_block.select("block").distinct().where("block <> ''").select("block", F.explode(F.sequence(F.lit(1), F.length("block"))).alias("d"))
    beside = beside.select("block", F.expr("substr(block, 1, d - 1)").alias("up"), F.concat(F.expr("substr(block, 1, d - 1)"), turn).alias("node"))
    sizes = node.select(F.col("node").alias("up"), F.col("n").alias("above"))
    beside = beside.join(node, "node").join(sizes, "up").select(F.col("block").alias("of"), "above", "n", "box")
    own = leaves.join(matrices.select("v", "m"), "v").select("block", "v", F.flatten("m").alias("flat"), F.size("m").alias("rows"))

    def work(mine: pd.DataFrame, others: pd.DataFrame) -> pd.DataFrame:
        out = np.zeros(len(mine))
        for box, n, above in zip(others["box"], others["n"], others["above"], strict=True):
            f0, f1, l0, l1, lo, hi = (np.array([b[c] for b in box]) for c in ("f0", "f1", "l0", "l1", "lo", "hi"))
            away = lambda x, low, high: (np.maximum(low - x, 0) + np.maximum(x - high, 0)).sum(-1)
            for i, (flat, rows) in enumerate(zip(mine["flat"], mine["rows"], strict=True)):
                m = np.asarray(flat, float).reshape(int(rows), -1)
                least = max(away(m[0], f0, f1), away(m[0], l0, l1)) if rows == 1 else away(m[0], f0, f1) + away(m[-1], l0, l1) + away(m[1:-1], lo, hi).sum()
                out[i] += n * np.exp(-factor * max(least - 1e-9, 0.0) * above)
        return pd.DataFrame({"v": mine["v"], "outside": out})

    return own.groupBy("block").cogroup(beside.groupBy("of")).applyInPandas(work, "v long, outside double")


def with_outside(table: DataFrame, n: int) -> DataFrame:
    """Block laws with their lost mass spread evenly over all n vertices; a draw of the null target stands for one of them.

    Every vertex then has a probability of at least lost_mass / n for every other, which bounds the ratios.
    """
    share = 1 - F.col("lost_mass")
    return table.select(
        "v", F.concat("targets", F.array(F.lit(None).cast("long"))).alias("targets"),
        F.concat(F.transform("cdf", lambda c: c * share), F.array(F.lit(1.0))).alias("cdf"), "lost_mass", F.lit(n).alias("n"),
    )


def _tables(dissim: DataFrame, leaves: DataFrame, block: Column, eps: float, scale: float, calibrated: float | None, n: int | None, outside: DataFrame | None = None) -> DataFrame:
    factor = factor_of(eps, scale, calibrated)
    at = leaves.select("v", "path", block.alias("block"))
    far = at.select("v", "block").withColumn("outside", F.lit(None).cast("double")) if outside is None else at.select("v", "block").join(outside, "v", "left")
    own = at.join(far.select("v", "outside"), "v").select("block", F.col("v").alias("u"), "v", "path", F.lit(0.0).alias("delta"), "outside")
    sides = at.select("v", "block")
    inner = dissim.select("u", "v", "delta").join(sides, "v").join(sides.withColumnsRenamed({"v": "u", "block": "other"}), "u").where("block = other")
    rows = own.unionByName(inner.select("block", "u", "v", F.lit(None).cast("string").alias("path"), "delta", F.lit(None).cast("double").alias("outside")))

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        one = pdf[pdf["path"].notna()].sort_values("v")
        ids, pairs = one["v"].to_numpy(), pdf[pdf["path"].isna()]
        d = square(ids, pairs["u"].to_numpy(), pairs["v"].to_numpy(), pairs["delta"].to_numpy())
        w = np.exp(-factor * d * lca_sizes(one["path"].tolist()))
        lost = np.zeros(len(ids))
        if n is not None and n > len(ids):
            beyond = one["outside"].fillna(n - len(ids)).to_numpy()
            lost = beyond / (beyond + w.sum(1))
        cdf = np.cumsum(w / w.sum(1, keepdims=True), axis=1)
        return pd.DataFrame({"v": ids, "targets": [ids] * len(ids), "cdf": list(cdf), "lost_mass": lost})

    return rows.groupBy("block").applyInPandas(work, "v long, targets array<long>, cdf array<double>, lost_mass double")


def law_rows(table: DataFrame) -> DataFrame:
    """(v, w, pr) from array rows."""
    z = table.select("v", F.posexplode("targets").alias("i", "w"), "cdf")
    at = F.element_at("cdf", F.col("i") + 1)
    return z.select("v", "w", (at - F.when(F.col("i") > 0, F.try_element_at("cdf", F.col("i"))).otherwise(0.0)).alias("pr"))


def as_table(law: DataFrame) -> DataFrame:
    """(v, targets, cdf) from (v, w, pr), in the order of w."""
    running = F.sum("pr").over(Window.partitionBy("v").orderBy("w").rowsBetween(Window.unboundedPreceding, 0))
    rows = law.select("v", "w", running.alias("c")).groupBy("v").agg(F.sort_array(F.collect_list(F.struct("w", "c"))).alias("r"))
    return rows.select("v", F.transform("r", lambda x: x["w"]).alias("targets"), F.transform("r", lambda x: x["c"]).alias("cdf"))


def draw(targets: Column, cdf: Column, u: Column) -> Column:
    """The first target whose cumulated probability exceeds u; the last one if rounding leaves u above all.

    A binary search whose state holds u, which is thus computed once for a row.
    """
    def halve(s: Column, _: Column) -> Column:
        mid = F.floor((s["lo"] + s["hi"]) / 2).cast("int")
        above = F.get(cdf, mid) > s["u"]
        open_ = s["lo"] < s["hi"]
        lo = F.when(open_ & ~above, mid + 1).otherwise(s["lo"])
        return F.struct(lo.alias("lo"), F.when(open_ & above, mid).otherwise(s["hi"]).alias("hi"), s["u"].alias("u"))

    start = F.struct(F.lit(0).alias("lo"), F.size(cdf).alias("hi"), u.alias("u"))
    steps = F.sequence(F.lit(0), F.ceil(F.log2(F.size(cdf) + 1)).cast("int"))
    return F.aggregate(steps, start, halve, lambda s: F.get(targets, F.least(s["lo"], F.size(targets) - 1)))


def encode(df: DataFrame, table: DataFrame, column: str, out: str, seed: str, *keys: str, rng: str = "md5") -> DataFrame:
    """df with out: a drawn substitute for the vertex in column. The law is joined by vertex once for all draws.

    Where a block law leaves the draw to all vertices, their number in the order of ids is drawn and looked up.
    """
    law = table.select(F.col("v").alias(column), "targets", "cdf", *(["n"] if "n" in table.columns else []))
    drawn = df.join(law, column).withColumn(out, draw(F.col("targets"), F.col("cdf"), unit(seed, "encode", *keys, rng=rng))).drop("targets", "cdf")
    if "n" not in table.columns:
        return drawn
    numbered = positions(table.select(F.col("v").alias("_w")), Store(df.sparkSession, "outside"), "_w", name="_at")
    asked = drawn.withColumn("_at", F.when(F.col(out).isNull(), F.floor(unit(seed, "outside", *keys, rng=rng) * F.col("n")))).drop("n")
    return asked.join(numbered, "_at", "left").withColumn(out, F.coalesce(out, "_w")).drop("_at", "_w")


def encoder_utility(law: DataFrame) -> DataFrame:
    """Mean probability of keeping a vertex, and of changing it, in one row; with scores in the law their mean under it as well."""
    kept = F.avg(F.when(F.col("v") == F.col("w"), F.col("pr")))
    cells = [F.round(kept, 6).alias("kept"), F.round(1 - kept, 6).alias("changed")]
    if "score" in law.columns:
        cells.append((F.round(F.sum(F.col("pr") * F.col("score")) / F.count_distinct("v"), 6) + F.lit(0.0)).alias("mean_score"))
    return law.agg(*cells)


def encoder_audit(law: DataFrame) -> DataFrame:
    """(w, held, missing, log_ratio): for each output the vertices that may give it, those that never do, and the largest log-ratio among the former.

    An output that some vertices give and others never do tells them apart with certainty; the privacy claim for a walk
    element is that log_ratio stays below the stated epsilon and missing is zero.
    """
    n = law.select("v").distinct().agg(F.count("*").alias("n"))
    held = law.where("pr > 1e-300").groupBy("w").agg(F.count("*").alias("held"), F.max("pr").alias("top"), F.min("pr").alias("low"))
    return held.crossJoin(F.broadcast(n)).select("w", "held", (F.col("n") - F.col("held")).alias("missing"), F.round(F.log("top") - F.log("low"), 6).alias("log_ratio"))  # one row of n
