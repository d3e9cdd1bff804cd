"""Alignment dissimilarity of ordered degree matrices: dynamic time warping with L1 row distance.

The kernel takes many pairs at once, diagonal by diagonal: cells of a diagonal need none of one another, and with the pairs
on the last axis they are one run of memory. Pairs of like shape go together, so little is padded. One matrix against many
goes row by row, by a cumulative sum and a running minimum.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veilwalk.functions.vectors import align_cost, total

#: Columns of all pairs of a batch with a band, which a step works on, and numbers of their left matrices.
STEP, CELLS = 1 << 15, 1 << 22
#: Cells of the longest diagonal of all pairs of a batch: what a step works on stays in a core's own memory.
DIAGONAL = 1 << 14
#: Matrices of a batch differ in rows by this factor at most.
LIKE = 1.3
#: The same for stacks, which every left matrix meets whole.
STACK_LIKE = 1.5
#: Share of a stack below which those wanted are copied; else all are aligned, which takes less time than a copy.
COPIED = 0.4


def align_many(left: list[np.ndarray], right: list[np.ndarray], one_sided: bool = False, band: int | None = None) -> np.ndarray:
    """Costs of pairs of matrices (rows by bins)."""
    out = np.zeros(len(left))
    if one_sided:  # the longer matrix leads
        left, right = zip(*((a, b) if len(a) >= len(b) else (b, a) for a, b in zip(left, right, strict=True)), strict=True) if left else ((), ())
    sizes = np.array([(len(b), len(a)) for a, b in zip(left, right, strict=True)]).reshape(-1, 2)
    if not len(sizes):
        return out
    kinds = (np.log(sizes) / np.log(LIKE)).astype(np.int64)
    order = np.lexsort((sizes[:, 1], sizes[:, 0], kinds[:, 1], kinds[:, 0]))
    cuts = np.flatnonzero((np.diff(kinds[order], axis=0) != 0).any(1)) + 1
    for run in np.split(order, cuts):
        y, x = sizes[run].max(0)
        if band is None:
            n = max(1, DIAGONAL // int(min(x, y)))
        else:
            n = max(1, min(STEP // int(y), CELLS // int(x * left[0].shape[1])))
        for chosen in np.array_split(run, -(-len(run) // n)):  # even, since a small rest costs as much as a full batch
            both = [left[i] for i in chosen], [right[i] for i in chosen]
            out[chosen] = _diagonals(*both, one_sided) if band is None else _batch(*both, one_sided, band)
    return out


def _diagonals(left: list[np.ndarray], right: list[np.ndarray], one_sided: bool) -> np.ndarray:
    """Costs of pairs. A diagonal pairs ascending rows on the left with descending ones on the right, so both are slices."""
    x, y, k, n = max(map(len, left)), max(map(len, right)), left[0].shape[1], len(left)
    a, b = np.zeros((k, x, n)), np.zeros((k, y, n))
    for i, (p, q) in enumerate(zip(left, right, strict=True)):
        a[:, : len(p), i], b[:, y - len(q) :, i] = p.T, q[::-1].T
    nx, ny = np.array([len(p) for p in left]), np.array([len(q) for q in right])
    ends = {d: np.flatnonzero(nx + ny - 2 == d) for d in set((nx + ny - 2).tolist())}
    older, old, new = np.full((3, x + 1, n), np.inf)  # place 0 is before the first row
    older[0] = 0
    cost, least, gaps = *np.empty((2, min(x, y), n)), np.empty((k, min(x, y), n))
    out = np.zeros(n)
    for d in range(max(ends) + 1):
        lo, hi = max(0, d - y + 1), min(x, d + 1)
        s, low, g, t = cost[: hi - lo], least[: hi - lo], gaps[:, : hi - lo], y - 1 - d
        np.abs(np.subtract(a[:, lo:hi], b[:, t + lo : t + hi], out=g), out=g)
        np.add.reduce(g, axis=0, out=s)
        np.minimum(older[lo:hi], old[lo:hi], out=low)
        if not one_sided:
            np.minimum(low, old[lo + 1 : hi + 1], out=low)
        np.add(s, low, out=new[lo + 1 : hi + 1])
        if d in ends:
            out[ends[d]] = new[nx[ends[d]], ends[d]]
        older[0] = np.inf
        older, old, new = old, new, older
    return out


def _batch(left: list[np.ndarray], right: list[np.ndarray], one_sided: bool, band: int | None) -> np.ndarray:
    x, y, k = max(map(len, left)), max(map(len, right)), left[0].shape[1]
    a, b = np.zeros((len(left), x, k)), np.zeros((len(left), y, k))
    for i, (p, q) in enumerate(zip(left, right, strict=True)):
        a[i, : len(p)], b[i, : len(q)] = p, q
    nx, ny = np.array([len(p) for p in left]), np.array([len(q) for q in right])
    before = np.full((len(left), y + 1), np.inf)
    before[:, 0] = 0
    out = np.zeros(len(left))
    columns, gap = np.ascontiguousarray(b.transpose(2, 0, 1)), np.empty((len(left), y))  # one bin at a time, without a third axis
    for i in range(x):
        cost = np.abs(a[:, i, 0, None] - columns[0])
        for c in range(1, k):
            np.subtract(a[:, i, c, None], columns[c], out=gap)
            np.abs(gap, out=gap)
            cost += gap
        if band is not None:  # columns near the diagonal of each pair
            away = np.abs(np.arange(y)[None, :] * (np.maximum(nx - 1, 1) / np.maximum(ny - 1, 1))[:, None] - i)
            cost = np.where(away <= np.maximum(band, np.abs(nx - ny) / np.maximum(ny - 1, 1) + 1)[:, None], cost, np.inf)
        least = np.minimum(before[:, :-1], before[:, 1:])
        now = np.full((len(left), y + 1), np.inf)
        if one_sided:
            now[:, 1:] = cost + least
        elif band is None:
            run = np.cumsum(cost, axis=1)
            now[:, 1:] = np.minimum.accumulate(least - (run - cost), axis=1) + run
        else:
            for j in range(y):
                now[:, j + 1] = cost[:, j] + np.minimum(least[:, j], now[:, j])
        before = now
        ends = nx == i + 1
        out[ends] = now[ends, ny[ends]]
    return out


class Stacks:
    """Matrices in a given order, like numbers of rows side by side, to align one of them with many at a time. Equal ones are held once."""

    def __init__(self, matrices: list[np.ndarray], one_sided: bool = False, band: int | None = None):
        self.matrices, self.options, self.groups = matrices, (one_sided, band), []
        self.n, found = len(matrices), {}
        self.own = np.array([found.setdefault(m.tobytes(), len(found)) for m in matrices], np.int64)
        once = [matrices[i] for i in np.unique(self.own, return_index=True)[1]]
        n = np.array([len(m) for m in once])
        self.first, self.last = (np.array([m[i] for m in once]).T.copy() for i in (0, -1))
        self.alone, self.latest = n == 1, (-1, n)
        kinds = (np.log(n) / np.log(STACK_LIKE)).astype(np.int64)
        for kind in np.unique(kinds):
            at = np.flatnonzero(kinds == kind)
            held = np.zeros((matrices[0].shape[1], len(at), n[at].max()))
            for i, x in enumerate(at):
                held[:, i, : n[x]] = once[x].T
            self.groups.append((at, n[at], held))

    def row(self, i: int, wanted: np.ndarray | None = None) -> np.ndarray:
        """Costs of matrix i to all others or those wanted (a mask); 0 elsewhere and to itself.

        With a band or one side costs depend on which matrix is on the left: the earlier one, as in pairs_within().
        """
        if any(x not in (None, False) for x in self.options):
            out = np.zeros(self.n)
            at = np.arange(self.n) if wanted is None else np.flatnonzero(wanted)
            out[at] = align_many([self.matrices[min(i, x)] for x in at], [self.matrices[max(i, x)] for x in at], *self.options)
        elif wanted is None and self.latest[0] == self.own[i]:  # equal matrices have one row
            out = self.latest[1][self.own]
        else:
            once, asked = np.zeros(len(self.alone)), np.ones(len(self.alone), bool)
            if wanted is not None:
                asked[:] = False
                asked[self.own[wanted]] = True
            for at, n, held in self.groups:
                some = asked[at]
                if not some.any():
                    continue
                if some.mean() < COPIED:
                    at, n, held = at[some], n[some], held[:, some]
                once[at] = _one_to_many(self.matrices[i], held, n)
            if wanted is None:
                self.latest = self.own[i], once
            out = once[self.own]
            if wanted is not None:
                out[~wanted] = 0.0
        out[i] = 0.0
        return out

    def floor(self, i: int) -> np.ndarray:
        """A bound below the costs of matrix i to all: the first rows and the last ones are always paired."""
        m = self.matrices[i]
        ends = np.zeros(len(self.alone))
        for x, column in zip(m[-1], self.last, strict=True):
            ends += np.abs(x - column)
        if len(m) == 1:
            ends[self.alone] = 0.0  # there one pair is both
        for x, column in zip(m[0], self.first, strict=True):
            ends += np.abs(x - column)
        return ends[self.own]


def _one_to_many(m: np.ndarray, held: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Costs of m to matrices held (bins by matrices by rows, of n rows each), step by step as in _batch(). One row meets all rows of the other."""
    if len(m) == 1 or held.shape[2] == 1:
        out = np.zeros(len(n))
        for row in m:
            cost = np.abs(row[0] - held[0])
            for x, column in zip(row[1:], held[1:], strict=True):
                gap = x - column
                cost += np.abs(gap, out=gap)
            out += cost[:, 0] if held.shape[2] == 1 else np.cumsum(cost, axis=1)[np.arange(len(n)), n - 1]
        return out
    before, now = np.full((2, len(n), held.shape[2] + 1), np.inf)
    before[:, 0] = 0
    cost, gap = np.empty((2, len(n), held.shape[2]))
    for row in m:
        np.abs(np.subtract(row[0], held[0], out=cost), out=cost)
        for x, column in zip(row[1:], held[1:], strict=True):
            cost += np.abs(np.subtract(x, column, out=gap), out=gap)
        least = np.minimum(before[:, :-1], before[:, 1:])
        run = np.cumsum(cost, axis=1)
        least -= run - cost
        np.add(np.minimum.accumulate(least, axis=1, out=least), run, out=now[:, 1:])
        now[:, 0] = np.inf
        before, now = now, before
    return before[np.arange(len(n)), n]


class Held:
    """Matrices of all vertices in the order of ids, dealt to every task: rows of the square of dissimilarities are made there."""

    def __init__(self, matrices: DataFrame, one_sided: bool = False, band: int | None = None):
        self.spark = matrices.sparkSession
        t = matrices.select("v", F.flatten("m").cast("array<double>").alias("flat"), F.size("m").cast("long").alias("rows")).toArrow().sort_by("v").combine_chunks()
        self.ids = t["v"].to_numpy()
        self.n, self.parts = len(self.ids), max(1, min(wide(self.spark), len(self.ids)))
        flat = t["flat"].combine_chunks()
        lists = rows_of(flat.combine_chunks() if isinstance(flat, pa.ChunkedArray) else flat, t["rows"].to_numpy()) if self.n else []
        self.shared = self.spark.sparkContext.broadcast((self.ids, lists, one_sided, band))

    def rows(self) -> DataFrame:
        """(id): places of all vertices in the order of ids."""
        return self.spark.range(0, self.n, 1, self.parts)

    def triangle(self) -> DataFrame:
        """(at, cells): for each place the dissimilarities to all later places, as doubles."""
        shared = self.shared

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            stacks, every = stacks_of(shared), np.arange(len(shared.value[0]))
            for b in batches:
                for i in b.column(0).to_pylist():
                    row = stacks.row(i, every > i)[i + 1 :]
                    yield pa.RecordBatch.from_arrays([pa.array([i]), pa.array([row.tobytes()], pa.binary())], names=["at", "cells"])

        mixed = F.when(F.col("id") % 2 == 0, F.expr("id div 2")).otherwise(self.n - 1 - F.expr("id div 2"))  # early places have long rows
        return self.rows().select(mixed.alias("id")).mapInArrow(run, "at long, cells binary")


#: The stacks that a worker made last, for the value they stand for: its next tasks take them again.
_MADE: list = [None, None]


def stacks_of(shared) -> Stacks:
    if _MADE[0] is not shared.value:
        _MADE[:] = [shared.value, Stacks(*shared.value[1:])]
    return _MADE[1]


def lower_bound(a: np.ndarray, b: np.ndarray) -> float:
    """A bound that no path beats: both corners are on it, and each row meets some row."""
    d = np.abs(a[:, None, :] - b[None, :, :]).sum(2)
    corners = d[0, 0] + (d[-1, -1] if d.size > 1 else 0.0)
    return float(max(corners, d.min(1).sum(), d.min(0).sum()))


def rows_of(flat: pa.Array, rows: np.ndarray) -> list[np.ndarray]:
    values = flat.flatten().to_numpy(zero_copy_only=False)
    ends = np.cumsum(flat.value_lengths().to_numpy(zero_copy_only=False))
    return [values[s:e].reshape(r, -1) for s, e, r in zip(np.r_[0, ends[:-1]], ends, rows, strict=True)]


def dissimilarity(matrices: DataFrame, pairs: DataFrame, kernel: str = "arrow", one_sided: bool = False, band: int | None = None, prune_above: float | None = None) -> DataFrame:
    """(u, v, delta) of given pairs. prune_above leaves out pairs that a lower bound shows to be dearer."""
    m = matrices.select("v", "m")
    both = pairs.select("u", "v").join(m.withColumnsRenamed({"v": "u", "m": "mu"}), "u").join(m.withColumnRenamed("m", "mv"), "v")
    if kernel == "expr":
        a, b = F.col("mu"), F.col("mv")
        if one_sided:
            longer = F.size("mu") >= F.size("mv")
            a, b = F.when(longer, a).otherwise(b), F.when(longer, b).otherwise(a)
        return both.select("u", "v", align_cost(a, b, one_sided).alias("delta"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in batches:
            mu, mv = (rows_of(t.column(c), t.column(n).to_numpy()) for c, n in ((2, 4), (3, 5)))
            keep = np.arange(len(mu))
            if prune_above is not None:
                keep = np.array([i for i in keep if lower_bound(mu[i], mv[i]) <= prune_above], np.int64)
            delta = align_many([mu[i] for i in keep], [mv[i] for i in keep], one_sided, band)
            yield pa.RecordBatch.from_arrays([t.column(0).take(pa.array(keep)), t.column(1).take(pa.array(keep)), pa.array(delta)], names=["u", "v", "delta"])

    flat = both.select("u", "v", F.flatten("mu"), F.flatten("mv"), F.size("mu"), F.size("mv")).toDF("u", "v", "a", "b", "na", "nb")
    return flat.mapInArrow(run, "u long, v long, delta double")


def wide(spark) -> int:
    """Partitions of work that is much for its bytes, which Spark would else gather in one task."""
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), 4 * spark.sparkContext.defaultParallelism)


PACKED = "struct<v: bigint, n: int, m: array<double>>"


def pairs_within(matrices: DataFrame, block: str | None = None, size: int = 64, one_sided: bool = False, band: int | None = None) -> DataFrame:
    """(u, v, delta) with u < v of all pairs, or of all pairs with an equal block column.

    Vertices are packed into chunks; a task aligns two chunks, so matrices travel once for each chunk they meet.
    """
    group = [] if block is None else [block]
    chunk = F.pmod(F.xxhash64("v"), F.greatest(F.lit(1), F.ceil(F.col("_n") / size)))
    n = matrices.groupBy(*group).agg(F.count("*").alias("_n"), )
    sized = matrices.join(n, group) if group else matrices.crossJoin(F.broadcast(n))  # one row
    packed = sized.withColumn("_c", chunk).groupBy(*group, "_c", F.ceil(F.col("_n") / size).alias("_k")).agg(F.collect_list(F.struct("v", F.size("m").alias("n"), F.flatten("m").alias("m"))).alias("rows"))
    meet = packed.withColumn("_o", F.explode(F.sequence(F.lit(0).cast("long"), F.greatest(F.lit(0), F.col("_k") - 1).cast("long"))))
    meet = meet.select(*group, F.least("_c", "_o").alias("i"), F.greatest("_c", "_o").alias("j"), F.col("_c").alias("own"), "rows")
    meet = meet.repartition(wide(matrices.sparkSession), *group, "i", "j")

    def work(t: pa.Table) -> pa.Table:
        parts = {}
        for own, rows in zip(t["own"].to_pylist(), t["rows"].to_pylist(), strict=True):
            parts[own] = [(r["v"], np.array(r["m"]).reshape(r["n"], -1)) for r in rows]
        i, j = t["i"][0].as_py(), t["j"][0].as_py()
        if i not in parts or j not in parts:
            pairs = []
        elif i == j:
            one = sorted(parts[i], key=lambda x: x[0])
            pairs = [(a, b) for k, a in enumerate(one) for b in one[k + 1 :]]
        else:
            pairs = [(a, b) if a[0] < b[0] else (b, a) for a in parts[i] for b in parts[j]]
        delta = align_many([a[1] for a, _ in pairs], [b[1] for _, b in pairs], one_sided, band)
        ids = [pa.array([x[0] for x, _ in pairs], pa.int64()), pa.array([y[0] for _, y in pairs], pa.int64())]
        return pa.table([*ids, pa.array(delta)], names=["u", "v", "delta"])

    return meet.groupBy(*group, "i", "j").applyInArrow(work, "u long, v long, delta double")


def pairs_to(matrices: DataFrame, landmarks: DataFrame) -> DataFrame:
    """(u, v) of each landmark with each vertex. Landmarks are few by contract: at most 64 are taken to every task."""
    if landmarks.limit(65).count() > 64:
        raise ValueError("more than 64 landmarks")
    return matrices.select("v").crossJoin(F.broadcast(landmarks.select(F.col("v").alias("u")))).where("u <> v")


def vector_dissimilarity(vectors: DataFrame, pairs: DataFrame) -> DataFrame:
    """(u, v, delta): L1 distance of the noisy degree vectors; a cheap stand-in for the alignment."""
    c = vectors.select("v", "c")
    both = pairs.select("u", "v").join(c.withColumnsRenamed({"v": "u", "c": "cu"}), "u").join(c.withColumnRenamed("c", "cv"), "v")
    return both.select("u", "v", total(F.zip_with("cu", "cv", lambda x, y: F.abs(x - y))).alias("delta"))


def dissimilarity_error(noisy: DataFrame, clean: DataFrame, matrices: DataFrame, eps: float, k: int) -> DataFrame:
    """(u, v, error, pair_bound, bound): what noise added to each pair, and what it adds at most on average."""
    rows = matrices.select("v", F.greatest(F.lit(1), F.size("nbr_order")).alias("n"))
    top = rows.agg(F.max("n").alias("d"))
    both = noisy.select("u", "v", F.col("delta").alias("a")).join(clean.select("u", "v", F.col("delta").alias("b")), ["u", "v"])
    both = both.join(rows.withColumnsRenamed({"v": "u", "n": "x"}), "u").join(rows.withColumnRenamed("n", "y"), "v").crossJoin(F.broadcast(top))
    unit = 3.0 * k / (2.0 * eps)
    return both.select("u", "v", (F.col("a") - F.col("b")).alias("error"), (unit * (F.col("x") + F.col("y") - 1)).alias("pair_bound"), (unit * F.col("d") * F.col("d")).alias("bound"))


def overlap_dissimilarity(edges: DataFrame) -> DataFrame:
    """(u, v, delta): one minus the topological overlap of pairs that are linked or share a neighbour."""
    deg = edges.groupBy("v").agg(F.count("*").alias("d"))
    mid = edges.select(F.col("u").alias("w"), "v")
    shared = mid.join(mid.withColumnRenamed("v", "u"), "w").where("u < v").groupBy("u", "v").agg(F.count("*").alias("s"))
    linked = edges.where("v < u").select(F.col("v").alias("u"), F.col("u").alias("v"), F.lit(1).alias("a"))
    both = shared.join(linked, ["u", "v"], "full").na.fill(0)
    both = both.join(deg.withColumnsRenamed({"v": "u", "d": "du"}), "u").join(deg.withColumnRenamed("d", "dv"), "v")
    overlap = (F.col("s") + F.col("a")) / (F.least("du", "dv") + 1 - F.col("a"))
    return both.select("u", "v", (F.lit(1.0) - overlap).alias("delta"))
