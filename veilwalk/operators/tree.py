"""Binary cluster trees over vertices.

A tree is given by its leaves: (v, path), path being the turns from the root, '0' left and '1' right. Ordinals follow
the order of paths, a node is a common prefix of paths, and its leaves are an interval of ordinals.
"""

from __future__ import annotations

import bisect
import hashlib
import os
import tempfile
import threading
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from veilwalk.functions.draws import number
from veilwalk.operators.align import Held, align_many, dissimilarity, pairs_within, rows_of, wide
from veilwalk.operators.groups import hybrid_leaves
from veilwalk.plans.lineage import Store, positions

#: Vertices of the exact tree, whose square of distances then takes 137 GB of one task's scratch file.
EXACT_LIMIT = 1 << 17
#: Vertices whose pairs are taken to one task as rows.
PAIRS_LIMIT = 4096
#: Bytes of a square that a task holds in memory; larger ones lie in a scratch file.
SQUARE_BYTES = 1 << 30
#: Numbers in the pivots' matrices of one level of a bisection that are sent to every task.
PIVOT_FLOATS = 1 << 23
#: Numbers in the matrices of a node that one task splits down to its blocks.
NODE_FLOATS = 1 << 20
#: Levels of a bisection, and the share of a node's vertices below which a side is too small.
LEVELS, LOPSIDED = 64, 0.02


def linkage(d: np.ndarray, method: str = "average", copy: bool = True) -> list[tuple[int, int, float]]:
    """Merges (kept slot, absorbed slot, height) of agglomeration; ties go to the smallest slots, which are members.

    Without a copy d is used up.
    """
    d = np.array(d, float) if copy else d
    n = len(d)
    np.fill_diagonal(d, np.inf)
    size, out = np.ones(n), []
    near = d.argmin(1) if n > 1 else np.zeros(n, int)
    best = d[np.arange(n), near] if n > 1 else np.full(n, np.inf)
    for _ in range(n - 1):
        i = int(best.argmin())
        j = int(near[i])
        i, j = min(i, j), max(i, j)
        out.append((i, j, float(best.min())))
        if method == "average":
            row = (size[i] * d[i] + size[j] * d[j]) / (size[i] + size[j])
        else:
            row = np.minimum(d[i], d[j]) if method == "single" else np.maximum(d[i], d[j])
        row[[i, j]] = np.inf
        d[i], d[:, i] = row, row
        d[j], d[:, j] = np.inf, np.inf
        size[i] += size[j]
        best[j] = np.inf
        stale = np.flatnonzero((near == i) | (near == j))
        for s in np.unique(np.r_[stale, i]):
            if best[s] < np.inf or s == i:
                near[s] = d[s].argmin()
                best[s] = d[s, near[s]]
        closer = (row < best) | ((row == best) & (i < near))
        closer &= np.isfinite(row)
        near[closer], best[closer] = i, row[closer]
    return out


def paths_of_merges(n: int, merges: list[tuple[int, int, float]]) -> list[str]:
    """Leaf paths of a merge list; the side with the smaller slot is on the left."""
    members = {i: [i] for i in range(n)}
    turns: list[list[str]] = [[] for _ in range(n)]
    for i, j, _ in merges:
        for x in members[i]:
            turns[x].append("0")
        for x in members[j]:
            turns[x].append("1")
        members[i] += members.pop(j)
    return ["".join(reversed(t)) for t in turns]


def spanning_edges(d: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ends and lengths of a least spanning tree; the shortest distance from a set to the rest is that of an edge between them."""
    n = len(d)
    near, best, left = np.zeros(n, np.int64), np.array(d[0], float), np.ones(n, bool)
    left[0], best[0] = False, np.inf
    a, b, w = np.zeros(n - 1, np.int64), np.zeros(n - 1, np.int64), np.zeros(n - 1)
    for k in range(n - 1):
        j = int(best.argmin())
        j = j if left[j] else int(left.argmax())
        a[k], b[k], w[k] = near[j], j, best[j]
        left[j], best[j] = False, np.inf
        closer = left & (d[j] < best)
        near[closer], best[closer] = j, d[j][closer]
    return a, b, w


def mutual_groups(d: np.ndarray, copy: bool = True) -> list[list[int]]:
    """Largest groups whose members are all closer to one another than to any outsider.

    Such a group is a node of the complete-linkage tree, so only its nodes are tried. Without a copy d is used up.
    """
    n = len(d)
    a, b, w = spanning_edges(d)
    groups, members = {i: [i] for i in range(n)}, {i: [i] for i in range(n)}
    for i, j, height in linkage(d, "complete", copy):
        members[i] = members[i] + members.pop(j)
        a[a == j], b[b == j] = i, i
        across = ((a == i) | (b == i)) & (a != b)
        if across.any() and height < w[across].min():
            for x in members[i]:
                groups.pop(x, None)
            groups[members[i][0]] = sorted(members[i])
    return sorted(groups.values())


class Between:
    """Means of distances between groups, added up from rows of the upper triangle in any order, and distances inside groups."""

    def __init__(self, groups: list[list[int]]):
        self.groups, n = groups, sum(map(len, groups))
        self.label, self.place = np.zeros(n, np.int64), np.zeros(n, np.int64)
        for k, g in enumerate(groups):
            self.label[g], self.place[g] = k, np.arange(len(g))
        self.sums = scratch(len(groups))
        self.inner = [np.zeros((len(g), len(g))) for g in groups]

    def add(self, i: int, row: np.ndarray) -> None:
        """row: distances from i to all later places."""
        k, later = self.label[i], self.label[i + 1 :]
        own = np.flatnonzero(later == k)
        x, y = self.place[i], self.place[i + 1 :][own]
        self.inner[k][x, y] = self.inner[k][y, x] = row[own]
        if len(row):
            self.sums[k] += np.bincount(later, row, len(self.groups))

    def paths(self, method: str) -> list[str]:
        """Groups stay whole: split top-down between groups, merged bottom-up inside. The sums are used up."""
        means, size = self.sums, np.array([len(g) for g in self.groups], float)
        for lo in range(0, len(means), 512):
            hi = min(lo + 512, len(means))
            both = means[lo:hi, lo:] + means[lo:, lo:hi].T
            both /= size[lo:hi, None] * size[None, lo:]
            means[lo:hi, lo:], means[lo:, lo:hi] = both, both.T
        paths = [""] * len(self.label)
        for g, inner, path in zip(self.groups, self.inner, split_paths(means), strict=True):
            for x, p in zip(g, paths_of_merges(len(g), linkage(inner, method)) if len(g) > 1 else [""], strict=True):
                paths[x] = path + p
        return paths


def split_paths(means: np.ndarray) -> list[str]:
    """Leaf paths of a top-down tree: the two farthest apart seed the two sides of a part. means is used up."""
    paths, stack = [""] * len(means), [(np.arange(len(means)), "")]
    while stack:
        part, path = stack.pop()
        if len(part) == 1:
            paths[part[0]] = path
            continue
        b = means if len(part) == len(means) else means[np.ix_(part, part)]
        np.fill_diagonal(b, -1)
        one, two = np.unravel_index(b.argmax(), b.shape)
        np.fill_diagonal(b, 0)
        left = b[:, min(one, two)] <= b[:, max(one, two)]
        left[min(one, two)], left[max(one, two)] = True, False
        stack += [(part[~left], path + "1"), (part[left], path + "0")]
    return paths


def hybrid_paths(d: np.ndarray, method: str = "average") -> list[str]:
    """Mutual groups stay whole: split top-down between groups, merged bottom-up inside."""
    between = Between(mutual_groups(d))
    for i in range(len(d)):
        between.add(i, d[i, i + 1 :])
    return between.paths(method)


def scratch(n: int) -> np.ndarray:
    """A square of zeros, in an unnamed file if it is large."""
    if n * n * 8 <= SQUARE_BYTES:
        return np.zeros((n, n))
    with tempfile.TemporaryFile() as file:
        file.truncate(n * n * 8)
        return np.memmap(file, np.float64, "r+", shape=(n, n))


def leaf_paths(d: np.ndarray, method: str) -> list[str]:
    if len(d) == 1:
        return [""]
    return hybrid_paths(d) if method == "hybrid" else paths_of_merges(len(d), linkage(d, method))


def square(ids: np.ndarray, u: np.ndarray, v: np.ndarray, delta: np.ndarray) -> np.ndarray:
    """Symmetric matrix over sorted ids from pairs."""
    d = np.zeros((len(ids), len(ids)))
    i, j = np.searchsorted(ids, u), np.searchsorted(ids, v)
    d[i, j] = d[j, i] = delta
    return d


def build_tree(dissim: DataFrame, vertices: DataFrame, method: str = "hybrid", exact_limit: int = PAIRS_LIMIT) -> DataFrame:
    """(v, path) of the exact tree from pairs, built in one task; more than exact_limit vertices are refused."""
    n = vertices.count()
    if n > exact_limit:
        raise ValueError(f"{n} vertices exceed the limit {exact_limit} of pairs in one task; use cluster_tree or bisect_tree")
    rows = dissim.select("u", "v", "delta").unionByName(vertices.select(F.col("v").alias("u"), "v", F.lit(0.0).alias("delta")))
    rows = rows.withColumn("all", F.lit(0))

    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        ids = np.unique(np.r_[pdf["u"], pdf["v"]])
        return pd.DataFrame({"v": ids, "path": leaf_paths(square(ids, pdf["u"], pdf["v"], pdf["delta"]), method)})

    return rows.groupBy("all").applyInPandas(work, "v long, path string")


#: Squares are held one at a time, however many trees are built at once.
_ONE_SQUARE = threading.Lock()


def cluster_tree(held: Held, method: str = "hybrid") -> DataFrame:
    """(v, path) of the exact tree. The hybrid tree keeps no square; for others rows of the triangle are made by all tasks and read
    by one, which holds the square once.
    """
    if held.n > EXACT_LIMIT:
        raise ValueError(f"{held.n} vertices exceed the limit {EXACT_LIMIT} of the exact tree; choose tree='bisect'")
    store = Store(held.spark, "cluster")
    if held.n < 2:
        return store.keep(held.spark.createDataFrame([(int(v), "") for v in held.ids], "v long, path string"))
    if method == "hybrid":
        return hybrid_leaves(held)
    triangle, shared, n = store.keep(held.triangle()), held.shared, held.n

    def cells(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, np.ndarray]]:
        for b in batches:
            for i, x in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                yield i, np.frombuffer(x.as_buffer(), np.float64)

    def whole(batches: Iterator[pa.RecordBatch]) -> np.ndarray:
        d = scratch(n)
        for i, row in cells(batches):
            d[i, i + 1 :] = row
        for lo in range(0, n, 512):
            hi = min(lo + 512, n)
            d[hi:, lo:hi] = d[lo:hi, hi:].T
            d[lo:hi, lo:hi] += np.triu(d[lo:hi, lo:hi], 1).T
        return d

    def merged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        paths = paths_of_merges(n, linkage(whole(batches), method, copy=False))
        yield pa.RecordBatch.from_arrays([pa.array(shared.value[0]), pa.array(paths, pa.string())], names=["v", "path"])

    with _ONE_SQUARE:
        return store.keep(triangle.coalesce(1).mapInArrow(merged, "v long, path string"))


def bisect_tree(matrices: DataFrame, block: int = 256, method: str = "hybrid", seed: str = "1", one_sided: bool = False, band: int | None = None) -> DataFrame:
    """(v, path) for graphs of any size: nodes above block vertices are bisected, the blocks that remain are finished exactly."""
    blocks = bisect_blocks(matrices, block, seed, one_sided, band)
    return block_leaves(blocks, pairs_within(matrices.join(blocks, "v"), "block", 64, one_sided, band), method)


def bisect_blocks(matrices: DataFrame, block: int = 256, seed: str = "1", one_sided: bool = False, band: int | None = None) -> DataFrame:
    """(v, block): the paths of the first nodes of at most block vertices.

    A node's two pivots are its vertices of extreme draws; a vertex goes to the nearer. A node whose vertices all go to
    one side is split by draws instead. All nodes of a level that are too large for a task are split in one job; a task
    splits a smaller node down to its blocks. Which of both splits a node makes no difference to the blocks.
    """
    spark, store = matrices.sparkSession, Store(matrices.sparkSession, "bisect")
    m = store.keep(matrices.select("v", "m"))
    at = store.keep(m.select("v", (F.size("m") * F.size(F.element_at("m", 1))).cast("long").alias("cells"), F.lit("").alias("path")))
    for level in range(LEVELS):
        drawn = at.withColumn("w", number(seed, "pivot", F.lit(level), "v"))
        who = F.struct("v", "cells")
        sized = drawn.groupBy("path").agg(F.count("*").alias("n"), F.sum("cells").alias("cells"), F.min_by(who, F.struct("w", "v")).alias("p"), F.max_by(who, F.struct("w", "v")).alias("q"))
        large = sized.where((F.col("n") > block) & (F.col("cells") > NODE_FLOATS)).collect()  # few: each holds more than NODE_FLOATS
        if not large:
            break
        pivots = F.broadcast(spark.createDataFrame([(r["path"], r["p"]["v"], r["q"]["v"]) for r in large], "path string, p long, q long"))
        asked = drawn.join(pivots, "path").drop("cells")
        if sum(r[e]["cells"] for r in large for e in "pq") <= PIVOT_FLOATS:  # checked: their matrices go to every task, those of all others are dealt once
            ends = F.broadcast(spark.createDataFrame([(r["path"], i, r[e]["v"]) for r in large for i, e in enumerate("pq")], "path string, end int, v long"))
            held = {(r["path"], r["end"]): (r["v"], r["m"]) for r in m.join(ends, "v").collect()}
            sides = _sides(asked.join(m, "v"), spark.sparkContext.broadcast(held), one_sided, band)
        else:
            pairs = asked.select(F.col("p").alias("u"), "v").union(asked.select(F.col("q").alias("u"), "v")).where("u <> v").distinct()
            delta = store.keep(dissimilarity(m, pairs, one_sided=one_sided, band=band))
            near = lambda c: delta.select(F.col("u").alias(c), "v", F.col("delta").alias(f"d{c}"))
            both = asked.join(near("p"), [c for c in ("p", "v")], "left").join(near("q"), ["q", "v"], "left")
            right = F.coalesce("dp", F.lit(0.0)) > F.coalesce("dq", F.lit(0.0))
            sides = both.select("path", "v", "w", F.when(F.col("v") == F.col("p"), False).when(F.col("v") == F.col("q"), True).otherwise(right).alias("r"))
        sides = store.keep(sides)
        share = sides.groupBy("path").agg(F.avg(F.col("r").cast("double")).alias("s"))
        turn = F.when((F.col("s") < LOPSIDED) | (F.col("s") > 1 - LOPSIDED), F.col("w") % 2 == 1).otherwise(F.col("r"))
        moved = sides.join(share, "path").select("v", F.concat("path", F.when(turn, "1").otherwise("0")).alias("to"))
        at = store.keep(at.join(moved, "v", "left").select("v", "cells", F.coalesce("to", "path").alias("path")))

    def split(pdf: pd.DataFrame) -> pd.DataFrame:
        ms = [np.asarray(x).reshape(n, -1) for x, n in zip(pdf["flat"], pdf["rows"], strict=True)]
        return pd.DataFrame({"v": pdf["v"], "block": _split(pdf["path"].iloc[0], pdf["v"].to_numpy(), ms, block, seed, one_sided, band)})

    sized = at.groupBy("path").agg(F.count("*").alias("n"))
    open_ = at.join(sized.where(F.col("n") > block), "path", "left_semi").join(m, "v").select("v", "path", F.flatten("m").alias("flat"), F.size("m").alias("rows"))
    done = at.join(sized.where(F.col("n") <= block), "path", "left_semi").select("v", F.col("path").alias("block"))
    return store.keep(done.union(open_.repartition(wide(spark), "path").groupBy("path").applyInPandas(split, "v long, block string")))


def _split(path: str, ids: np.ndarray, ms: list[np.ndarray], block: int, seed: str, one_sided: bool, band: int | None) -> list[str]:
    """Blocks of the vertices of one node, by the draws and rules of bisect_blocks()."""
    out, stack = [""] * len(ids), [(path, np.arange(len(ids)))]
    while stack:
        path, at = stack.pop()
        if len(at) <= block or len(path) >= LEVELS:
            for x in at:
                out[x] = path
            continue
        w = np.array([int(hashlib.md5(f"{seed}|pivot|{len(path)}|{v}".encode()).hexdigest()[:13], 16) for v in ids[at].tolist()])
        order = np.lexsort((ids[at], w))
        p, q = at[order[0]], at[order[-1]]
        mine = [ms[x] for x in at]
        right = align_many([ms[p]] * len(at), mine, one_sided, band) > align_many([ms[q]] * len(at), mine, one_sided, band)
        right[order[-1]], right[order[0]] = True, False
        if not LOPSIDED <= right.mean() <= 1 - LOPSIDED:
            right = w % 2 == 1
        stack += [(path + "1", at[right]), (path + "0", at[~right])]
    return out


def block_leaves(blocks: DataFrame, dissim: DataFrame, method: str = "hybrid") -> DataFrame:
    """(v, path) of the exact trees of blocks (v, block), from pairs within them; a block's path leads those of its leaves."""
    own = blocks.select("block", F.col("v").alias("u"), "v", F.lit(0.0).alias("delta"))
    rows = own.unionByName(dissim.select("u", "v", "delta").join(blocks, "v").select("block", "u", "v", "delta"))

    def finish(pdf: pd.DataFrame) -> pd.DataFrame:
        ids, path = np.unique(pdf["v"]), pdf["block"].iloc[0]
        d = square(ids, pdf["u"].to_numpy(), pdf["v"].to_numpy(), pdf["delta"].to_numpy())
        return pd.DataFrame({"v": ids, "path": [path + p for p in leaf_paths(d, method)]})

    store = Store(blocks.sparkSession, "blockleaves")
    return store.keep(rows.repartition(wide(blocks.sparkSession), "block").groupBy("block").applyInPandas(finish, "v long, path string"))


def _sides(rows: DataFrame, pivots, one_sided: bool, band: int | None) -> DataFrame:
    """(path, v, w, r): whether each vertex of rows (v, path, w, m) is nearer to its node's second pivot; pivots maps (path, end) to id and matrix."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = {k: (v, np.array(m, float)) for k, (v, m) in pivots.value.items()}
        for b in batches:
            paths, ids = b.column("path").to_pylist(), b.column("v").to_numpy()
            mine = rows_of(b.column("flat"), b.column("rows").to_numpy())
            p, q = ([known[x, end] for x in paths] for end in (0, 1))
            dp, dq = (align_many([x[1] for x in e], mine, one_sided, band) for e in (p, q))
            first, second = (np.array([x[0] for x in e], np.int64) == ids for e in (p, q))
            right = np.where(first, False, np.where(second, True, dp > dq))
            yield pa.RecordBatch.from_arrays([b.column("path"), b.column("v"), b.column("w"), pa.array(right)], names=["path", "v", "w", "r"])

    flat = rows.select("path", "v", "w", F.flatten("m").alias("flat"), F.size("m").cast("long").alias("rows"))
    return flat.repartition(wide(rows.sparkSession), "v").mapInArrow(run, "path string, v long, w long, r boolean")


def ordinals(leaves: DataFrame) -> DataFrame:
    """(v, path, ordinal) in the order of paths."""
    return positions(leaves.select("v", "path"), Store(leaves.sparkSession, "leaves"), "path", "v")


def nodes(leaves: DataFrame) -> DataFrame:
    """(path, lo, hi, size, depth, is_leaf) of all nodes; lo and hi are the ordinals of its first leaf and past its last."""
    placed = ordinals(leaves)
    cut = F.transform(F.sequence(F.lit(0), F.length("path")), lambda i: F.col("path").substr(F.lit(1), i))
    up = placed.select("ordinal", F.explode(cut).alias("node"), "path")
    found = up.groupBy("node").agg(F.min("ordinal").alias("lo"), (F.max("ordinal") + 1).alias("hi"), F.count("*").alias("size"), F.bool_or(F.col("node") == F.col("path")).alias("is_leaf"))
    return found.select(F.col("node").alias("path"), "lo", "hi", "size", F.length("node").alias("depth"), "is_leaf")


def tree_violations(leaves: DataFrame) -> DataFrame:
    """Counts of what a binary tree must have, and of nodes that break it, in one row."""
    n = nodes(leaves)
    children = n.where("depth > 0").select(F.expr("substr(path, 1, depth - 1)").alias("path"), "size").groupBy("path").agg(F.count("*").alias("c"), F.sum("size").alias("s"))
    both = n.join(children, "path", "left")
    bad = F.when(F.col("is_leaf"), (F.col("size") != 1) | F.col("c").isNotNull()).otherwise((F.col("c") != 2) | (F.col("s") != F.col("size")))
    bad |= F.col("hi") - F.col("lo") != F.col("size")
    return both.agg(F.count_if("is_leaf").alias("leaves"), F.count_if(~F.col("is_leaf")).alias("internal"), F.count_if(F.col("depth") == 0).alias("roots"), F.count_if(F.coalesce(bad, F.lit(True))).alias("violations"))


def median_order(vectors: DataFrame) -> DataFrame:
    """(v, ordinal) by noisy degree: the leaves of the rank tree, whose nodes are ranges of ordinals by their leading bits."""
    est = vectors.select("v", F.aggregate("c", F.lit(0.0), lambda s, x: s + x).alias("est"))
    return positions(est.withColumn("est", F.round("est", 9)), Store(vectors.sparkSession, "median"), "est", "v").select("v", "ordinal")


def rank_lca(i: Column, j: Column, n: Column) -> Column:
    """Leaves under the lowest common ancestor of two ordinals in the rank tree of n leaves: a shared bit prefix."""
    span = F.pow(F.lit(2.0), F.length(F.bin(i.bitwiseXOR(j)))).cast("long")
    low = F.floor(i / span) * span
    return F.when(i == j, F.lit(1)).otherwise(F.least(n, low + span) - low).cast("long")


def splits(paths: list[str]) -> list[tuple[list[int], list[int], int]]:
    """(left leaves, right leaves, depth) of each inner node above some leaves, by indices into paths."""
    order, out = sorted(range(len(paths)), key=lambda i: paths[i]), []
    stack = [(0, len(order))]
    while stack:
        lo, hi = stack.pop()
        if hi - lo < 2:
            continue
        first, last = paths[order[lo]], paths[order[hi - 1]]
        depth = len(os.path.commonprefix([first, last]))
        if depth == len(first):
            raise ValueError("a leaf above another")
        mid = bisect.bisect_left(order, last[: depth + 1], lo, hi, key=lambda i: paths[i])
        out.append((order[lo:mid], order[mid:hi], depth))
        stack += [(lo, mid), (mid, hi)]
    return out


def lca_sizes(paths: list[str]) -> np.ndarray:
    """Leaves under the lowest common ancestor of each pair of leaves given by paths."""
    size = np.ones((len(paths), len(paths)), np.int64)
    for a, b, _ in splits(paths):
        size[np.ix_(a, b)] = size[np.ix_(b, a)] = len(a) + len(b)
    return size


def common_depth(paths: list[str]) -> np.ndarray:
    """Length of the common prefix of each pair of paths."""
    out = np.array([[len(p)] * len(paths) for p in paths])
    for a, b, depth in splits(paths):
        out[np.ix_(a, b)] = out[np.ix_(b, a)] = depth
    return out


class LeafOrder:
    """A tree over the vertices of held, dealt to every task: what a leaf shares with all others, in time linear in them.

    Between neighbours in the order of paths lies one inner node; the common node of two leaves is the least deep between them.
    """

    def __init__(self, leaves: DataFrame, held: Held):
        t = leaves.select("v", "path").toArrow().sort_by("v")
        if not np.array_equal(t["v"].to_numpy(), held.ids):
            raise ValueError("the tree and the matrices are not of the same vertices")
        paths = t["path"].to_pylist()
        order = sorted(range(held.n), key=paths.__getitem__)
        depth = np.array([len(os.path.commonprefix([paths[x], paths[y]])) for x, y in zip(order, order[1:], strict=False)], np.int64)
        size, open_ = np.zeros(len(depth), np.int64), []
        for at, d in enumerate([*depth.tolist(), -1]):
            while open_ and depth[open_[-1]] > d:
                node = open_.pop()
                size[node] = at - (open_[-1] if open_ else -1)
            open_.append(at)
        place = np.empty(held.n, np.int64)
        place[order] = np.arange(held.n)
        self.shared = held.spark.sparkContext.broadcast((place, size, depth, np.array([len(p) for p in paths], np.int64)))


def shared_leaves(order, i: int) -> np.ndarray:
    """Leaves under the lowest common node of leaf i and each leaf, by the value of a LeafOrder."""
    place, size, _, _ = order
    return _outwards(np.maximum, size, place[i], 1)[place]


def shared_depth(order, i: int) -> np.ndarray:
    """Depth of that node."""
    place, _, depth, length = order
    return _outwards(np.minimum, depth, place[i], length[i])[place]


def _outwards(pick: np.ufunc, between: np.ndarray, p: int, own: int) -> np.ndarray:
    return np.concatenate([pick.accumulate(between[:p][::-1])[::-1], [own], pick.accumulate(between[p:])])


def lca_leaves(leaves: DataFrame, pairs: DataFrame) -> DataFrame:
    """(u, v, leaves) of pairs: the smallest node that holds both, found among the nodes above u."""
    placed = ordinals(leaves).select("v", "path", "ordinal")
    cut = F.transform(F.sequence(F.lit(0), F.length("path")), lambda i: F.col("path").substr(F.lit(1), i))
    above = pairs.select("u", "v").join(placed.select(F.col("v").alias("u"), "path"), "u").join(placed.select("v", F.col("ordinal").alias("o")), "v")
    above = above.select("u", "v", "o", F.explode(cut).alias("path"))
    inside = above.join(nodes(leaves).select("path", "lo", "hi", "size"), "path").where("o >= lo and o < hi")
    return inside.groupBy("u", "v").agg(F.min("size").alias("leaves"))
