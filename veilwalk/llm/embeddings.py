"""Near-duplicate vectors: all pairs with cosine at or above a threshold, by int8 tiles with rigorous error bounds.

Equal vectors become one class first. Classes are numbered and packed into tiles; each pair of tiles is one task's work.
A vector is scaled to int8 and keeps the norm of what rounding lost, so a product of int8 vectors bounds the cosine from
above; only pairs whose bound reaches the threshold are computed in double precision. A pair of tiles gives numbers of
links, and links that span its components, never all pairs.

Results: vectors that are null, empty, zero, or hold null or non-finite components link with nothing; only vectors of
one length link; rows without an id link with nothing and keep a null id; rows that repeat an id count as vectors of
their own; an empty table gives an empty result; other columns are ignored. Work is that of all pairs of tiles.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veilwalk.llm.common import Forest, Scratch, connected_components, numbered, spread_join

THRESHOLD = 0.9
TILE = 8192
ROWS, COLS = 512, 2048
#: Pairs computed in double precision at once.
PAIRS = 1 << 15
#: Sums of this many products of int8 numbers are exact in single precision.
EXACT_DIMS = 1024
#: Relative slack for single-precision scaling of exact integers.
SLACK = 1e-5


class Tile:
    """Vectors of one length: unit vectors in double precision, int8 values, scales, and norms of what rounding lost."""

    def __init__(self, pos: np.ndarray, weight: np.ndarray, x: np.ndarray):
        self.pos, self.weight, self.raw = pos, weight, x
        peak = np.abs(x).max(1, keepdims=True)
        self.x = x / peak
        self.x /= np.linalg.norm(self.x, axis=1, keepdims=True)
        self.scale = np.abs(self.x).max(1) / 127
        q = np.rint(self.x / self.scale[:, None])
        self.lost = np.linalg.norm(self.x - q * self.scale[:, None], axis=1) * (1 + 1e-9) + 1e-12
        self.q = q.astype(np.int8)

    def part(self, s: int, e: int) -> Tile:
        t = object.__new__(Tile)
        for k in ("pos", "weight", "raw", "x", "scale", "lost", "q"):
            setattr(t, k, getattr(self, k)[s:e])
        return t


def int8_products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Exact integer products; single precision holds them for up to EXACT_DIMS dimensions at a time."""
    dims = a.shape[1]
    if dims <= EXACT_DIMS:
        return a.astype(np.float32) @ b.astype(np.float32).T
    out = np.zeros((len(a), len(b)))
    for d in range(0, dims, EXACT_DIMS):
        out += a[:, d : d + EXACT_DIMS].astype(np.float32) @ b[:, d : d + EXACT_DIMS].astype(np.float32).T
    return out


def _exact(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Cosines of paired rows in double precision."""
    return (a * b).sum(1)


def link_matrix(a: Tile, b: Tile, threshold: float) -> np.ndarray:
    """Truth table of the links of two blocks.

    A product of int8 vectors lies within a known distance of the cosine: pairs surely above or surely below the
    threshold are settled by it, all others by their cosine in double precision.
    """
    products = int8_products(a.q, b.q)
    products *= b.scale.astype(products.dtype)
    error = (1 + a.lost) * b.lost.max() + a.lost
    low, high = (threshold - error) / a.scale, (threshold + error) / a.scale
    low -= np.abs(low) * SLACK + SLACK
    high += np.abs(high) * SLACK + SLACK
    links = products >= high[:, None].astype(products.dtype)
    i, j = np.nonzero((products >= low[:, None].astype(products.dtype)) & ~links)
    for at in range(0, len(i), PAIRS):
        p, q = i[at : at + PAIRS], j[at : at + PAIRS]
        links[p, q] = _exact(a.x[p], b.x[q]) >= threshold
    return links


def spanning(table: np.ndarray) -> list[tuple[int, int]]:
    """Links that keep the components of a two-sided truth table together."""
    edges: list[tuple[int, int]] = []
    rows_left, cols_left = table.any(1), np.ones(table.shape[1], bool)
    while rows_left.any():
        row = int(rows_left.argmax())
        rows_left[row] = False
        queue = [row]
        while queue:
            r = queue.pop()
            new = np.flatnonzero(table[r] & cols_left)
            cols_left[new] = False
            for c in new:
                edges.append((r, int(c)))
                more = np.flatnonzero(table[:, c] & rows_left)
                rows_left[more] = False
                edges += [(int(m), int(c)) for m in more]
                queue += more.tolist()
    return edges


def compare(a: Tile, b: Tile, same: bool, threshold: float) -> tuple[np.ndarray, np.ndarray, list[tuple[int, int]]]:
    """Weighted numbers of links of a's and of b's vectors, and links (positions) that span the components."""
    na, nb, edges = np.zeros(len(a.pos), np.int64), np.zeros(len(b.pos), np.int64), []
    for r in range(0, len(a.pos), ROWS):
        pa_ = a.part(r, r + ROWS)
        for c in range(0, len(b.pos), COLS):
            if same and c + COLS <= r:
                continue
            pb = b.part(c, c + COLS)
            links = link_matrix(pa_, pb, threshold)
            if same:
                links &= np.arange(r, r + len(pa_.pos))[:, None] < np.arange(c, c + len(pb.pos))
            if not links.any():
                continue
            na[r : r + ROWS] += links @ pb.weight
            nb[c : c + COLS] += pa_.weight @ links
            pairs = spanning(links)
            edges += [(int(pa_.pos[i]), int(pb.pos[j])) for i, j in pairs]
    return na, nb, edges


def _tiles(row: dict) -> dict[int, Tile]:
    """Tiles of a packed row by vector length."""
    pos, weight, dims = (np.frombuffer(row[k], np.int64) for k in ("pos", "weight", "dims"))
    flat, ends = np.frombuffer(row["x"], np.float64), np.cumsum(dims)
    out = {}
    for d in np.unique(dims):
        at = np.flatnonzero(dims == d)
        out[int(d)] = Tile(pos[at], weight[at], np.stack([flat[ends[i] - d : ends[i]] for i in at]))
    return out


PACKED = "tile long, pos binary, weight binary, dims binary, x binary"


def _pack(table: pa.Table) -> pa.Table:
    vectors = table["vec"].combine_chunks()
    flat = vectors.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    dims = vectors.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
    cells = [table["pos"].to_numpy().astype(np.int64), table["weight"].to_numpy().astype(np.int64), dims, flat]
    cols = [table["tile"].combine_chunks().slice(0, 1), *[pa.array([c.tobytes()], pa.binary()) for c in cells]]
    return pa.table(cols, names=["tile", "pos", "weight", "dims", "x"])


def near_duplicates(vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", threshold: float = THRESHOLD, tile: int = TILE) -> DataFrame:
    """(vec_id, n_links, component_id, kept), one row for each row with an id."""
    spark = vectors.sparkSession
    scratch = Scratch(spark, "embeddings")
    vec = F.col("vec")
    rows = vectors.select(vectors[id_col].cast("long").alias("vec_id"), vectors[vec_col].cast("array<double>").alias("vec"))
    finite = F.forall("vec", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf")))
    usable = F.coalesce(finite & F.exists("vec", lambda v: v != 0), F.lit(False)) & F.col("vec_id").isNotNull()
    plain = F.transform("vec", lambda v: v + 0.0)  # -0.0 becomes 0.0, so that equal vectors have equal names
    rows = scratch.save(rows.select("vec_id", F.when(usable, plain).alias("vec")).withColumn("class", F.when(vec.isNotNull(), F.sha2(F.to_json(F.struct("vec")), 256))), "rows")
    classes = rows.where("vec is not null").groupBy("class").agg(F.first("vec").alias("vec"), F.min("vec_id").alias("first_id"), F.count("*").alias("weight"))
    classes = scratch.save(classes.withColumn("h", F.xxhash64("class")), "classes")
    rows = rows.drop("vec")
    ranked = scratch.save(numbered(classes, scratch, "ranked", ["h", "first_id"]).drop("h"), "numbered")
    n = ranked.count()
    if not n:
        return rows.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    tiles = -(-n // tile)
    placed = ranked.withColumn("tile", F.expr(f"pos * {tiles} div {n}")).select("tile", "pos", "weight", "vec")  # tiles of one size
    packed = scratch.save(placed.groupBy("tile").applyInArrow(_pack, PACKED), "tiles")
    pairs = packed.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(tiles - 1).cast("long"))))
    pairs = pairs.select(F.least("tile", "other").alias("i"), F.greatest("tile", "other").alias("j"), "tile", "pos", "weight", "dims", "x")

    def work(group: pa.Table) -> pa.Table:
        both = sorted(group.to_pylist(), key=lambda r: r["tile"])
        same = len(both) == 1
        left, right = _tiles(both[0]), _tiles(both[-1])
        kinds, xs, ys = [], [], []
        for d in left.keys() & right.keys():
            na, nb, edges = compare(left[d], right[d], same, threshold)
            for t, m in ((left[d], na), (right[d], nb)):
                at = np.flatnonzero(m)
                kinds.append(np.ones(len(at), np.int32))
                xs.append(t.pos[at])
                ys.append(m[at])
            forest = Forest()
            forest.add(edges)
            e = forest.stars()
            if len(e):
                kinds.append(np.zeros(len(e), np.int32))
                xs.append(e[:, 0])
                ys.append(e[:, 1])
        cols = [np.concatenate(x) if x else np.zeros(0, k) for x, k in ((kinds, np.int32), (xs, np.int64), (ys, np.int64))]
        return pa.table([pa.array(c) for c in cols], names=["kind", "x", "y"])

    found = scratch.save(pairs.groupBy("i", "j").applyInArrow(work, "kind int, x long, y long"), "links")
    counts = found.where("kind = 1").groupBy(F.col("x").alias("pos")).agg(F.sum("y").alias("links"))
    edges = found.where("kind = 0").select(F.col("x").alias("a"), F.col("y").alias("b"))
    roots = connected_components(edges, scratch).withColumnsRenamed({"node": "pos"})
    full = ranked.drop("vec").join(counts, "pos", "left").join(roots, "pos", "left").withColumn("root", F.coalesce("root", "pos"))
    least = full.groupBy("root").agg(F.min("first_id").alias("component_id"))
    full = full.join(least, "root").select("class", (F.coalesce("links", F.lit(0)) + F.col("weight") - 1).alias("n_links"), "component_id")
    out = spread_join(rows, full, "class", ["vec_id"], "left").select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id"))
    return out.withColumn("kept", F.col("vec_id") == F.col("component_id"))
