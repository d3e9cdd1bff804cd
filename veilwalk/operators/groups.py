"""The hybrid cluster tree without the square of distances: rows of it are made where they are asked for, and none is kept.

A mutual group is a component of the graph of all pairs below some distance, so components are joined by their shortest ways
out (Boruvka) and those whose own pairs are all shorter than that way are groups. Between groups, a part is split by the two
farthest ones. All passes are made by tasks that hold the matrices; the driver holds a few numbers for each vertex.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame

from veilwalk.operators.align import Held, Stacks, stacks_of, wide
from veilwalk.plans.lineage import Store

#: Nearest vertices that are kept of each vertex.
NEAREST = 16
#: Groups of a part whose square one task takes; larger parts are split by passes.
PART = 4096
#: Groups of a part that are looked at first for the farthest pair.
FIRST = 256


def rows_by(held: Held, todo: np.ndarray, work, schema: str, *more, alike: np.ndarray | None = None) -> DataFrame:
    """Rows of work(stacks, number, *more) for each number of todo; what is more is dealt to every task. Those alike go to one task, one after the other."""
    spark, shared, numbers = held.spark, held.shared, np.asarray(todo, np.int64)
    parts = max(1, min(wide(spark), len(numbers)))
    if alike is not None:
        numbers = numbers[np.argsort(alike[numbers], kind="stable")]
    else:
        numbers = np.concatenate([numbers[p::parts] for p in range(parts)])  # a task's are far from one another, since near ones are of like work
    given = spark.sparkContext.broadcast((numbers, more))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        stacks, (every, rest) = stacks_of(shared), given.value
        for b in batches:
            for i in b.column(0).to_pylist():
                found = work(stacks, int(every[i]), *rest)
                if found is not None:
                    yield found

    return spark.range(0, len(numbers), 1, parts).mapInArrow(run, schema)


def nearest(row: np.ndarray, among: np.ndarray, count: int) -> tuple[np.ndarray, np.ndarray]:
    """The places among (a mask) of the least distances of a row, and these, nearest first."""
    at = np.flatnonzero(among)
    most = np.partition(row[at], count - 1)[count - 1]
    at = at[row[at] <= most]
    order = np.lexsort((at, row[at]))[:count]
    return at[order], row[at[order]]


class Links:
    """A forest that grows by edges: labels of its trees, and their merges in the order of lengths."""

    def __init__(self, n: int):
        self.up, self.edges = np.arange(n), []

    def top(self, x: int) -> int:
        up = self.up
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return int(x)

    def join(self, x: int, y: int) -> bool:
        x, y = self.top(x), self.top(y)
        self.up[max(x, y)] = min(x, y)
        return x != y

    def labels(self) -> np.ndarray:
        while not np.array_equal(self.up, self.up[self.up]):
            self.up = self.up[self.up]
        return self.up


def _near_row(stacks: Stacks, i: int, count: int) -> pa.RecordBatch:
    among = np.ones(stacks.n, bool)
    among[i] = False
    at, far = nearest(stacks.row(i), among, count)
    return pa.RecordBatch.from_arrays([pa.array([i]), pa.array([at.tobytes()], pa.binary()), pa.array([far.tobytes()], pa.binary())], names=["i", "at", "far"])


def _out_row(stacks: Stacks, i: int, label: np.ndarray) -> pa.RecordBatch:
    at, far = nearest(stacks.row(i), label != label[i], 1)
    return pa.RecordBatch.from_arrays([pa.array([i]), pa.array(at), pa.array(far)], names=["i", "j", "far"])


def spanning_links(held: Held) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ends and lengths of a least spanning tree of all pairs, in the order of lengths."""
    n, count = held.n, min(NEAREST, held.n - 1)
    found: dict[bytes, int] = {}
    alike = np.array([found.setdefault(m.tobytes(), len(found)) for m in held.shared.value[1]])
    t = rows_by(held, np.arange(n), _near_row, "i long, at binary, far binary", count, alike=alike).toArrow().sort_by("i")
    at = np.stack([np.frombuffer(x, np.int64) for x in t["at"].to_pylist()])
    far = np.stack([np.frombuffer(x, np.float64) for x in t["far"].to_pylist()])
    radius, links, out = far[:, -1], Links(n), []
    while len(out) < n - 1:
        label = links.labels().copy()
        outside = label[at] != label[:, None]
        known, first = outside.any(1), outside.argmax(1)
        best, other = np.where(known, far[np.arange(n), first], np.inf), at[np.arange(n), first]
        least = np.full(n, np.inf)
        np.minimum.at(least, label, best)
        large = np.bincount(label).argmax()  # it is joined by the others' ways out
        ask = np.flatnonzero((label != large) & ~known & ((radius < least[label]) | np.isinf(least[label])))  # all others have a farther way out
        if len(ask):
            more = rows_by(held, ask, _out_row, "i long, j long, far double", label, alike=alike).toArrow()
            i = more["i"].to_numpy()
            best[i], other[i] = more["far"].to_numpy(), more["j"].to_numpy()
            known[i] = True
        asked = np.flatnonzero(known & (label != large))
        order = asked[np.lexsort((asked, best[asked], label[asked]))]
        leads = order[np.r_[True, label[order][1:] != label[order][:-1]]]  # of each tree its shortest way out
        for x in leads[np.lexsort((leads, best[leads]))].tolist():
            if links.join(x, int(other[x])):
                out.append((x, int(other[x]), best[x]))
    a, b, w = (np.array(x) for x in zip(*out, strict=True))
    order = np.argsort(w, kind="stable")
    return a[order].astype(np.int64), b[order].astype(np.int64), w[order].astype(float)


class Components:
    """The merges of a least spanning tree: node k is what edge k joins, an interval of an order of all vertices."""

    def __init__(self, a: np.ndarray, b: np.ndarray, w: np.ndarray):
        n = len(w) + 1
        links, node, after, tail = Links(n), np.full(n, -1), np.full(n, -1), np.arange(n)
        self.up, self.gap, size = np.full(n - 1, -1), np.zeros(n, np.int64), np.ones(n, np.int64)
        for k, (x, y) in enumerate(zip(a.tolist(), b.tolist(), strict=True)):
            x, y = links.top(x), links.top(y)
            for z in (x, y):
                if node[z] >= 0:
                    self.up[node[z]] = k
            x, y = min(x, y), max(x, y)
            links.up[y] = x
            after[tail[x]], self.gap[tail[x]] = y, k  # the list of y follows that of x; between them lies node k
            tail[x], node[x], size[x] = tail[y], k, size[x] + size[y]
        self.place, order, x = np.zeros(n, np.int64), np.zeros(n, np.int64), 0
        for p in range(n):
            self.place[x], order[p] = p, x
            x = after[x]
        self.order, self.between = order, self.gap[order[:-1]]
        self.exit = np.where(self.up >= 0, w[self.up], -np.inf)  # of the whole there is none: it is no group

    def shared(self, i: int) -> np.ndarray:
        """The least node above both i and each vertex, by places; -1 at i itself."""
        p = self.place[i]
        return np.concatenate([np.maximum.accumulate(self.between[:p][::-1])[::-1], [-1], np.maximum.accumulate(self.between[p:])])

    def spans(self) -> tuple[np.ndarray, np.ndarray]:
        """First place and the place past the last of each node."""
        lo, hi, stack = *np.zeros((2, len(self.up)), np.int64), []
        for q, k in enumerate([*self.between.tolist(), len(self.up)]):
            start = q
            while stack and stack[-1][0] < k:
                node, start = stack.pop()
                lo[node], hi[node] = start, q + 1
            stack.append((k, start))
        return lo, hi


def _broken_row(stacks: Stacks, i: int, parts: Components, after: np.ndarray) -> pa.RecordBatch | None:
    """Open nodes above i with a vertex that is as far from i as their way out; after has the open node at or above each node, then that above it."""
    node, chain = parts.shared(i), []
    k = after[0, node[node >= 0].min()]
    while k >= 0:
        chain.append(k)
        k = after[1, k]
    if not chain:
        return None
    lead, wanted = chain[-1], np.zeros(stacks.n, bool)
    wanted[parts.order[(node <= lead) & (node >= 0)]] = True
    row = stacks.row(i, wanted)[parts.order]
    inside = np.flatnonzero((node <= lead) & (node >= 0))
    inside = inside[np.argsort(node[inside], kind="stable")]
    most, at = np.maximum.accumulate(row[inside]), np.searchsorted(node[inside], chain, "right") - 1
    broken = [int(k) for k, p in zip(chain, at, strict=True) if most[p] >= parts.exit[k]]
    return pa.RecordBatch.from_arrays([pa.array(broken, pa.int64())], names=["k"]) if broken else None


def mutual_groups(held: Held) -> list[list[int]]:
    """Largest groups whose members are all closer to one another than to any outsider, as tree.mutual_groups() finds them in a square."""
    if held.n < 3:
        return [[i] for i in range(held.n)]
    a, b, w = spanning_links(held)
    parts = Components(a, b, w)
    lo, hi = parts.spans()
    open_, one_each = w < parts.exit, True  # the longest edge inside is a pair of its own
    for some in (parts.order[:: max(1, held.n // FIRST)], None, None):  # few vertices break most of the large nodes, one of each node most others
        inside = np.zeros(held.n + 1, np.int64)
        np.add.at(inside, lo[open_], 1)
        np.add.at(inside, hi[open_], -1)
        if some is None:
            some = parts.order[lo[open_]] if one_each else parts.order[np.cumsum(inside)[:-1] > 0]
            one_each = False
        if len(some) and open_.any():
            after = np.full((2, len(w)), -1)
            for k in range(len(w) - 1, -1, -1):
                above = after[0, parts.up[k]] if parts.up[k] >= 0 else -1
                after[:, k] = k if open_[k] else above, above
            found = rows_by(held, np.unique(some), _broken_row, "k long", parts, after).distinct().toArrow()["k"].to_numpy()
            open_[found] = False
    groups, taken = [], np.zeros(held.n, bool)
    for k in np.flatnonzero(open_)[::-1].tolist():  # a node comes after all inside it
        if not taken[lo[k]]:
            taken[lo[k] : hi[k]] = True
            groups.append(sorted(parts.order[lo[k] : hi[k]].tolist()))
    return sorted(groups + [[int(x)] for x in parts.order[~taken]])


def group_means(stacks: Stacks, g: int, members: list, label: np.ndarray, size: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    """Mean distances of group g to all groups whose vertices are wanted (a mask); 0 for others."""
    sums, at = np.zeros(len(size)), np.flatnonzero(wanted)
    for i in members[g]:
        sums += np.bincount(label[at], stacks.row(i, wanted)[at], len(size))
    return sums / (size[g] * size)


def _far_row(stacks: Stacks, g: int, members: list, label: np.ndarray, size: np.ndarray, part: np.ndarray) -> pa.RecordBatch:
    """The farthest of the later groups in the part of g."""
    later = (part[label] == part[g]) & (label > g)
    far, h = 0.0, g
    if later.any():
        means = group_means(stacks, g, members, label, size, later)
        means[(part != part[g]) | (np.arange(len(size)) <= g)] = -1.0
        h = int(means.argmax())
        far = float(means[h])
    return pa.RecordBatch.from_arrays([pa.array([g]), pa.array([h]), pa.array([far if h != g else -1.0])], names=["g", "h", "far"])


def _side_row(stacks: Stacks, g: int, members: list, label: np.ndarray, size: np.ndarray, part: np.ndarray) -> pa.RecordBatch:
    """Means of g to all groups of its part, in their order."""
    own = part == part[g]
    wanted = own[label] & (label != g)
    means = group_means(stacks, g, members, label, size, wanted)[own]
    return pa.RecordBatch.from_arrays([pa.array([g]), pa.array([means.tobytes()], pa.binary())], names=["g", "cells"])


def _later_row(stacks: Stacks, g: int, members: list, label: np.ndarray, size: np.ndarray, part: np.ndarray) -> pa.RecordBatch:
    """Means of g to the later groups of its part."""
    own = np.flatnonzero((part == part[g]) & (np.arange(len(part)) > g))
    later = (part[label] == part[g]) & (label > g)
    means = group_means(stacks, g, members, label, size, later)[own] if later.any() else np.zeros(0)
    return pa.RecordBatch.from_arrays([pa.array([int(part[g])]), pa.array([g]), pa.array([means.tobytes()], pa.binary())], names=["part", "g", "cells"])


def farthest(held: Held, todo: np.ndarray, part: np.ndarray, known: tuple, bound: np.ndarray, partner: np.ndarray) -> dict[int, tuple[int, int]]:
    """The first of the farthest pairs of groups of each part in todo.

    bound and partner hold for each group the distance and number of the farthest later group, of its part when that was last
    asked for; as parts only shrink, it is a bound from above while the partner is elsewhere. Only groups whose bound reaches the
    best pair known are asked anew, those of the largest bounds first, and eight times as many each time.
    """
    most = FIRST
    while True:
        right = (partner >= 0) & (part[partner] == part)
        right |= bound < 0
        ask, out = [], {}
        for p in todo:
            own = np.flatnonzero(part == p)
            sure = own[right[own]]
            best = bound[sure].max() if len(sure) else -1.0
            open_ = own[~right[own] & (bound[own] >= best)]
            if len(open_):
                ask.append(open_ if np.isinf(bound[open_[0]]) else open_[np.argsort(-bound[open_], kind="stable")[:most]])
            else:
                one = int(sure[bound[sure] == best].min())
                out[p] = (one, int(partner[one]))
        if not ask:
            return out
        t, most = rows_by(held, np.concatenate(ask), _far_row, "g long, h long, far double", *known, part).toArrow(), 8 * most
        g = t["g"].to_numpy()
        bound[g], partner[g] = t["far"].to_numpy(), t["h"].to_numpy()


def hybrid_leaves(held: Held, method: str = "average") -> DataFrame:
    """(v, path) of the hybrid tree: groups stay whole, are split top-down, and are merged bottom-up inside."""
    from veilwalk.operators.tree import linkage, paths_of_merges, scratch, split_paths  # which takes this module's trees

    store, spark, shared = Store(held.spark, "hybrid"), held.spark, held.shared
    members = mutual_groups(held)
    m = len(members)
    label, size = np.zeros(held.n, np.int64), np.array([len(g) for g in members], float)
    for k, g in enumerate(members):
        label[g] = k
    known = (members, label, size)
    part, path = np.zeros(m, np.int64), {0: ""}
    bound, partner = np.full(m, np.inf), np.full(m, -1)
    while large := [p for p, c in zip(*np.unique(part, return_counts=True), strict=True) if c > PART]:
        ends = farthest(held, large, part, known, bound, partner)
        seeds = np.array([x for p in large for x in ends[p]])
        t = rows_by(held, seeds, _side_row, "g long, cells binary", *known, part).toArrow()
        means = {g: np.frombuffer(x, np.float64) for g, x in zip(t["g"].to_pylist(), t["cells"].to_pylist(), strict=True)}
        after = part.copy()
        for p in large:
            one, two = ends[p]
            left = means[one] <= means[two]
            own = np.flatnonzero(part == p)
            left[own == one], left[own == two] = True, False
            after[own[~left]] = q = max(path) + 1
            path[p], path[q] = path[p] + "0", path[p] + "1"
        part = after
    rows = store.keep(rows_by(held, np.arange(m), _later_row, "part long, g long, cells binary", *known, part))
    lead = spark.sparkContext.broadcast(path)

    def split(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("g")
        n, means = len(pdf), scratch(len(pdf))
        for i, cells in enumerate(pdf["cells"]):
            means[i, i + 1 :] = means[i + 1 :, i] = np.frombuffer(cells, np.float64)
        first = lead.value[int(pdf["part"].iloc[0])]
        return pd.DataFrame({"g": pdf["g"].to_numpy(), "path": [first + x for x in split_paths(means)] if n > 1 else [first]})

    tops = rows.repartition(wide(spark), "part").groupBy("part").applyInPandas(split, "g long, path string")

    def inner(stacks: Stacks, g: int, members: list) -> pa.RecordBatch:
        own, d = np.array(members[g]), scratch(len(members[g]))
        wanted = np.zeros(stacks.n, bool)
        wanted[own] = True
        for x, i in enumerate(own.tolist()):
            wanted[i] = False
            d[x, x + 1 :] = d[x + 1 :, x] = stacks.row(i, wanted)[own[x + 1 :]]
        inside = paths_of_merges(len(own), linkage(d, method, copy=False)) if len(own) > 1 else [""]
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(own), g)), pa.array(shared.value[0][own]), pa.array(inside, pa.string())], names=["g", "v", "inside"])

    inside = rows_by(held, np.arange(m), inner, "g long, v long, inside string", members)
    return store.keep(tops.join(inside, "g").selectExpr("v", "concat(path, inside) AS path"))
