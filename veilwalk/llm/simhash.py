"""SimHash near-duplicates with multi-index hashing.

A fingerprint has one bit per bit position of the shingles' 64-bit hashes, by majority. Pairs within three differing
bits are found through two 32-bit segments: three differences leave one segment with at most one, so each fingerprint
enters a table under its exact segment and looks up the Hamming ball of radius one around it. Of two segments one bit
apart just one has that bit set, so enumerating the ball over set bits alone meets every pair. All distances are
verified in full.

That finds near-exact copies. Documents that are alike (five-word shingles, similarity 0.8) may differ in more bits; alike()
takes fingerprints at most three bits apart as candidates, and others by bands of minima over the shingles' hashes, and
verifies each link by the exact similarity.

Results: null or blank text has fingerprint zero, which links like any other; components() gives rows without an id their
fingerprint and a null component, alike() leaves them out; rows that repeat an id are kept, each with its own
fingerprint; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veilwalk.llm.common import Forest, Scratch, arrow_map, connected_components, release, spread_join, text_buffer

#: Sketches of documents that are alike: 64-bit words, one bit for each minimum; minima of a band, bands, the
#: dissimilarity allowed; and the bits that may differ before a pair is not worth a look (at a similarity of 0.8: 25.6
#: expected, standard deviation 4.8, so five of them above).
WIDE, BAND, BANDS, UNLIKE, FAR = 4, 3, 21, 0.2, 51
MINIMA = 64 * WIDE
#: Runs of one band up to this size give all their pairs, larger ones pairs that span them.
SPANNED_RUN = 64
#: Rows whose minima are held at once.
SKETCHED = 512
#: Shingles of one tile of a family.
CHUNK = 1 << 19

SEED = 42
MAX_BITS = 3
#: Runs of one key up to this size are compared as they are; larger ones go through the bytes of the other segment.
DIRECT_RUN = 4096
BLOCK = 1 << 16


def shingle_hashes(data: bytes, width: int) -> np.ndarray:
    """Hashes of all shingles of UTF-8 text; A-Z is lowered, words end at ASCII white space."""
    words = data.lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    n = len(words) - width + 1
    shingles = [b" ".join(words)] if n < 1 else [b" ".join(words[i : i + width]) for i in range(n)]
    return np.fromiter((xxhash.xxh64_intdigest(s, SEED) for s in shingles), np.uint64, len(shingles))


def majority(hashes: np.ndarray) -> int:
    """A bit is set where more than half of the hashes have it."""
    ones = np.zeros(64, np.int64)
    for at in range(0, len(hashes), BLOCK):
        part = hashes[at : at + BLOCK].astype("<u8").view(np.uint8).reshape(-1, 8)
        ones += np.unpackbits(part, axis=1, bitorder="little").sum(0, dtype=np.int64)
    bits = np.packbits(2 * ones > len(hashes), bitorder="little")
    return int(bits.view("<u8")[0])


def fingerprint(data: bytes, width: int = 3) -> int:
    return majority(shingle_hashes(data, width))


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ x >> np.uint64(30)) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ x >> np.uint64(27)) * np.uint64(0x94D049BB133111EB)
    return x ^ x >> np.uint64(31)


#: Fixed values of the functions whose minima are taken.
XORS, FACTORS = (_mixed(np.arange(at, at + MINIMA, dtype=np.uint64))[:, None] for at in (1, 1001))
FACTORS |= np.uint64(1)


def minima(hashes: np.ndarray) -> np.ndarray:
    """The least value over the hashes of each of MINIMA functions; two sets share one with the chance of their Jaccard similarity."""
    least = np.full(MINIMA, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(hashes), 256):
        least = np.minimum(least, ((hashes[at : at + 256] ^ XORS) * FACTORS).min(1))
    return least


def band_keys(least: np.ndarray) -> np.ndarray:
    """A key for each BAND minima of rows of minima, different in each band."""
    parts = least[:, : BANDS * BAND].reshape(len(least), BANDS, BAND)
    key = np.broadcast_to(np.arange(BANDS, dtype=np.uint64), parts.shape[:2])
    for k in range(BAND):
        key = _mixed(key * np.uint64(0x9E3779B97F4A7C15) + parts[:, :, k])
    return key


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3) -> DataFrame:
    """(doc_id, fp): fp is the fingerprint as a signed 64-bit integer."""

    def run(b: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        raw, offsets = text_buffer(b.column(1))
        data = memoryview(raw)
        fps = [fingerprint(bytes(data[s:e]), width) for s, e in zip(offsets[:-1], offsets[1:], strict=True)]
        yield pa.RecordBatch.from_arrays([b.column(0), pa.array(np.array(fps, np.uint64).view(np.int64))], names=["doc_id", "fp"])

    return arrow_map(docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col]), run, "doc_id long, fp long")


def segment_keys(fps: DataFrame) -> DataFrame:
    """Table and ball entries of distinct fingerprints: key is segment number and segment value."""
    halves = fps.select("fp", F.explode(F.array(
        F.struct(F.lit(0).alias("seg"), F.col("fp").bitwiseAND(0xFFFFFFFF).alias("half")),
        F.struct(F.lit(1).alias("seg"), F.shiftrightunsigned("fp", 32).alias("half")),
    )).alias("s")).select("fp", F.shiftleft(F.col("s.seg").cast("long"), 32).alias("seg"), F.col("s.half").alias("half"))
    masks = F.array(F.lit(0).cast("long"), *[F.lit(1 << b).cast("long") for b in range(32)])
    ball = halves.select("fp", "seg", "half", F.explode(masks).alias("mask"))
    ball = ball.where(F.col("half").bitwiseAND(F.col("mask")) == F.col("mask"))
    return ball.select(F.col("seg").bitwiseOR(F.col("half") - F.col("mask")).alias("key"), "fp", (F.col("mask") != 0).alias("probe"))


def _spanning(fps: np.ndarray, limit: int) -> list[tuple[int, int]]:
    """Links that span the components of fps (uint64) at most limit bits apart; each found by breadth-first search."""
    rest, edges, queue = fps[1:], [], [fps[0]]
    while len(rest) or queue:
        if not queue:
            queue, rest = [rest[0]], rest[1:]
        x = queue.pop()
        if len(rest):
            near = np.bitwise_count(rest ^ x) <= limit
            if near.any():
                for y in rest[near]:
                    edges.append((x, y))
                    queue.append(y)
                rest = rest[~near]
    return edges


def run_links(fps: np.ndarray, limit: int = MAX_BITS) -> list[tuple[int, int]]:
    """Links among the fingerprints of one key that keep all its components together."""
    fps = np.unique(fps)
    if len(fps) < 2:
        return []
    if len(fps) <= DIRECT_RUN:
        return _spanning(fps, limit)
    edges: list[tuple[int, int]] = []
    parts = fps.astype("<u8").view(np.uint8).reshape(-1, 8)
    for k in range(8):  # at most three of eight bytes differ, so each link shares five of them
        order = np.argsort(parts[:, k], kind="stable")
        cuts = np.flatnonzero(np.diff(parts[order, k])) + 1
        for group in np.split(order, cuts):
            if len(group) > 1:
                edges += _spanning(fps[group], limit)
        if k == 3:
            break  # any four bytes hold one that is equal
    return edges


def links(fps: DataFrame, limit: int = MAX_BITS) -> DataFrame:
    """(a, b) links between distinct fingerprints that join every component of pairs at most three bits apart.

    Entries are dealt by key and sorted; a task streams over runs of one key. A run holds distinct fingerprints that
    agree in about half of their bits: 8 bytes each, whatever the number of copies.
    """
    entries = segment_keys(fps)
    entries = entries.repartition("key").sortWithinPartitions("key")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, vals, probes = np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, bool)

        def found(keys, vals, probes):
            cuts = np.flatnonzero(np.diff(keys)) + 1
            starts, ends = np.r_[0, cuts], np.r_[cuts, len(keys)]
            live = ends - starts > 1
            tables = np.r_[0, np.cumsum(~probes)]
            live &= tables[ends] > tables[starts]  # links meet at a table entry
            edges: list[tuple[int, int]] = []
            two = live & (ends - starts == 2)
            x, y = vals[starts[two]], vals[starts[two] + 1]
            near = (np.bitwise_count(x ^ y) <= limit) & (x != y)
            for s, e in zip(starts[live & ~two], ends[live & ~two], strict=True):
                edges += run_links(vals[s:e], limit)
            a = np.concatenate([x[near], np.array([p for p, _ in edges], np.uint64)])
            c = np.concatenate([y[near], np.array([q for _, q in edges], np.uint64)])
            return pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(c.view(np.int64))], names=["a", "b"])

        for b in batches:
            keys = np.concatenate([keys, b.column(0).to_numpy()])
            vals = np.concatenate([vals, b.column(1).to_numpy().view(np.uint64)])
            probes = np.concatenate([probes, b.column(2).to_numpy(zero_copy_only=False)])
            open_at = np.searchsorted(keys, keys[-1]) if len(keys) else 0
            if open_at:
                yield found(keys[:open_at], vals[:open_at], probes[:open_at])
                keys, vals, probes = keys[open_at:], vals[open_at:], probes[open_at:]
        if len(keys):
            yield found(keys, vals, probes)

    return entries.mapInArrow(run, "a long, b long")


def components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3, limit: int = MAX_BITS) -> DataFrame:
    """(doc_id, fp, component_id): component_id is the smallest id reachable by links.

    Copies collapse to one fingerprint before any pair is looked for; the links of a component span it rather than list
    all its pairs. Everything that is iterated is keyed by fingerprint and kept in shared tables.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "simhash")
    fps = scratch.save(fingerprints(docs, id_col, text_col, width), "fps")
    distinct = scratch.save(fps.where("doc_id is not null").groupBy("fp").agg(F.min("doc_id").alias("first_id")), "distinct")
    roots = connected_components(links(distinct.select("fp"), limit), scratch).withColumnsRenamed({"node": "fp"})
    ids = distinct.join(roots, "fp", "left").select("fp", "first_id", F.coalesce("root", "fp").alias("root"))
    least = ids.groupBy("root").agg(F.min("first_id").alias("component_id"))
    ids = ids.join(least, "root").select("fp", "component_id")
    component = F.when(F.col("doc_id").isNotNull(), F.col("component_id"))
    return spread_join(fps, ids, "fp", ["doc_id"], "left").select("doc_id", "fp", component.alias("component_id"))


def fingerprint_hex(fp: F.Column) -> F.Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def _node(kinds: np.ndarray) -> int:
    """Number of a set of shingles, given its sorted distinct hashes."""
    return xxhash.xxh64_intdigest(kinds.astype("<u8").tobytes(), SEED)


def sketches(docs: DataFrame, id_col: str, text_col: str, width: int) -> DataFrame:
    """(doc_id, fp, node, kinds, w0..w3, keys): the row's fingerprint, and number, size, bits of the minima and band keys of its set of shingles; no keys without words."""
    names = [f"w{k}" for k in range(WIDE)]

    def part(b: pa.RecordBatch) -> pa.RecordBatch:
        raw, offsets = text_buffer(b.column(1))
        data, n = memoryview(raw), b.num_rows
        nodes, least, size, fps = np.zeros(n, np.uint64), np.zeros((n, MINIMA), np.uint64), np.zeros(n, np.int64), np.zeros(n, np.uint64)
        for i, (s, e) in enumerate(zip(offsets[:-1], offsets[1:], strict=True)):
            kinds = np.unique(shingle_hashes(bytes(data[s:e]), width))
            nodes[i], least[i], size[i], fps[i] = _node(kinds), minima(kinds), len(kinds), fingerprint(bytes(data[s:e]))
        bits = (_mixed(least) & np.uint64(1)).astype(np.uint8)
        words = np.packbits(bits, axis=1, bitorder="little").view("<i8").reshape(n, WIDE)
        keys, full = band_keys(least).view(np.int64), size > 0
        ends = np.r_[0, np.cumsum(full * BANDS)].astype(np.int32)
        cols = [pa.array(fps.view(np.int64)), pa.array(nodes.view(np.int64)), pa.array(size), *[pa.array(words[:, k].copy()) for k in range(WIDE)], pa.ListArray.from_arrays(pa.array(ends), pa.array(keys[full].ravel()))]
        return pa.RecordBatch.from_arrays([b.column(0), *cols], names=["doc_id", "fp", "node", "kinds", *names, "keys"])

    def run(b: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        for at in range(0, b.num_rows, SKETCHED):
            yield part(b.slice(at, SKETCHED))

    rows = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col]).where("doc_id is not null")
    return arrow_map(rows, run, "doc_id long, fp long, node long, kinds long, " + ", ".join(f"{n} long" for n in names) + ", keys array<long>")


def _far(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Differing bits of rows of words."""
    return np.bitwise_count(a ^ b).sum(-1, dtype=np.int64)


def _wide_spanning(ids: np.ndarray, fps: np.ndarray, limit: int) -> list[tuple[int, int]]:
    """Links that span the components of the fingerprints of one key, by breadth-first search."""
    _, first = np.unique(ids, return_index=True)
    ids, fps = ids[first], fps[first]
    rest, edges, queue = np.arange(1, len(ids)), [], [0]
    while len(rest) or queue:
        if not queue:
            queue, rest = [int(rest[0])], rest[1:]
        x = queue.pop()
        if len(rest):
            near = _far(fps[rest], fps[x]) <= limit
            if near.any():
                edges += [(int(ids[x]), int(ids[y])) for y in rest[near]]
                queue += rest[near].tolist()
                rest = rest[~near]
    return edges


def _wide_links(keys: np.ndarray, probes: np.ndarray, ids: np.ndarray, fps: np.ndarray, limit: int, direct: int = 256) -> list[tuple[int, int]]:
    """Links of all runs of equal keys: table entries against all entries of their run; runs beyond direct by search."""
    cuts = np.flatnonzero(np.diff(keys)) + 1
    starts, ends = np.r_[0, cuts], np.r_[cuts, len(keys)]
    size, edges = ends - starts, []
    for s, e in zip(starts[size > direct], ends[size > direct], strict=True):
        edges += _wide_spanning(ids[s:e], fps[s:e], limit)
    run = np.repeat(np.arange(len(size)), size)
    tables = np.flatnonzero(~probes & (size[run] <= direct) & (size[run] > 1))
    for at in range(0, len(tables), 20_000):
        t = tables[at : at + 20_000]
        n = size[run[t]]
        left = np.repeat(t, n)
        right = np.arange(len(left)) - np.repeat(np.cumsum(n) - n, n) + np.repeat(starts[run[t]], n)
        near = (ids[left] != ids[right]) & (_far(fps[left], fps[right]) <= limit)
        edges += np.unique(np.c_[ids[left[near]], ids[right[near]]], axis=0).tolist()
    return edges


def _runs(batches: Iterator[pa.RecordBatch], names: list[str]) -> Iterator[list[np.ndarray]]:
    """Columns key, names... of sorted rows, cut so that no run of equal keys is parted."""
    held: list[np.ndarray] = []
    for b in batches:
        new = [b.column(n).to_numpy() for n in ["key", *names]]
        held = [np.concatenate(x) for x in zip(held, new, strict=True)] if held else new
        open_at = int(np.searchsorted(held[0], held[0][-1])) if len(held[0]) else 0
        if open_at:
            yield [x[:open_at] for x in held]
            held = [x[open_at:] for x in held]
    if held and len(held[0]):
        yield held


class Sets:
    """Sets of shingles in one task, their tokens numbered from the rarest to the most frequent one."""

    def __init__(self, sets: list[np.ndarray], least: float):
        self.least, self.size = least, np.array([len(x) for x in sets], np.int64)
        self.ends = np.cumsum(self.size)
        _, token, often = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
        rank = np.empty(len(often), np.int64)
        rank[np.argsort(often, kind="stable")] = np.arange(len(often))
        owner = np.repeat(np.arange(len(sets)), self.size)
        order = np.lexsort((rank[token], owner))
        self.tokens = rank[token][order]
        self.common = np.add.reduceat(often[token], np.r_[0, self.ends[:-1]]) / self.size
        # Sets this similar share one of the rarest tokens of each: as many as may miss in the other one, and one more.
        self.lead = self.size - np.ceil(least * self.size - 1e-9).astype(np.int64) + 1
        place = np.arange(len(owner)) - np.repeat(self.ends - self.size, self.size)
        leading = place < np.repeat(self.lead, self.size)
        by_token = np.argsort(self.tokens[leading], kind="stable")
        self.holders = owner[leading][by_token]
        self.holder_ends = np.cumsum(np.bincount(self.tokens[leading], minlength=len(often)))
        self.holder_starts = np.r_[0, self.holder_ends[:-1]]
        self.mark = np.zeros(len(often), bool)

    def of(self, i: int) -> np.ndarray:
        return self.tokens[self.ends[i] - self.size[i] : self.ends[i]]

    def candidates(self, i: int) -> np.ndarray:
        lead = self.of(i)[: self.lead[i]]
        return np.unique(_ranges(self.holders, self.holder_starts[lead], self.holder_ends[lead]))

    def alike(self, i: int, others: np.ndarray) -> np.ndarray:
        """Those others whose similarity to set i is at least the limit."""
        small, large = np.minimum(self.size[others], self.size[i]), np.maximum(self.size[others], self.size[i])
        others = others[small >= self.least * large - 1e-9]
        if not len(others):
            return others
        self.mark[self.of(i)] = True
        held = self.mark[_ranges(self.tokens, self.ends[others] - self.size[others], self.ends[others])]
        both = np.add.reduceat(held.astype(np.int64), np.r_[0, np.cumsum(self.size[others])[:-1]])
        self.mark[self.of(i)] = False
        return others[both >= self.least * (self.size[i] + self.size[others] - both) - 1e-9]


def _ranges(values: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Slices of values laid end to end."""
    n = ends - starts
    return values[np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + np.repeat(starts, n)]


def spanning_sets(sets: list[np.ndarray], side: np.ndarray | None, least: float) -> list[tuple[int, int]]:
    """Links (indices) that join the components of pairs with at least that Jaccard similarity, each of them exact.

    With sides only pairs of both sides count. The sets that share most with others lead, so that copies of one text
    join it first; what is joined already is not compared again. No pair is left out.
    """
    s, component, open_, edges = Sets(sets, least), np.arange(len(sets)), np.ones(len(sets), bool), []
    for i in np.argsort(-s.common, kind="stable"):
        open_[i] = False
        near = s.candidates(i)
        near = near[open_[near] & (component[near] != component[i])]
        if side is not None:
            near = near[side[near] != side[i]]
        for j in s.alike(i, near):
            if component[j] != component[i]:
                component[component == component[j]] = component[i]
                edges.append((int(i), int(j)))
    return edges


def print_links(prints: DataFrame) -> DataFrame:
    """(a, b) links of nodes by their fingerprints (fp, node): of one fingerprint, or of two at most MAX_BITS apart."""
    one = prints.groupBy("fp").agg(F.min("node").alias("first"))
    same = prints.join(one, "fp").where("node <> first").select(F.col("node").alias("a"), F.col("first").alias("b"))
    apart = links(one.select("fp")).withColumnsRenamed({"a": "x", "b": "y"}).distinct()
    a, b = (one.select(F.col("fp").alias(x), F.col("first").alias(n)) for x, n in (("x", "a"), ("y", "b")))
    return same.unionByName(apart.join(a, "x").join(b, "y").where("a <> b").select("a", "b"))


def alike(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, unlike: float = UNLIKE) -> DataFrame:
    """(doc_id, component_id) of documents linked where the Jaccard similarity of their shingles is at least 1 - unlike.

    Equal sets of shingles collapse before. Sets of documents whose fingerprints are at most MAX_BITS apart, and sets that
    agree in a segment of three minima and differ in at most FAR bits of their sketches, form families; of pairs at a similarity of 0.8 fewer than one in a million fall to different ones.
    Within a family links are found by exact similarity, a pair of tiles at a time: a set is dealt once for each tile of
    its family, and no pair of sets is ever a row.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "alike")
    names, least = [f"w{k}" for k in range(WIDE)], 1 - unlike
    rows = scratch.save(sketches(docs, id_col, text_col, width), "rows")
    nodes = scratch.save(rows.groupBy("node").agg(F.min("doc_id").alias("first_id"), *[F.first(c).alias(c) for c in ("kinds", *names, "keys")]), "nodes")
    dealt = nodes.select(F.explode("keys").alias("key"), "node", *names).repartition("key").sortWithinPartitions("key")

    def join(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for key, node, *words in _runs(batches, ["node", *names]):
            forest = Forest()
            forest.add(_wide_links(key, np.zeros(len(key), bool), node, np.stack(words, 1).view(np.uint64), FAR, SPANNED_RUN))
            e = forest.stars()
            yield pa.RecordBatch.from_arrays([pa.array(e[:, 0].copy()), pa.array(e[:, 1].copy())], names=["a", "b"])
        release()

    prints = scratch.save(rows.where("kinds > 0").select("fp", "node").distinct(), "prints")
    families = connected_components(dealt.mapInArrow(join, "a long, b long").unionByName(print_links(prints)), scratch)
    members = families.join(nodes.select("node", "first_id", "kinds"), "node").withColumnRenamed("root", "family")
    tiles = members.groupBy("family").agg(F.ceil(F.sum("kinds") / CHUNK).alias("tiles"))
    members = scratch.save(members.join(tiles, "family").select("node", "family", "first_id", "tiles"), "members")
    wanted = members.select("first_id").distinct()
    texts_of = docs.select(docs[id_col].cast("long").alias("first_id"), docs[text_col].alias("text")).join(wanted, "first_id", "left_semi")

    def sets(b: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        raw, offsets = text_buffer(b.column(1))
        data = memoryview(raw)
        kinds = [np.unique(shingle_hashes(bytes(data[s:e]), width)) for s, e in zip(offsets[:-1], offsets[1:], strict=True)]
        found = pa.array(np.array([_node(x) for x in kinds], np.uint64).view(np.int64))
        yield pa.RecordBatch.from_arrays([found, pa.array([x.tobytes() for x in kinds], pa.binary())], names=["node", "set"])

    held = arrow_map(texts_of, sets, "node long, set binary").join(members.select("node", "family", "tiles"), "node")
    held = held.withColumn("tile", F.pmod(F.xxhash64("node"), "tiles")).withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("tiles") - 1)))
    held = held.select("family", F.least("tile", "other").alias("i"), F.greatest("tile", "other").alias("j"), "tile", "node", "set")

    def links(t: pa.Table) -> pa.Table:
        node, first = np.unique(t["node"].to_numpy(), return_index=True)  # rows that repeat an id repeat its set
        side = t["tile"].to_numpy()[first] if t["i"][0].as_py() != t["j"][0].as_py() else None
        column = t["set"].combine_chunks()
        found = spanning_sets([np.frombuffer(column[int(k)].as_buffer(), np.uint64) for k in first], side, least) if len(node) > 1 else []
        e = np.array(found, np.int64).reshape(-1, 2)
        return pa.table([pa.array(node[e[:, 0]]), pa.array(node[e[:, 1]])], names=["a", "b"])

    linked = held.groupBy("family", "i", "j").applyInArrow(links, "a long, b long")
    roots = connected_components(linked, Scratch(spark, "alike"))
    ids = nodes.select("node", "first_id").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    names_of = ids.groupBy("root").agg(F.min("first_id").alias("component_id"))
    ids = ids.join(names_of, "root").select("node", "component_id")
    return spread_join(rows.select("doc_id", "node"), ids, "node", ["doc_id"]).select("doc_id", "component_id")


def keep_first(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", groups: DataFrame | None = None) -> DataFrame:
    """One row of docs for each group of alike documents: that of the smallest id. Rows without an id are kept.

    groups (doc_id, component_id) are those of alike() unless given. Rows that repeat a kept id are all kept: they are
    the same document.
    """
    groups = alike(docs, id_col, text_col) if groups is None else groups
    keep = groups.where("doc_id = component_id").select(F.col("doc_id").alias("_kept")).distinct()
    return docs.join(keep, docs[id_col].cast("long") == keep["_kept"], "left_semi").unionByName(docs.where(docs[id_col].isNull()))
