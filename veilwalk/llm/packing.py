"""Best-fit decreasing packing of token sequences.

Lengths are whole numbers up to the capacity, so documents of one length are alike and the driver packs counts of
lengths, not documents: a segment tree over remaining capacities finds the tightest open bin in logarithmic time, and
bins that look alike are kept as one run. The outcome is that of best-fit decreasing over all documents one by one.
Its plan is a list of intervals of positions in the order of decreasing length; executors look their rows up in it.
The plan grows with the capacity, not with the documents.

Results: null and empty texts are documents of the end id alone; rows that repeat an id are packed each on their own;
rows without an id are packed with a null id; an empty table gives no sequences; very long texts are cut into pieces.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from veilwalk.llm.common import Scratch, arrow_map, numbered
from veilwalk.llm.tokens import default_path, encoder

CAPACITY = 2048
VOCABULARY = "byte_bpe_50k.json"
END_ID = 0


class CapacityTree:
    """Segment tree over remaining capacities; a leaf is set while bins with that much room are open."""

    def __init__(self, capacity: int):
        self.leaves = 1 << (capacity + 1).bit_length()
        self.open = [False] * (2 * self.leaves)

    def mark(self, room: int, is_open: bool) -> None:
        i = self.leaves + room
        self.open[i] = is_open
        while i > 1:
            i //= 2
            self.open[i] = self.open[2 * i] or self.open[2 * i + 1]

    def tightest(self, need: int) -> int | None:
        """The smallest open room of at least need."""
        i = self.leaves + need
        if self.open[i]:
            return need
        while i > 1:
            if i % 2 == 0 and self.open[i + 1]:
                i += 1
                break
            i //= 2
        else:
            return None
        while i < self.leaves:
            i = 2 * i if self.open[2 * i] else 2 * i + 1
        return i - self.leaves


def plan(counts: dict[int, int], capacity: int = CAPACITY) -> tuple[np.ndarray, int]:
    """Rows (first position, first bin, items in each bin, offset of the first item, length) and the number of bins.

    Positions run over items by decreasing length. A row covers the positions up to the next row's.
    """
    tree, runs, rows, bins, pos = CapacityTree(capacity), {}, [], 0, 0

    def put(room: int, first: int, n: int) -> None:
        if n and room:
            if not runs.get(room):
                runs[room] = []
                tree.mark(room, True)
            runs[room].append((first, n))

    for length in sorted(counts, reverse=True):
        left = counts[length]
        while left:
            room = tree.tightest(length)
            if room is None:
                room, first, n = capacity, bins, -(-left // (capacity // length))
                bins += n
            else:
                first, n = runs[room].pop()
                if not runs[room]:
                    tree.mark(room, False)
            each = room // length
            full = min(n, left // each)
            over = min(left - full * each, each - 1) if full < n else 0
            offset = capacity - room
            if full:
                rows.append((pos, first, each, offset, length))
                pos, left = pos + full * each, left - full * each
                put(room - each * length, first, full)
            if over:
                rows.append((pos, first + full, each, offset, length))
                pos, left = pos + over, left - over
                put(room - over * length, first + full, 1)
            put(room, first + full + bool(over), n - full - bool(over))
    return np.array(rows, np.int64).reshape(-1, 5), bins


def pieces(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", path: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32): whole documents, and pieces of those longer than the capacity."""
    path = path or default_path(VOCABULARY)
    def run(b: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        out: list[tuple] = []
        for doc, ids in zip(b.column(0).to_pylist(), encoder(path).encode_column(b.column(1), END_ID), strict=True):
            n = len(ids)
            cuts = [0, *range(n % capacity or capacity, n + 1, capacity)] if n > capacity else [0, n]
            for k, (s, e) in enumerate(zip(cuts, cuts[1:], strict=False)):
                out.append((doc, k, s, e - s, zlib.crc32(ids[s:e])))
        cols = list(zip(*out, strict=True)) or [()] * 5
        kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
        names = ["doc_id", "piece", "start", "length", "ids_crc32"]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names=names)

    rows = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col])
    return arrow_map(rows, run, "doc_id long, piece int, start long, length long, ids_crc32 long")


def pack(items: DataFrame, capacity: int = CAPACITY, order: tuple[str, ...] = ("doc_id", "piece")) -> DataFrame:
    """Rows of items (column length, 1 to capacity) with sequence_id and offset added."""
    scratch = Scratch(items.sparkSession, "packing")
    kept = scratch.save(items, "items")  # range partitioning reads its input twice
    ranked = numbered(kept.withColumn("_shorter", -F.col("length")), scratch, "pieces", ["_shorter", *order]).drop("_shorter")
    counts = {r["length"]: r["n"] for r in ranked.groupBy("length").agg(F.count("*").alias("n")).collect()}
    rows, _ = plan(counts, capacity)
    own = items.columns
    names = [*own, "sequence_id", "offset"]

    def run(b: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        pos = b.column(b.schema.get_field_index("pos")).to_numpy()
        first, base, each, offset, length = rows[np.searchsorted(rows[:, 0], pos, "right") - 1].T
        seq, at = base + (pos - first) // each, offset + (pos - first) % each * length
        cols = [b.column(b.schema.get_field_index(c)) for c in own]
        yield pa.RecordBatch.from_arrays([*cols, pa.array(seq), pa.array(at)], names=names)

    schema = T.StructType([*items.schema.fields, T.StructField("sequence_id", T.LongType()), T.StructField("offset", T.LongType())])
    return arrow_map(ranked, run, schema)


def packed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", path: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    return pack(pieces(docs, id_col, text_col, path, capacity), capacity)
