"""Repeated byte strings by bucket-pointer refinement over sampled suffixes.

Every string of WIDTH bytes holds an anchor: the position of its smallest 32-byte bucket identifier, leftmost on ties.
Equal strings have their anchors at equal places, so only suffixes that start around a common anchor need comparing.

1. Identifiers. A position's bucket at 8 bytes is those bytes; the bucket at twice the length comes from the
   identifiers at the position and at a later offset, and so on to 100 bytes: each refinement reuses the last one's.
2. Initial buckets. Windows that share an anchor form one item: a run of starts. Items are dealt by the anchor's 32-byte
   bucket and refined by the 100-byte identifiers of their first and last windows, which cover the item's whole string.
   Of items with one such string all but the earliest are repeats as a whole.
3. Where a bucket still holds different strings, it is refined by the identifiers at the offsets 32 bytes before and
   after the anchor, one of which every window covers; the windows of what is left are compared one by one by a 128-bit
   digest of their bytes.

Repeats within a batch are settled there, so a string that many documents hold reaches its bucket once for each batch.
A task streams over sorted buckets and keeps a few numbers.

Results: null and empty texts have no bytes; texts shorter than WIDTH lose nothing; rows without an id have no place
before or after others, so they lose nothing and take nothing from others; rows that repeat an id are one document, of which none is earlier; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veilwalk.llm.common import Scratch, text_buffer

WIDTH = 100
GRAM = 32
#: Window starts of one slice of bytes.
SLICE = 1 << 20
K1, K2, K3 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0x165667B19E3779F9)
S29, S32, ONE = np.uint64(29), np.uint64(32), np.uint64(1)


def refine(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Identifiers of longer strings from identifiers at a position and at a later offset."""
    x = a * K1
    x += b
    x ^= x >> S29
    x *= K2
    x ^= x >> S32
    return x


def identifiers(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Identifiers of the 32-byte and 100-byte strings at each position of raw (at least 100 bytes)."""
    h = np.array(np.ndarray((len(raw) - 7,), "<u8", np.ascontiguousarray(raw), 0, (1,)))
    h = refine(h[:-8], h[8:])
    h32 = refine(h[:-16], h[16:])
    h = refine(h32[:-32], h32[32:])
    return h32, refine(h[:-36], h[36:])


def leftmost_least(h: np.ndarray, width: int) -> np.ndarray:
    """For each window of width values, the position of its smallest, leftmost on ties."""
    at, value, have = np.arange(len(h), dtype=np.int32), h, 1
    while have < width:
        step = min(have, width - have)
        right = value[step:] < value[: len(value) - step]
        at = np.where(right, at[step:], at[: len(at) - step])
        value = np.where(right, value[step:], value[: len(value) - step])
        have += step
    return at


def items(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, ...]:
    """(bucket, string, document index, first start, number of starts, sides) of all items of documents laid end to end.

    sides holds 32 bits each of the identifiers of the 32 bytes before and after the anchor, 0 where the item ends first.
    """
    out = []
    for c in range(0, max(len(raw) - WIDTH + 1, 0), SLICE):
        part = raw[c : c + SLICE + WIDTH - 1]
        starts = len(part) - WIDTH + 1
        d = slice(max(np.searchsorted(offsets, c, "right") - 1, 0), np.searchsorted(offsets, c + starts, "left"))
        lo = np.clip(offsets[:-1][d] - c, 0, starts)
        hi = np.clip(offsets[1:][d] - (WIDTH - 1) - c, 0, starts)
        mark = np.zeros(starts + 1, np.int32)
        good = hi > lo
        np.add.at(mark, lo[good], 1)
        np.add.at(mark, hi[good], -1)
        s = np.flatnonzero(np.cumsum(mark[:-1]) > 0)
        if not len(s):
            continue
        h32, h100 = identifiers(part)
        anchor = leftmost_least(h32, WIDTH - GRAM + 1)[s]
        new = np.r_[True, (np.diff(anchor) != 0) | (np.diff(s) != 1)]
        first = np.flatnonzero(new)
        n = np.diff(np.r_[first, len(s)])
        s0 = s[first]
        string = refine(h100[s0], h100[s0 + n - 1] ^ (n.astype(np.uint64) * K3))
        doc = np.searchsorted(offsets, s0 + c, "right") - 1
        p = anchor[first]
        before = np.where(p - GRAM >= s0, h32[np.maximum(p - GRAM, 0)] >> S32 | ONE, 0)
        after = np.where(p + 2 * GRAM <= s0 + n + WIDTH - 1, h32[np.minimum(p + GRAM, len(h32) - 1)] >> S32 | ONE, 0)
        out.append((h32[p], string, doc, s0 + c - offsets[doc], n, (before.astype(np.uint64) << S32 | after.astype(np.uint64)).view(np.int64)))
    kinds = (np.uint64, np.uint64, np.int64, np.int64, np.int64, np.int64)
    return tuple(np.concatenate(x) if x else np.zeros(0, k) for x, k in zip(list(zip(*out, strict=True)) or [()] * 6, kinds, strict=True))


ROWS = "q long, u long, doc long, place long"


def _settle(q: np.ndarray, u: np.ndarray, doc: np.ndarray, place: np.ndarray, sides: np.ndarray | None = None) -> pa.RecordBatch:
    """Rows of a batch with its own repeats settled: those have a negative place and a bucket that spreads them."""
    order = np.lexsort((place, doc, u, q))
    q, u, doc, place = q[order], u[order], doc[order], place[order]
    new = np.r_[True, (q[1:] != q[:-1]) | (u[1:] != u[:-1])] if len(q) else np.zeros(0, bool)
    rep = np.maximum.accumulate(np.where(new, np.arange(len(q)), 0)) if len(q) else np.zeros(0, np.int64)
    later = (doc != doc[rep]) | (place != place[rep])
    keep = new | later
    place, q, u = np.where(later, ~place, place), np.where(later, refine(doc.astype(np.uint64), place.astype(np.uint64)), q), np.where(later, np.uint64(0), u)
    cols = [q.view(np.int64)[keep], u.view(np.int64)[keep], doc[keep], place[keep]]
    names = ["q", "u", "doc", "place"]
    if sides is not None:
        cols, names = [*cols, np.where(later, 0, sides[order])[keep]], [*names, "sides"]
    return pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=names)


def _lonely(bucket: np.ndarray, sides: np.ndarray, candidates: np.ndarray) -> np.ndarray:
    """True for candidates that agree with no other of their bucket in the bytes before or after the anchor.

    A window has 68 bytes besides its anchor's 32, so it holds all 32 before the anchor or all 32 after it: without
    agreement there no window of the item can occur in another item.
    """
    at = np.flatnonzero(candidates)
    agrees = np.zeros(len(at), bool)
    for side in (sides[at] >> 32 & 0xFFFFFFFF, sides[at] & 0xFFFFFFFF):
        key = refine(bucket[at].astype(np.uint64), side.astype(np.uint64))
        _, group, size = np.unique(key, return_inverse=True, return_counts=True)
        agrees |= (side != 0) & (size[group] > 1)
    out = np.zeros(len(bucket), bool)
    out[at] = ~agrees
    return out


def _decided(rows: DataFrame) -> DataFrame:
    """(doc, place): repeats; with a negative place, the earliest items of buckets that hold several strings.

    place is the first start times 128 plus the number of starts.
    """
    dealt = rows.repartition("q").sortWithinPartitions("q", "u", "doc", "place")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last = None  # bucket, string, its earliest item; the bucket's first item and whether it was handed on
        for b in batches:
            q, u, doc, place = (b.column(k).to_numpy() for k in range(4))
            known = place < 0
            docs, places = [doc[known]], [~place[known]]
            sides = b.column(4).to_numpy()[~known] if b.num_columns > 4 else None
            q, u, doc, place = q[~known], u[~known], doc[~known], place[~known]
            if len(q):
                if last is None:
                    last = [q[0] - 1 if q[0] > -(1 << 62) else q[0] + 1, 0, 0, 0, 0, 0, True]
                lq, lu, rd, rp, fd, fp, told = last
                newq = np.r_[q[0] != lq, q[1:] != q[:-1]]
                newu = newq | np.r_[u[0] != lu, u[1:] != u[:-1]]
                at = np.maximum.accumulate(np.where(newu, np.arange(len(q)), -1))
                rep_doc, rep_place = np.where(at < 0, rd, doc[at]), np.where(at < 0, rp, place[at])
                later = ~newu & ((doc != rep_doc) | (place != rep_place))
                docs.append(doc[later])
                places.append(place[later])
                bucket = np.cumsum(newq)
                strings = np.bincount(bucket, newu)
                mixed = newu & ((bucket == 0) | (strings[bucket] > 1))
                if sides is not None:  # buckets that lie within the batch as a whole
                    mixed &= ~_lonely(bucket, sides, mixed & (bucket > 0) & (bucket < bucket[-1]))
                docs.append(doc[mixed])
                places.append(~place[mixed])
                if strings[0] and not told:
                    docs.append(np.array([fd]))
                    places.append(np.array([~fp]))
                    told = True
                if newq.any():
                    k = np.flatnonzero(newq)[-1]
                    fd, fp, told = doc[k], place[k], bool(strings[bucket[-1]] > 1)
                last = [q[-1], u[-1], rep_doc[-1], rep_place[-1], fd, fp, told]
            cols = [pa.array(np.concatenate(x).astype(np.int64)) for x in (docs, places)]
            yield pa.RecordBatch.from_arrays(cols, names=["doc", "place"])

    return dealt.mapInArrow(run, "doc long, place long")


def _spans(places: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs of bytes that the windows of places cover."""
    start, n = places >> 7, places & 127
    order = np.argsort(start, kind="stable")
    start, end = start[order], np.maximum.accumulate((start + n - 1 + WIDTH)[order])
    new = np.r_[True, start[1:] > end[:-1]]
    first = np.flatnonzero(new)
    return start[first], end[np.r_[first[1:] - 1, len(start) - 1]]


def _lists(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Values and n+1 offsets of a list column; nulls are empty."""
    lengths = column.value_lengths().fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.int64), np.r_[0, np.cumsum(lengths)]


RESULT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"


def repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, DataFrame]:
    """The texts (doc, text) and the repeated windows of each document (doc, places)."""
    scratch = Scratch(docs.sparkSession, "suffixes")
    source = docs.select(docs[id_col].cast("long").alias("doc"), docs[text_col].alias("text"))

    def sample(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            raw, offsets = text_buffer(b.column(1))
            q, u, doc, start, n, sides = items(raw, offsets)
            yield _settle(q, u, b.column(0).to_numpy()[doc], start * 128 + n, sides)

    decided = scratch.save(_decided(source.where("doc is not null").mapInArrow(sample, ROWS + ", sides long")), "decided")
    whole = decided.where("place >= 0")
    open_ = decided.where("place < 0").groupBy("doc").agg(F.collect_list(F.bitwise_not("place")).alias("places"))

    def windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            raw, offsets = text_buffer(b.column(1))
            values, ends = _lists(b.column(2))
            data, ids = raw.tobytes(), b.column(0).fill_null(0).to_numpy()  # rows without an id have no places
            digests, doc, place = [], [], []
            for k in np.flatnonzero(np.diff(ends)):
                base = int(offsets[k])
                for p in values[ends[k] : ends[k + 1]].tolist():
                    s, n = base + (p >> 7), p & 127
                    digests += [xxhash.xxh3_128_digest(data[x : x + WIDTH]) for x in range(s, s + n)]
                    place += [(x - base) * 128 + 1 for x in range(s, s + n)]
                    doc += [ids[k]] * n
            pair = np.frombuffer(b"".join(digests), np.uint64).reshape(-1, 2)
            yield _settle(pair[:, 0].copy(), pair[:, 1].copy(), np.array(doc, np.int64), np.array(place, np.int64))

    text = source  # the join below deals the same columns by the same key twice; Spark deals them once
    opened = text.join(open_, "doc", "left").select("doc", "text", "places")
    single = _decided(opened.mapInArrow(windows, ROWS)).where("place >= 0")
    places = whole.union(single).groupBy("doc").agg(F.collect_list("place").alias("places"))
    return text, places


def removed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256): what is left when all repeated bytes are gone."""
    text, places = repeats(docs, id_col, text_col)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            raw, offsets = text_buffer(b.column(1))
            values, ends = _lists(b.column(2))
            rows = []
            for k in range(b.num_rows):
                part = raw[offsets[k] : offsets[k + 1]]
                if ends[k] == ends[k + 1]:
                    rows.append((len(part), 0, 0, hashlib.sha256(part).hexdigest()))
                    continue
                s, e = _spans(values[ends[k] : ends[k + 1]])
                e = np.minimum(e, len(part))
                digest = hashlib.sha256()
                for x, y in zip([0, *e.tolist()], [*s.tolist(), len(part)], strict=True):
                    digest.update(part[x:y])
                rows.append((len(part), int((e - s).sum()), len(s), digest.hexdigest()))
            cols = list(zip(*rows, strict=True)) or [()] * 4
            kinds = [pa.int64()] * 3 + [pa.string()]
            yield pa.RecordBatch.from_arrays([b.column(0), *[pa.array(c, t) for c, t in zip(cols, kinds, strict=True)]], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    return text.join(places, "doc", "left").select("doc", "text", "places").mapInArrow(cut, RESULT)


def cleaned(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text): texts without their repeated bytes; bytes that no longer form a character are left out."""
    text, places = repeats(docs, id_col, text_col)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            raw, offsets = text_buffer(b.column(1))
            values, ends = _lists(b.column(2))
            kept = []
            for k in range(b.num_rows):
                part = raw[offsets[k] : offsets[k + 1]].tobytes()
                if ends[k] < ends[k + 1]:
                    s, e = _spans(values[ends[k] : ends[k + 1]])
                    part = b"".join(part[x:y] for x, y in zip([0, *e.tolist()], [*s.tolist(), len(part)], strict=True))
                kept.append(part.decode("utf-8", "ignore"))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(kept, pa.string())], names=["doc_id", "text"])

    return text.join(places, "doc", "left").select("doc", "text", "places").mapInArrow(cut, "doc_id long, text string")
