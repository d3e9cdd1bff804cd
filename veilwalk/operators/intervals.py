"""Pairs of users with events close in time, counted without a shuffle of pairs."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Blocks of users at least, and events of a block on average before there are more of them.
LEAST_BLOCKS, BLOCK_EVENTS = 8, 1_000_000
#: Rows of a batch of results.
ROWS = 1 << 16


def _packed(values: np.ndarray) -> tuple[bytes, str]:
    """Whole numbers of at least 0 in the narrowest type that holds them."""
    kind = np.min_scalar_type(int(values.max()) if len(values) else 0)
    return values.astype(kind).tobytes(), kind.str


def _pack(events: pa.Table) -> pa.Table:
    """One row for a block of users: their ids, and the users (by place among ids) and steps in time of its events, by time."""
    t = events["t"].to_numpy()
    order = np.argsort(t, kind="stable")
    ids, users = np.unique(events["user_id"].to_numpy()[order], return_inverse=True)
    t = t[order]
    (users, user_kind), (steps, step_kind) = _packed(users), _packed(np.diff(t))
    cells = {"block": events["block"][:1], "first": [int(t[0])], "ids": [ids.tobytes()], "users": [users], "user_kind": [user_kind], "steps": [steps], "step_kind": [step_kind]}
    return pa.table(cells, schema=PACKED)


PACKED = pa.schema([("block", pa.int64()), ("first", pa.int64()), ("ids", pa.binary()), ("users", pa.binary()), ("user_kind", pa.string()), ("steps", pa.binary()), ("step_kind", pa.string())])


def _unpack(row: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    steps = np.frombuffer(row["steps"], row["step_kind"]).astype(np.int64)
    return np.frombuffer(row["ids"], np.int64), np.frombuffer(row["users"], row["user_kind"]).astype(np.int64), row["first"] + np.r_[0, np.cumsum(steps)]


def near_counts(one: tuple, other: tuple, within: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(user, other, n) of the pairs of two blocks, a user of the first at a time; the smaller id is the user.

    Of a block with itself each pair is given once.
    """
    ids, users, t = one
    names, theirs, s = other
    order = np.argsort(users, kind="stable")
    ends = np.cumsum(np.bincount(users, minlength=len(ids)))
    low, high = np.searchsorted(s, t - within, "left"), np.searchsorted(s, t + within, "right")
    for k, end in enumerate(ends):
        mine = order[ends[k - 1] if k else 0 : end]
        lo, hi = low[mine], high[mine]
        n = hi - lo
        met = int(n.sum())
        if not met:
            continue
        if met > len(s):  # how often each of the other events is met, without a list of all pairs
            cover = np.cumsum(np.bincount(lo, minlength=len(s) + 1) - np.bincount(hi, minlength=len(s) + 1))[:-1]
            count = np.bincount(theirs, weights=cover, minlength=len(names)).astype(np.int64)
            who = np.flatnonzero(count)
            count = count[who]
        else:
            near = theirs[np.arange(met) + np.repeat(lo - np.cumsum(n) + n, n)]
            if 8 * met < len(names):
                who, count = np.unique(near, return_counts=True)
            else:
                count = np.bincount(near, minlength=len(names))
                who = np.flatnonzero(count)
                count = count[who]
        if one is other:
            count, who = count[who > k], who[who > k]
        theirs_ids = names[who]
        yield np.minimum(theirs_ids, ids[k]), np.maximum(theirs_ids, ids[k]), count


def user_pairs(events: DataFrame, within: int) -> DataFrame:
    """(user_id, other, n): pairs of events (user_id, t) of two users at most within apart, counted by users; nulls meet nothing.

    Users are dealt into blocks. A block is packed into one row of a few bytes an event and meets every other block in one
    task, which counts all pairs of their users: only packed events are shuffled, once for each block.
    """
    known = events.where("user_id is not null and t is not null").select(F.col("user_id").cast("long").alias("user_id"), "t")
    blocks = max(LEAST_BLOCKS, -(-known.count() // BLOCK_EVENTS))
    packed = known.withColumn("block", F.pmod(F.xxhash64("user_id"), F.lit(blocks))).groupBy("block").applyInArrow(_pack, "block long, first long, ids binary, users binary, user_kind string, steps binary, step_kind string")
    ahead = F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))
    met = packed.withColumn("other", F.explode(ahead))
    tile = met.select(F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), *PACKED.names)
    tiles = blocks * (blocks + 1) // 2
    # A tile's rows are its two blocks, the first block first; the tile of a block with itself has one row.
    dealt = tile.repartition(tiles, "i", "j").sortWithinPartitions("i", "j", "block")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, out, rows = None, [], 0
        for b in batches:
            for at in range(b.num_rows):
                row = b.slice(at, 1).to_pylist()[0]
                mine = _unpack(row)
                if row["i"] == row["j"]:
                    pair = (mine, mine)
                elif row["block"] == row["i"]:
                    held = (row["i"], row["j"], mine)
                    continue
                elif held and held[:2] == (row["i"], row["j"]):
                    pair = (held[2], mine)
                else:
                    continue  # the first block has no events
                for found in near_counts(*pair, within):
                    out.append(found)
                    rows += len(found[0])
                    if rows >= ROWS:
                        yield _batch(out)
                        out, rows = [], 0
        if out:
            yield _batch(out)

    return dealt.mapInArrow(run, "user_id long, other long, n long")


def _batch(found: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.concatenate(c).astype(np.int64)) for c in zip(*found, strict=True)], names=["user_id", "other", "n"])
