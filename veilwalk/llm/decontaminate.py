"""Benchmark decontamination by pigeonhole edit matching.

A test item may differ from a passage by its error budget of k edits. Cut into k+1 pieces, one piece is untouched, so
an Aho-Corasick automaton over the pieces of all items finds every place to look at, and Myers' bit-parallel distance
settles it. Texts and items are compared in lower case with everything but letters and digits as single spaces.

Results: null or blank texts and items match nothing; rows without an id are left out; rows that repeat an id repeat
their matches, repeated items of one id count once; empty tables give no matches; other columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veilwalk.llm.common import Scratch, release, texts

ERROR_RATE = 0.08
#: Letters of items that one automaton holds; more items are matched in several passes.
PASS_CHARS = 8_000_000
GAPS = re.compile(r"[\W_]+")


def normalize(text: str | None) -> str:
    return GAPS.sub(" ", (text or "").lower()).strip()


class Item:
    """A normalized item, its budget, its pieces, and the bit masks of its letters."""

    def __init__(self, item_id, text: str, rate: float = ERROR_RATE):
        self.id, self.text, self.budget = item_id, text, int(len(text) * rate)
        self.masks: dict[str, int] = {}
        for i, c in enumerate(text):
            self.masks[c] = self.masks.get(c, 0) | 1 << i

    def pieces(self) -> list[tuple[int, str]]:
        n, k = len(self.text), self.budget + 1
        cuts = [n * i // k for i in range(k + 1)]
        return [(s, self.text[s:e]) for s, e in zip(cuts, cuts[1:], strict=False)]

    def distance(self, window: str) -> int:
        """Smallest edit distance of the item to a substring of window, by Myers' bit vectors."""
        m = len(self.text)
        top, full = 1 << (m - 1), (1 << m) - 1
        plus, minus, score, best, masks = full, 0, m, m, self.masks
        for c in window:
            eq = masks.get(c, 0)
            xv = eq | minus
            xh = (((eq & plus) + plus) ^ plus) | eq
            ph = minus | ~(xh | plus)
            mh = plus & xh
            if ph & top:
                score += 1
            elif mh & top:
                score -= 1
                if score < best:
                    best = score
            ph <<= 1
            mh <<= 1
            plus = (mh | ~(xv | ph)) & full
            minus = ph & xv & full
        return best


class Matcher:
    def __init__(self, items: list[tuple], rate: float = ERROR_RATE):
        self.items = [Item(i, t, rate) for i, t in items]
        places: dict[str, list[tuple[int, int]]] = {}
        for k, item in enumerate(self.items):
            for at, piece in item.pieces():
                places.setdefault(piece, []).append((k, at))
        self.automaton = ahocorasick.Automaton()
        for piece, where in places.items():
            self.automaton.add_word(piece, (len(piece), where))
        if places:
            self.automaton.make_automaton()

    def matches(self, text: str) -> list[tuple]:
        """(item id, distance) of items that a passage of the normalized text matches within their budgets."""
        if not self.items or not text:
            return []
        hits: dict[int, list[int]] = {}
        for end, (size, where) in self.automaton.iter(text):
            for k, at in where:
                hits.setdefault(k, []).append(end + 1 - size - at)
        out = []
        for k, begins in hits.items():
            item, best = self.items[k], None
            begins.sort()
            reach, i = item.budget, 0
            while i < len(begins) and best != 0:
                j = i
                while j + 1 < len(begins) and begins[j + 1] - begins[j] <= reach:
                    j += 1
                window = text[max(0, begins[i] - reach) : begins[j] + len(item.text) + reach]
                if item.text in window:
                    best = 0
                else:
                    d = item.distance(window)
                    best = d if best is None else min(best, d)
                i = j + 1
            if best is not None and best <= item.budget:
                out.append((item.id, best))
        return sorted(out)


def item_groups(benchmark: DataFrame, item_col: str = "item_id", item_text: str = "text") -> Iterator[list[tuple]]:
    """Normalized items in groups that one automaton each may hold, one group at a time; one group at least."""
    rows = benchmark.where(benchmark[item_col].isNotNull()).select(benchmark[item_col].cast("long").alias("i"), benchmark[item_text].alias("t"))
    group, size, first = [], 0, True
    for r in rows.distinct().orderBy("i", "t").toLocalIterator():
        t = normalize(r["t"])
        if t:
            if size + len(t) > PASS_CHARS and group:
                yield group
                group, size, first = [], 0, False
            group.append((r["i"], t))
            size += len(t)
    if group or first:
        yield group


def matches(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", rate: float = ERROR_RATE) -> DataFrame:
    """(doc_id, item_id, distance) of every item that a document holds within the item's budget.

    Items are sent to the tasks in automata of at most PASS_CHARS letters each, and the driver holds two such groups at
    most: what one finds is written before the next is read. The documents are never dealt.
    """
    source = docs.where(docs[id_col].isNotNull()).select(docs[id_col].cast("long").alias("doc_id"), docs[text_col])
    scratch, groups = Scratch(docs.sparkSession, "leaks"), item_groups(benchmark, item_col, item_text)
    group, k, out = next(groups), 0, None
    while (more := next(groups, None)) is not None:
        found = scratch.save(_pass(source, group, rate), f"found{k}")
        out = found if out is None else out.unionByName(found)
        group, k = more, k + 1
    last = _pass(source, group, rate)
    return last if out is None else out.unionByName(last).groupBy("doc_id", "item_id").agg(F.min("distance").alias("distance"))


def _pass(source: DataFrame, group: list[tuple], rate: float) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matcher = Matcher(group, rate)
        for b in batches:
            rows = []
            for doc, text in zip(b.column(0).to_pylist(), texts(b.column(1)), strict=True):
                best: dict = {}
                for i, d in matcher.matches(normalize(text)):
                    best[i] = min(d, best.get(i, d))
                rows += [(doc, i, d) for i, d in best.items()]
            cols = list(zip(*rows, strict=True)) or [()] * 3
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.int32()), strict=True)], names=["doc_id", "item_id", "distance"])

    return source.mapInArrow(run, "doc_id long, item_id long, distance int")


def clean(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", rate: float = ERROR_RATE) -> DataFrame:
    """The rows of docs that match no item; each text is matched where it is, so no text is dealt."""
    at, schema = docs.columns.index(text_col), docs.schema
    scratch, groups = Scratch(docs.sparkSession, "clean"), item_groups(benchmark)
    group, k = next(groups), 0

    def kept(docs: DataFrame, group: list[tuple]) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            matcher = Matcher(group, rate)
            for b in batches:
                yield b.filter(pa.array([not matcher.matches(normalize(t)) for t in texts(b.column(at))], pa.bool_()))
            del matcher
            release()

        return docs.mapInArrow(run, schema)

    while (more := next(groups, None)) is not None:
        docs = scratch.save(kept(docs, group), f"kept{k}")
        group, k = more, k + 1
    return kept(docs, group)
