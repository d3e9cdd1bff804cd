"""Language identification of mixed-language text.

Script ranges narrow the candidate languages of each word; each word gets a score for each candidate from character
n-grams; Viterbi over the words with a switching penalty labels spans. The language of a text is the one whose spans
hold most letters. Letters of words in scripts that no language was learned in count for no language, but for the whole of
the text. The margin of a text is the log-likelihood per letter that its leading language has, on the words of its spans,
over a background where all n-grams seen in training are equally likely; text unlike anything learned lies below zero.

Most texts need no table: where no stretch of words favours another language by more than half the penalty, the path that
stays in the best single language is optimal (two stretches or more, m, gain at most m/2 penalties and cost m-1 switches),
which numpy shows for a whole batch at once. The others are decoded word by word.

Results: null texts, and texts without a letter of a learned script, are 'und' with score and margin 0; training rows without a text or language are
left out; with nothing to learn from every text is 'und'; ties go to the language that sorts first; rows that repeat
are labelled each on their own.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from veilwalk.llm.common import arrow_map, release, texts

BUCKETS = 1 << 16
#: Training documents for each language, about; a documented bound, drawn by a hash of the id.
SAMPLE = 1500
PENALTY = 12.0
FLOOR = -40.0
REMEMBERED = 250_000
#: Multipliers of the n-gram hashes.
G1, G2, G3 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0xD6E8FEB86659FD93)
WORD = re.compile(r"[^\W\d_]+")
#: First code point, last code point, script.
SCRIPTS = (
    (0x0041, 0x024F, "latin"), (0x0370, 0x03FF, "greek"), (0x0400, 0x052F, "cyrillic"), (0x0530, 0x058F, "armenian"),
    (0x0590, 0x05FF, "hebrew"), (0x0600, 0x077F, "arabic"), (0x0900, 0x097F, "devanagari"), (0x0980, 0x09FF, "bengali"),
    (0x0E00, 0x0E7F, "thai"), (0x10A0, 0x10FF, "georgian"), (0x1E00, 0x1EFF, "latin"), (0x3040, 0x30FF, "kana"),
    (0x3400, 0x4DBF, "han"), (0x4E00, 0x9FFF, "han"), (0xAC00, 0xD7AF, "hangul"),
)


def script(word: str) -> str:
    """Script of the first letter that a range covers."""
    if "a" <= word[:1] <= "z":
        return "latin"
    for c in word:
        n = ord(c)
        for lo, hi, name in SCRIPTS:
            if lo <= n <= hi:
                return name
    return "other"


def grams(words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Buckets of the two- and three-letter n-grams of lower-case words with their ends marked.

    Both are arrays over all letters of all words, end marks included, with -1 where a word ends first; the third array
    holds the words' starts.
    """
    codes = np.frombuffer(("<" + "><".join(words) + ">").encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64)
    sizes = np.fromiter(map(len, words), np.int64, len(words)) + 2
    ends = np.cumsum(sizes)
    two, three = np.full(len(codes), -1, np.int64), np.full(len(codes), -1, np.int64)
    h = codes[:-1] * G1 + codes[1:]
    two[:-1] = _bucket(h)
    three[:-2] = _bucket(h[:-1] * G2 + codes[2:])
    two[ends - 1] = -1
    three[ends - 1] = three[ends - 2] = -1
    return two, three, ends - sizes


def _bucket(h: np.ndarray) -> np.ndarray:
    h = h * G3
    return ((h ^ h >> np.uint64(31)) & np.uint64(BUCKETS - 1)).astype(np.int64)


@dataclass
class Model:
    """langs; log-probabilities of n-gram buckets by language; the languages seen in each script; the background's log-probability."""

    langs: list[str]
    logp: np.ndarray
    scripts: dict[str, np.ndarray]
    background: float = 0.0

    def score(self, words: list[str]) -> np.ndarray:
        """Scores of lower-case words by language; languages that do not use a word's script have the floor."""
        return self.judge(words)[0]

    def judge(self, words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Scores; whether a language uses the word's script; log-likelihood of the best such language over the background."""
        if not words:
            return np.zeros((0, len(self.langs))), np.zeros(0, bool), np.zeros(0)
        padded = np.concatenate([self.logp, np.zeros((1, len(self.langs)))])  # row -1 adds nothing
        two, three, starts = grams(words)
        own = np.add.reduceat(padded[two] + padded[three], starts, axis=0) / 2
        kinds = [script(w) for w in words]
        names = sorted(set(kinds))
        known = np.stack([self.scripts.get(k, np.zeros(len(self.langs), bool)) for k in names])[np.fromiter(map(names.index, kinds), np.int64, len(kinds))]
        best = np.where(known, own, -np.inf).max(1, keepdims=True, initial=-1e300)
        some = known.any(1)
        over = np.where(some, best[:, 0] - self.background * (np.fromiter(map(len, words), np.int64, len(words)) + 0.5), 0.0)
        return np.where(some[:, None], np.where(known, np.maximum(own - best, FLOOR), FLOOR), 0.0), some, over


def fit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", sample: int = SAMPLE) -> Model:
    """Learn from about sample labelled rows of each language, chosen by a hash of their ids and read whole."""
    keyed = docs.where(docs[lang_col].isNotNull() & docs[text_col].isNotNull()).select(
        F.col(lang_col).alias("lang"), F.col(text_col).alias("text"), F.xxhash64(F.col(id_col).cast("string"), F.lit(7)).alias("h")
    )
    counts = {r["lang"]: r["n"] for r in keyed.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    langs = sorted(counts)
    if not langs:
        return Model([], np.zeros((BUCKETS, 0)), {})
    chosen = F.lit(False)
    for lang in langs:
        share = min(1.0, sample / counts[lang])
        chosen |= (F.col("lang") == lang) & (F.pmod("h", F.lit(1_000_000)) < int(np.ceil(share * 1_000_000)))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[tuple[str, str], int] = {}
        for b in batches:
            total = {}
            for lang, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                words: dict[str, int] = {}
                for w in WORD.findall(text.lower()):
                    words[w] = words.get(w, 0) + 1
                if not words:
                    continue
                t = total.setdefault(lang, np.zeros(BUCKETS, np.int64))
                two, three, starts = grams(list(words))
                n = np.repeat(list(words.values()), np.diff(np.r_[starts, len(two)]))
                for g in (two, three):
                    t += np.bincount(g[g >= 0], n[g >= 0], BUCKETS).astype(np.int64)
                for w, n in words.items():
                    key = (lang, script(w))
                    seen[key] = seen.get(key, 0) + n * len(w)
            for lang, t in total.items():
                at = np.flatnonzero(t)
                yield _counts([lang] * len(at), at.tolist(), [""] * len(at), t[at].tolist())
        yield _counts([k[0] for k in seen], [-1] * len(seen), [k[1] for k in seen], list(seen.values()))

    rows = keyed.where(chosen).select("lang", "text").mapInArrow(count, "lang string, bucket int, script string, n long")
    rows = rows.groupBy("lang", "bucket", "script").agg(F.sum("n").alias("n")).toPandas()  # at most one row for each bucket and language
    table, letters = np.zeros((BUCKETS, len(langs))), {}
    for lang, bucket, name, n in rows.itertuples(index=False):
        if bucket >= 0:
            table[bucket, langs.index(lang)] = n
        else:
            letters.setdefault(name, np.zeros(len(langs)))[langs.index(lang)] = n
    total = np.array(sum(letters.values(), np.zeros(len(langs))))
    scripts = {k: v >= 0.01 * total for k, v in letters.items() if (v >= 0.01 * total).any()}
    smooth = table + 0.5
    return Model(langs, np.log(smooth / smooth.sum(0)), scripts, -float(np.log(max(1, np.count_nonzero(table.any(1))))))


def _counts(langs: list, buckets: list, scripts: list, n: list) -> pa.RecordBatch:
    cols = [pa.array(langs, pa.string()), pa.array(buckets, pa.int32()), pa.array(scripts, pa.string()), pa.array(n, pa.int64())]
    return pa.RecordBatch.from_arrays(cols, names=["lang", "bucket", "script", "n"])


class Tagger:
    """Labels of words; scores of frequent words are remembered."""

    def __init__(self, model: Model, penalty: float = PENALTY):
        self.model, self.penalty = model, penalty
        self.forget()

    def forget(self) -> None:
        self.index: dict[str, int] = {}
        self.scores = np.zeros((1024, len(self.model.langs)))
        self.known, self.over = np.zeros(1024, bool), np.zeros(1024)

    def rows(self, words: list[str]) -> np.ndarray:
        index = self.index
        new = list(set(words).difference(index))
        k = len(index)
        while k + len(new) > len(self.scores):
            self.scores, self.known, self.over = (np.concatenate([x, np.zeros_like(x)]) for x in (self.scores, self.known, self.over))
        for at in range(0, len(new), 20_000):
            part = slice(k + at, k + min(at + 20_000, len(new)))
            self.scores[part], self.known[part], self.over[part] = self.model.judge(new[at : at + 20_000])
        index.update(zip(new, range(k, k + len(new)), strict=True))
        return np.fromiter(map(index.__getitem__, words), np.int64, len(words))

    def viterbi(self, e: np.ndarray) -> np.ndarray:
        """The best path through scores e (words by languages) where each change costs the penalty."""
        n = len(e)
        if not n:
            return np.zeros(0, np.int64)
        penalty, back = self.penalty, []
        best = e[0].tolist()
        for row in e[1:].tolist():
            top = max(best)
            least = top - penalty
            back.append((best.index(top), [b < least for b in best]))
            best = [(least if b < least else b) + x for b, x in zip(best, row, strict=True)]
        at = best.index(max(best))
        path = np.zeros(n, np.int64)
        path[-1] = at
        for i in range(n - 2, -1, -1):
            top, changed = back[i]
            if changed[at]:
                at = top
            path[i] = at
        return path

    def paths(self, e: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Best paths of texts whose words lie end to end in e; ends are the texts' ends."""
        n, k = e.shape
        starts = np.r_[0, ends[:-1]]
        full = np.flatnonzero(ends > starts)
        path = np.zeros(n, np.int64)
        if not len(full) or k < 2:
            return path
        sums = np.add.reduceat(e, starts[full], axis=0)
        stay = sums.argmax(1)
        sizes = (ends - starts)[full]
        doc = np.repeat(np.arange(len(full)), sizes)
        path[:] = stay[doc]
        gain = e - e[np.arange(n), path][:, None]
        total = np.cumsum(gain, axis=0)
        before = total - gain
        low = before - before[starts[full]][doc]  # gains of a text before each word
        step = 2 * np.abs(low).max() + 1.0
        low -= step * doc[:, None]  # later texts lie lower, so a running minimum starts anew with each
        low = np.minimum.accumulate(low, axis=0) + step * doc[:, None]
        here = total - before[starts[full]][doc]
        best = np.maximum.reduceat((here - low).max(1), starts[full])
        for i in np.flatnonzero(best > self.penalty / 2 - 1e-6):
            s, t = starts[full[i]], ends[full[i]]
            path[s:t] = self.viterbi(e[s:t])
        return path

    def words(self, text: str) -> list[str]:
        """Lower-case words; runs of numeric signs alone are no words."""
        found = WORD.findall(text.lower())
        return found if text.isascii() else [w for w in found if w.isalpha() or any(map(str.isalpha, w))]

    def spans(self, text: str) -> list[tuple[int, int, str]]:
        """(start, end, language) of maximal runs of words of one language; words of unlearned scripts end a run."""
        found = [m for m in WORD.finditer(text) if any(map(str.isalpha, m.group()))]
        if not self.model.langs:
            return []
        rows = self.rows([m.group().lower() for m in found])
        out: list[list] = []
        before = False
        for m, k, known in zip(found, self.viterbi(self.scores[rows]), self.known[rows], strict=True):
            if known and before and out[-1][2] == self.model.langs[k]:
                out[-1][1] = m.end()
            elif known:
                out.append([m.start(), m.end(), self.model.langs[k]])
            before = known
        return [tuple(x) for x in out]

    def label(self, batch: list[str]) -> tuple[list[str], list[float]]:
        """Language and share of letters in its spans, for each text."""
        return self.judge(batch)[:2]

    def judge(self, batch: list[str]) -> tuple[list[str], list[float], list[float]]:
        """Language, share of letters in its spans, and margin, for each text."""
        langs, out_lang, out_score, out_margin, at = self.model.langs, [], [], [], 0
        while at < len(batch):
            words, ends, size, first = [], [], 0, at
            while at < len(batch) and (size < 1 << 20 or at == first):
                size += len(batch[at])
                words += self.words(batch[at])
                ends.append(len(words))
                at += 1
            if not langs:
                out_lang += ["und"] * len(ends)
                out_score += [0.0] * len(ends)
                out_margin += [0.0] * len(ends)
                continue
            ends = np.array(ends)
            rows = self.rows(words)
            e, known = self.scores[rows], self.known[rows]
            path = self.paths(e, ends)
            letters = np.fromiter(map(len, words), np.int64, len(words))
            doc = np.repeat(np.arange(len(ends)), np.diff(np.r_[0, ends]))
            held = np.bincount(doc * len(langs) + path, letters * known, len(ends) * len(langs)).reshape(len(ends), -1)
            total = np.bincount(doc, letters, len(ends))
            top = held.argmax(1)
            lead = held[np.arange(len(ends)), top]
            out_lang += ["und" if t == 0 else langs[k] for t, k in zip(lead, top, strict=True)]
            out_score += (lead / np.maximum(total, 1)).tolist()
            gain = (e[np.arange(len(path)), path] + self.over[rows]) * (known & (path == top[doc]))
            out_margin += (np.bincount(doc, gain, len(ends)) / np.maximum(lead, 1)).tolist()
            if len(self.index) > REMEMBERED:
                self.forget()
        return out_lang, out_score, out_margin


def predict(docs: DataFrame, model: Model, penalty: float = PENALTY, text_col: str = "text", margin: bool = False) -> DataFrame:
    """docs with lang_pred and score, and with margin where asked for; one pass, no shuffle."""
    added = [T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType()), T.StructField("margin", T.DoubleType())][: 2 + margin]
    keep = [c for c in docs.columns if c not in [f.name for f in added]]
    docs = docs.select(*[F.col(f"`{c}`") for c in keep])
    i = keep.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tagger = Tagger(model, penalty)
        for b in batches:
            lang, score, over = tagger.judge(texts(b.column(i)))
            cols = [pa.array(lang, pa.string()), pa.array(score, pa.float64()), pa.array(over, pa.float64())]
            yield pa.RecordBatch.from_arrays([*b.columns, *cols[: len(added)]], names=[*keep, *[f.name for f in added]])
        del tagger  # with all the words it remembers
        release()

    return docs.mapInArrow(run, T.StructType([*docs.schema.fields, *added]))


def held_out(id_col: str = "doc_id") -> F.Column:
    """True for rows that are kept from training: the checksum of the id as text is a multiple of five."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string")) % 5 == 0, F.lit(True))
