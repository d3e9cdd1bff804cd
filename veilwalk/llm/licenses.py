"""Licence scans: sparse TF-IDF cosine of headers and licence files to templates, then inheritance along directories.

Templates are sentences that name a licence, blocks at the top of source files and texts of licences (licensetexts).
What is compared with them is a sentence or a line that holds a cue word, a header block (cue lines and the few lines
between them, without comment marks and copyright lines), and the whole text of a file that is named as a licence file.
Text without a cue word is not scored. Term weights come from document frequencies of the templates' terms over all
files; terms that no template has count with the weight of a term that no file has, so other words score low. Lines of
SPDX identifiers are scored term by term of their expression. A file without a notice takes the licence of the licence
file in its nearest directory upwards.

Results: null and empty texts have no notice; files without a path inherit nothing. Of several units the best score
counts, of those within NEAR of it the longest, of equal ones the earliest; a bare 'All rights reserved' only counts
where no other licence is found; ties between templates go to the licence that sorts first. An SPDX expression of
several known licences gives their names with its operators in lower case. Rows that repeat are scored each on their
own; an empty table gives an empty result. Columns license, score and origin of the input are replaced, all others are kept.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from veilwalk.llm.common import Scratch, spread_join, texts
from veilwalk.llm.licensetexts import CUES, TEMPLATES

THRESHOLD = 0.6
#: Units within this of the best score give way to the longest of them.
NEAR = 0.1
#: Lines without a cue between two cue lines of one block.
GAP = 2
#: The licence that any other one in a file outdoes.
RESERVED = "proprietary"
TERM = re.compile(r"[a-z]+[0-9]*|[0-9]+(?:\.[0-9]+)*")
SENTENCE = re.compile(r"(?<=[.!?])\s+(?=[A-Z0-9])")
MARKS = re.compile(r"^[\s/*#;%!<>|-]+|[\s*/>-]+$")
OWNER = re.compile(r"(?i)^(copyright\b|\(c\)|©).*?(all rights reserved\.?)?$")
SPDX = re.compile(r"SPDX-License-Identifier:\s*([A-Za-z0-9.+ ()-]+)")
SPDX_WORD = re.compile(r"[A-Za-z0-9.+-]+")
LICENSE_FILE = r"(?i)^(licen[sc]e|copying|unlicense|notice)([._-].*)?$"


def terms(text: str) -> dict[str, int]:
    out: dict[str, int] = {}
    for t in TERM.findall(text.lower()):
        out[t] = out.get(t, 0) + 1
    return out


VOCABULARY = sorted({t for forms in TEMPLATES.values() for text in forms for t in terms(text)})


class Scorer:
    """Cosine of a unit to the templates under given term weights."""

    def __init__(self, frequency: dict[str, int], files: int):
        self.weight = {t: math.log((1 + files) / (1 + frequency.get(t, 0))) + 1 for t in VOCABULARY}
        self.other = math.log(1 + files) + 1
        self.names: list[str] = []
        self.holders: dict[str, list[tuple[int, float]]] = {}
        for name in sorted(TEMPLATES):
            for text in TEMPLATES[name]:
                v = {t: n * self.weight[t] for t, n in terms(text).items()}
                norm = math.sqrt(sum(x * x for x in v.values()))
                for t, x in v.items():
                    self.holders.setdefault(t, []).append((len(self.names), x / norm))
                self.names.append(name)

    def best(self, unit: str) -> tuple[str | None, float]:
        """The licence of the nearest template and its cosine; only templates that share a term are summed up."""
        v = {t: n * self.weight.get(t, self.other) for t, n in terms(unit).items()}
        norm = math.sqrt(sum(x * x for x in v.values()))
        sums = [0.0] * len(self.names)
        for t, x in v.items():
            for k, y in self.holders.get(t, ()):
                sums[k] += x * y
        name, score = None, 0.0
        for k, s in enumerate(sums):
            if s > (score + 1e-12) * norm:
                name, score = self.names[k], s / norm
        return name, score

    def expression(self, unit: str) -> str | None:
        """The licences of an SPDX line, joined as in its expression; None where one of them is not known."""
        found = SPDX.search(unit)
        out = []
        for word in SPDX_WORD.findall(found.group(1) if found else ""):
            if word.lower() in ("and", "or", "with"):
                out.append(word.lower())
            elif out and out[-1] == "with":  # an exception of the licence before it
                out.pop()
            else:
                bare = re.sub(r"(-only|-or-later|\+)$", "", word.lower())
                if bare not in TEMPLATES:
                    return None
                out.append(bare)
        return " ".join(out) or None

    def licence(self, units: Iterator[str], threshold: float) -> tuple[str | None, float | None]:
        """The licence of a file by its units, and the score of the one that decides."""
        found = []
        for k, unit in enumerate(units):
            name, score = (spdx, 1.0) if "SPDX" in unit and (spdx := self.expression(unit)) else self.best(unit)
            if name is not None and score >= threshold and (name != RESERVED or "rights reserved" in unit.lower()):
                found.append((name, score, len(unit), -k))
        found = [f for f in found if f[0] != RESERVED] or found
        if not found:
            return None, None
        top = max(f[1] for f in found)
        name, score, *_ = max((f for f in found if f[1] >= top - NEAR), key=lambda f: (f[2], f[1], f[3]))
        return name, score


def cue_automaton() -> ahocorasick.Automaton:
    a = ahocorasick.Automaton()
    for c in CUES:
        a.add_word(c, len(c))
    a.make_automaton()
    return a


def units(text: str, cues: ahocorasick.Automaton, whole: bool = False) -> Iterator[str]:
    """What of a text is compared with templates: cue lines and their sentences, header blocks, the whole of a licence file."""
    lines, done = [], -1
    for end, _ in cues.iter(text):
        if end < done:
            continue
        start = text.rfind("\n", 0, end) + 1
        done = text.find("\n", end)
        done = len(text) if done < 0 else done
        lines.append((start, done))
        line = MARKS.sub("", text[start:done])
        yield line
        yield from (s for s in SENTENCE.split(line) if s != line)
    at = 0
    while at < len(lines):
        to = at
        while to + 1 < len(lines) and _filled(text[lines[to][1] : lines[to + 1][0]]) <= GAP:
            to += 1
        end = lines[to][1]
        for _ in range(GAP):  # the lines below, where a version or an address may stand
            stop = text.find("\n", end + 1)
            stop = len(text) if stop < 0 else stop
            if not MARKS.sub("", text[end:stop]):
                break
            end = stop
        if to > at or end > lines[to][1]:
            yield bare(text[lines[at][0] : end])
        if to > at and end > lines[to][1]:
            yield bare(text[lines[at][0] : lines[to][1]])
        at = to + 1
    if whole and lines:
        yield bare(text)


def _filled(part: str) -> int:
    return sum(MARKS.sub("", line) != "" for line in part.split("\n"))


def bare(text: str) -> str:
    """Text without comment marks and copyright lines."""
    kept = (MARKS.sub("", line) for line in text.split("\n"))
    return " ".join(line for line in kept if line and not OWNER.match(line))


def frequencies(files: DataFrame, text_col: str = "text") -> tuple[dict[str, int], int]:
    """Files that hold each term of the templates, and the number of files, over all rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary, count, n = set(VOCABULARY), dict.fromkeys(VOCABULARY, 0), 0
        for b in batches:
            for text in texts(b.column(0)):
                n += 1
                for t in vocabulary.intersection(TERM.findall(text.lower())):
                    count[t] += 1
        count[""] = n
        yield pa.RecordBatch.from_arrays([pa.array(list(count)), pa.array(list(count.values()), pa.int64())], names=["term", "n"])

    rows = files.select(text_col).mapInArrow(run, "term string, n long").groupBy("term").agg(F.sum("n").alias("n")).collect()
    found = {r["term"]: r["n"] for r in rows}  # one row for each term of the templates
    return found, found.pop("", 0)


def detect(files: DataFrame, text_col: str = "text", threshold: float = THRESHOLD, path_col: str | None = None) -> DataFrame:
    """files with license and score of what decides (null below the threshold), without their texts; with path_col licence files are compared as a whole too."""
    frequency, n = frequencies(files, text_col)
    keep = [c for c in files.columns if c not in (text_col, "license", "score")]
    named = F.lit(False) if path_col is None else F.coalesce(license_file(F.col(f"`{path_col}`")), F.lit(False))
    rows = files.select(*[F.col(f"`{c}`") for c in keep], named, F.col(f"`{text_col}`")).toDF(*[f"c{i}" for i in range(len(keep))], "named", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer, cues = Scorer(frequency, n), cue_automaton()
        for b in batches:
            found = [scorer.licence(units(t, cues, w), threshold) for w, t in zip(b.column(len(keep)).to_pylist(), texts(b.column(len(keep) + 1)), strict=True)]
            cols = [*b.columns[: len(keep)], pa.array([f[0] for f in found], pa.string()), pa.array([f[1] for f in found], pa.float64())]
            yield pa.RecordBatch.from_arrays(cols, names=[*[f"c{i}" for i in range(len(keep))], "license", "score"])

    schema = T.StructType([f for f in rows.schema.fields if f.name not in ("named", "text")] + [T.StructField("license", T.StringType()), T.StructField("score", T.DoubleType())])
    return rows.mapInArrow(run, schema).toDF(*keep, "license", "score")


def license_file(path: F.Column) -> F.Column:
    return F.element_at(F.split(path, "/"), -1).rlike(LICENSE_FILE)


def directory(path: F.Column) -> F.Column:
    """The path up to its last slash; the empty string at the top."""
    return F.regexp_replace(path, r"/?[^/]*$", "")


def scan(files: DataFrame, path_col: str = "path", text_col: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """files (without their texts) with license, score and origin: 'own', 'inherited' or null.

    Directories are reduced to distinct ones before their ancestors are listed, so a directory of many files is looked up
    once; the files of a very large one are dealt over several tasks.
    """
    scratch = Scratch(files.sparkSession, "licenses")
    held = scratch.save(detect(files.drop("origin") if "origin" not in (path_col, text_col) else files, text_col, threshold, path_col), "found")
    keep = held.columns
    path = F.col(f"`{path_col}`")
    found = held.select(F.struct(*[F.col(f"`{c}`") for c in keep]).alias("file"), directory(path).alias("dir"), F.xxhash64(path).alias("h"))
    given = held.where(license_file(path) & F.col("license").isNotNull()).groupBy(directory(path).alias("up")).agg(F.max_by("license", F.struct("score", path)).alias("given"))
    dirs = found.where("dir is not null").select("dir").distinct()
    parts = F.filter(F.split("dir", "/"), lambda p: p != "")
    chain = F.transform(F.sequence(F.lit(0), F.size(parts)), lambda i: F.struct(i.alias("depth"), F.array_join(F.slice(parts, 1, i), "/").alias("up")))
    above = dirs.select("dir", F.explode(chain).alias("a")).select("dir", "a.depth", "a.up")
    nearest = above.join(given, "up").groupBy("dir").agg(F.max_by("given", "depth").alias("given"))
    out = spread_join(found, nearest, "dir", ["h"], "left")
    own = F.col("file.license").isNotNull()
    origin = F.when(own, "own").when(F.col("given").isNotNull(), "inherited")
    kept = [F.col(f"file.`{c}`").alias(c) for c in keep if c not in ("license", "score")]
    return out.select(*kept, F.coalesce("file.license", "given").alias("license"), F.col("file.score").alias("score"), origin.alias("origin"))
