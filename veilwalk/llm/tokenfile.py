"""Token files: frequency-ranked ids in byte-aligned variable-length coding with separate control bytes.

Each id is replaced by its rank by frequency, so frequent ids take one byte. Four ranks share a control byte of four
two-bit lengths; control bytes and data bytes lie apart, so that numpy decodes them through a table of 256 rows.

A part file holds whole documents in ascending id order:
  magic, number of documents, doc ids (int64), tokens of each document (int64), bytes of controls, bytes of data,
  control bytes, data bytes. Integers are little-endian. The rank table is one more file, vocabulary.bin (uint32).
Parts are named by number of task and file, written whole and renamed, so a task that runs again replaces its own parts.
A part closes at PART_TOKENS, so a task holds no more than that and one batch.

Results: null and empty texts hold the end id alone; rows without an id come first with a null id (written as the
smallest int64); rows that repeat an id are kept; an empty table gives no part; other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from veilwalk.llm.common import Scratch, arrow_map
from veilwalk.llm.tokens import default_path, encoder

VOCABULARY = "word_bpe_49k.json"
END_ID = 1
#: Tokens after which a task begins another file.
PART_TOKENS = 1 << 25
MAGIC = b"VWTOK001"
NO_ID = -(1 << 63)


def _lengths(values: np.ndarray) -> np.ndarray:
    """Bytes of each value, 1 to 4."""
    return 1 + (values > 0xFF).astype(np.int64) + (values > 0xFFFF) + (values > 0xFFFFFF)


def encode(values: np.ndarray) -> tuple[bytes, bytes]:
    """Control bytes and data bytes of unsigned 32-bit values."""
    values = values.astype("<u4")
    n = _lengths(values)
    codes = np.zeros(-(-len(values) // 4) * 4, np.uint8)
    codes[: len(values)] = n - 1
    codes = codes.reshape(-1, 4)
    control = codes[:, 0] | codes[:, 1] << 2 | codes[:, 2] << 4 | codes[:, 3] << 6
    used = np.arange(4) < n[:, None]
    return control.astype(np.uint8).tobytes(), values.view(np.uint8).reshape(-1, 4)[used].tobytes()


#: For each control byte, the lengths of its four values.
LENGTHS = ((np.arange(256)[:, None] >> np.array([0, 2, 4, 6])) & 3) + 1
MASKS = np.array([0xFF, 0xFFFF, 0xFFFFFF, 0xFFFFFFFF], np.uint32)


def decode(control: bytes, data: bytes, count: int) -> np.ndarray:
    """The count values that encode() was given."""
    n = LENGTHS[np.frombuffer(control, np.uint8)].reshape(-1)[:count]
    ends = np.cumsum(n)
    at = ends - n
    raw = np.frombuffer(data + b"\0\0\0", np.uint8)
    words = np.ndarray((len(raw) - 3,), "<u4", raw, 0, (1,)) if len(raw) > 3 else np.zeros(0, "<u4")
    return words[at] & MASKS[n - 1]


def part_bytes(ids: list[int], counts: np.ndarray, values: np.ndarray) -> bytes:
    control, data = encode(values)
    head = np.array([len(ids), len(control), len(data)], "<i8").tobytes()
    return b"".join([MAGIC, head, np.array(ids, "<i8").tobytes(), counts.astype("<i8").tobytes(), control, data])


def read_part(content: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Doc ids, tokens of each, and all ranks of a part file."""
    if content[:8] != MAGIC:
        raise ValueError("not a token file")
    docs, controls, data = np.frombuffer(content, "<i8", 3, 8).tolist()
    ids = np.frombuffer(content, "<i8", docs, 32)
    counts = np.frombuffer(content, "<i8", docs, 32 + 8 * docs)
    at = 32 + 16 * docs
    ranks = decode(content[at : at + controls], content[at + controls : at + controls + data], int(counts.sum()))
    return ids, counts, ranks


def put_file(uri: str, content: bytes) -> None:
    """Write one file whole through a name of its own; works on any store that pyarrow opens."""
    fs, path = pafs.FileSystem.from_uri(uri)
    fs.create_dir(path.rsplit("/", 1)[0], recursive=True)
    own = f"{path}.{np.random.default_rng().integers(1 << 62):x}.tmp"
    with fs.open_output_stream(own) as f:
        f.write(content)
    fs.move(own, path)


def tokenized(docs: DataFrame, id_col: str, text_col: str, path: str) -> DataFrame:
    """(kind, doc_id, n, ids): ids with the end id as little-endian 16-bit integers where the vocabulary allows it.

    Rows of kind 1 hold how often each id occurs in a batch, as 64-bit integers: one row for each batch.
    """
    def run(b: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        enc = encoder(path, fold_ascii=True)
        width = "<u2" if enc.whole.get_vocab_size() <= 1 << 16 else "<u4"
        ids = enc.encode_column(b.column(1), END_ID)
        size = enc.whole.get_vocab_size()
        total = np.zeros(size, np.int64)
        for at in range(0, len(ids), 1000):
            total += np.bincount(np.concatenate(ids[at : at + 1000]), minlength=size)
        names = ["kind", "doc_id", "n", "ids"]
        cols = [pa.array(np.zeros(len(ids), np.int32)), b.column(0), pa.array([len(x) for x in ids], pa.int64()), pa.array([x.astype(width).tobytes() for x in ids], pa.binary())]
        yield pa.RecordBatch.from_arrays(cols, names=names)
        cols = [pa.array([1], pa.int32()), pa.array([None], pa.int64()), pa.array([0], pa.int64()), pa.array([total.astype("<i8").tobytes()], pa.binary())]
        yield pa.RecordBatch.from_arrays(cols, names=names)

    return arrow_map(docs.select(docs[id_col].cast("long"), docs[text_col]), run, "kind int, doc_id long, n long, ids binary")


def _bytes(column: pa.Array) -> memoryview:
    """All values of a binary column without nulls, end to end as they lie."""
    ends = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1]
    return memoryview(column.buffers()[2] or b"")[ends[0] : ends[-1]]


def write(docs: DataFrame, uri: str, scratch: Scratch, id_col: str = "doc_id", text_col: str = "text", path: str | None = None) -> DataFrame:
    """Write token files of all documents under uri; returns the manifest (part, docs, tokens).

    Texts are tokenized once and their ids kept in a shared table; ranks come from counts over all documents.
    """
    spark = docs.sparkSession
    path = path or default_path(VOCABULARY)
    from tokenizers import Tokenizer

    size = Tokenizer.from_file(path).get_vocab_size()
    width = "<u2" if size <= 1 << 16 else "<u4"
    both = scratch.save(tokenized(docs, id_col, text_col, path), "ids")
    kept = both.where("kind = 0").drop("kind")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(size, np.int64)
        for b in batches:
            for x in b.column(0):
                total += np.frombuffer(x.as_buffer(), "<i8")
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], names=["id", "n"])

    freq = both.where("kind = 1").select("ids").mapInArrow(count, "id long, n long").groupBy("id").agg(F.sum("n").alias("n")).toPandas()
    n = np.zeros(size, np.int64)  # one count for each entry of the vocabulary
    n[freq["id"].to_numpy(np.int64)] = freq["n"].to_numpy(np.int64)
    by_rank = np.lexsort((np.arange(size), -n)).astype("<u4")
    rank = np.empty(size, np.uint32)
    rank[by_rank] = np.arange(size, dtype=np.uint32)
    put_file(f"{uri}/vocabulary.bin", by_rank.tobytes())

    ordered = kept.repartitionByRange("doc_id").sortWithinPartitions("doc_id").withColumn("part", F.spark_partition_id())

    def store(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, k, ids, counts, coded, held = 0, 0, [], [], [], 0

        def close() -> pa.RecordBatch:
            put_file(f"{uri}/part-{part:08d}-{k:06d}.tok", part_bytes(ids, np.array(counts, np.int64), np.concatenate(coded)))
            return pa.RecordBatch.from_arrays([pa.array([x], pa.int64()) for x in (part, len(ids), sum(counts))], names=["part", "docs", "tokens"])

        for b in batches:
            if not b.num_rows:
                continue
            part = b.column(3)[0].as_py()
            docs = [NO_ID if x is None else x for x in b.column(0).to_pylist()]
            sizes, ranks = b.column(1).to_pylist(), rank[np.frombuffer(_bytes(b.column(2)), width)]
            first, begin, end = 0, 0, 0
            for i, n in enumerate(sizes):
                if held and held + n > PART_TOKENS:
                    ids, counts, coded = ids + docs[first:i], counts + sizes[first:i], [*coded, ranks[begin:end]]
                    yield close()
                    k, ids, counts, coded, held, first, begin = k + 1, [], [], [], 0, i, end
                end, held = end + n, held + n
            ids += docs[first:]
            counts += sizes[first:]
            coded.append(ranks[begin:])
        if ids:
            yield close()

    manifest = ordered.mapInArrow(store, "part long, docs long, tokens long")
    rows = [tuple(r) for r in manifest.collect()]  # one row for each file
    scratch.drop("ids")
    return spark.createDataFrame(rows, "part long, docs long, tokens long")


def read(spark: SparkSession, uri: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of the documents in the files under uri, in their order.

    start counts the ids of all earlier documents: those of earlier files come from the headers of the files.
    """
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.tok").load(uri)
    fs, path = pafs.FileSystem.from_uri(f"{uri}/vocabulary.bin")
    with fs.open_input_file(path) as f:
        by_rank = np.frombuffer(f.read(), "<u4")

    def part_of(name: str) -> str:
        return name.rsplit("part-", 1)[1].removesuffix(".tok")

    def sizes(b: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        parts, tokens = [], []
        for name in map(part_of, b.column(0).to_pylist()):  # headers alone are read here
            fs, path = pafs.FileSystem.from_uri(f"{uri}/part-{name}.tok")
            with fs.open_input_file(path) as f:
                docs = int(np.frombuffer(f.read_at(8, 8), "<i8")[0])
                tokens.append(int(np.frombuffer(f.read_at(8 * docs, 32 + 8 * docs), "<i8").sum()))
            parts.append(name)
        yield pa.RecordBatch.from_arrays([pa.array(parts, pa.string()), pa.array(tokens, pa.int64())], names=["part", "tokens"])

    before, total = {}, 0
    for r in sorted(arrow_map(files.select("path"), sizes, "part string, tokens long").collect()):  # one row for each file
        before[r["part"]], total = total, total + r["tokens"]

    def run(b: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        for name, content in zip(b.column(0).to_pylist(), b.column(1), strict=True):
            ids, counts, ranks = read_part(content.as_py())
            values = by_rank[ranks].astype("<u4")
            ends = np.cumsum(counts)
            crcs = [zlib.crc32(values[e - c : e]) for e, c in zip(ends.tolist(), counts.tolist(), strict=True)]
            cols = [pa.array(ids, mask=ids == NO_ID), pa.array(before[part_of(name)] + ends - counts), pa.array(counts), pa.array(crcs, pa.int64())]
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return arrow_map(files.select("path", "content"), run, "doc_id long, start long, n_tokens long, ids_crc32 long")
