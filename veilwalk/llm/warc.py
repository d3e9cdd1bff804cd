"""WARC archives: a writer of gzip-member records with revisits, and a PySpark data source that reads them.

The reader plans one partition for each archive, takes record-type and header predicates from Spark, parses the
headers of a record first, and jumps over the rest of a record that is not wanted: each gzip member tells its
compressed length in an extra field. Members without that field, and plain archives, are read too.

Results: null payloads are empty; pages without an id are written as responses without a record id of theirs; pages
that repeat the largest id of their payload are all responses; an empty table gives an empty archive; other columns are
ignored; records of any length are streamed one by one.
"""

from __future__ import annotations

import base64
import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, In, InputPartition, IsNotNull

from veilwalk.llm.common import spread_join, text_buffer

#: Fixed values of the archive format.
VERSION = b"WARC/1.1"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "2000-01-01T00:00:00Z"
PAGE = "<urn:page:%d>"
GZIP_HEAD = b"\x1f\x8b\x08\x04\0\0\0\0\0\xff\x0c\x00sl\x08\x00"
HEAD_BYTES = 4096
SCHEMA = "record_id string, record_type string, target_uri string, payload_digest string, payload_bytes long, refers_to string, payload binary"
COLUMNS = [f.split()[0] for f in SCHEMA.split(", ")]


def digest32(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def _clean(value: str) -> str:
    """A header value on one line."""
    return "".join(c if c > " " and c != "\x7f" else "".join(f"%{b:02X}" for b in c.encode()) for c in value)


def record(record_id: str | None, kind: str, uri: str | None, payload: bytes | None, digest: str, size: int, refers_to: str | None) -> bytes:
    """One record; a revisit has the HTTP head alone."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {size}\r\n\r\n".encode()
    block = http if payload is None else http + payload
    head = [("WARC-Type", kind), ("WARC-Date", DATE), ("WARC-Payload-Digest", f"sha1:{digest}"), ("Content-Type", "application/http; msgtype=response")]
    head += [("WARC-Record-ID", record_id)] * (record_id is not None) + [("WARC-Target-URI", _clean(uri or ""))] * (uri is not None)
    if refers_to is not None:
        head += [("WARC-Refers-To", refers_to), ("WARC-Profile", PROFILE)]
    head.append(("Content-Length", str(len(block))))
    return b"".join([VERSION, b"\r\n", *(f"{k}: {v}\r\n".encode() for k, v in head), b"\r\n", block, b"\r\n\r\n"])


def member(data: bytes, level: int = 6) -> bytes:
    """A gzip member that carries its own compressed and plain length."""
    z = zlib.compressobj(level, zlib.DEFLATED, -15)
    body = z.compress(data) + z.flush()
    total = len(GZIP_HEAD) + 8 + len(body) + 8
    return b"".join([GZIP_HEAD, struct.pack("<II", total, len(data) & 0xFFFFFFFF), body, struct.pack("<II", zlib.crc32(data), len(data) & 0xFFFFFFFF)])


def revisits(pages: DataFrame, least: int = 0) -> DataFrame:
    """(page_id, h, n, refers_to) of pages whose payload of at least that many bytes, of digest h and length n, a page of larger id has as well.

    Payloads are compared by digest and length; counts per digest are combined before they are dealt.
    """
    keyed = pages.where("page_id is not null").select("page_id", F.sha1("html").alias("h"), F.octet_length("html").alias("n"))
    keyed = keyed.where(F.col("n") >= least).withColumn("k", F.concat_ws(":", "h", "n"))
    best = keyed.groupBy("k").agg(F.max("page_id").alias("refers_to"), F.count("*").alias("c")).where("c > 1").drop("c")
    return spread_join(keyed, best, "k", ["page_id"]).where("page_id < refers_to").select("page_id", "h", "n", "refers_to").distinct()


def write(pages: DataFrame, uri: str, least: int = 0, level: int = 6) -> int:
    """Write archives of (page_id, url, html) under uri, one for each partition; returns the number of records.

    Whole records are dealt by page id, which no group of equal payloads can make uneven.
    """
    pages = pages.select(F.col("page_id").cast("long"), "url", F.coalesce("html", F.lit("")).alias("html"))
    keyed = pages.withColumns({"h": F.sha1("html"), "n": F.octet_length("html")})
    marked = keyed.join(revisits(pages, least), ["page_id", "h", "n"], "left").select("page_id", "url", "html", "refers_to")

    def store(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId()
        fs, path = pafs.FileSystem.from_uri(f"{uri}/part-{part:08d}.warc.gz")
        fs.create_dir(path.rsplit("/", 1)[0], recursive=True)
        own, n = f"{path}.{np.random.default_rng().integers(1 << 62):x}.tmp", 0
        with fs.open_output_stream(own) as f:
            for b in batches:
                raw, offsets = text_buffer(b.column(2))
                rows = zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(3).to_pylist(), offsets[:-1], offsets[1:], strict=True)
                for page, url, other, s, e in rows:
                    payload = raw[s:e].tobytes()
                    kind = "response" if other is None else "revisit"
                    args = (None if page is None else PAGE % page, kind, url, payload if other is None else None)
                    f.write(member(record(*args, digest32(payload), len(payload), None if other is None else PAGE % other), level))
                    n += 1
        if n:
            fs.move(own, path)
            yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64())], names=["n"])
        else:
            fs.delete_file(own)

    return marked.mapInArrow(store, "n long").agg(F.sum("n")).first()[0] or 0


class Members:
    """Records of one archive in turn: head() parses the headers, rest() the block; what is not asked for is skipped."""

    def __init__(self, f):
        self.f, self.at, self.size = f, 0, f.size()

    def _peek(self, n: int) -> bytes:
        self.f.seek(self.at)
        return self.f.read(n)

    def head(self) -> dict[str, str] | None:
        while True:
            first = self._peek(HEAD_BYTES)
            if not first:
                return None
            self.gzip = first[:2] == b"\x1f\x8b"
            self.skip = struct.unpack("<I", first[16:20])[0] if first[:16] == GZIP_HEAD else None
            self.plain, self.z, self.taken = b"", zlib.decompressobj(31) if self.gzip else None, 0
            while b"\r\n\r\n" not in self.plain.lstrip(b"\r\n"):
                if not self._more(HEAD_BYTES):
                    break
            body = self.plain.lstrip(b"\r\n")
            if body:
                break
            self.at += self.taken or len(first)
        cut = body.index(b"\r\n\r\n") + 4
        lines = body[: cut - 4].decode("utf-8", "replace").split("\r\n")
        if not lines[0].startswith("WARC/"):
            raise ValueError("not a WARC record")
        self.block_at = len(self.plain) - len(body) + cut
        self.headers = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
        self.length = int(self.headers["content-length"])
        return self.headers

    def _more(self, n: int) -> bool:
        if self.z is not None and self.z.eof:
            return False
        raw = self._peek_at(self.at + self.taken, n)
        if not raw:
            return False
        if self.z is None:
            self.plain += raw
            self.taken += len(raw)
        else:
            self.plain += self.z.decompress(raw)
            self.taken += len(raw) - len(self.z.unused_data)
        return True

    def _peek_at(self, at: int, n: int) -> bytes:
        self.f.seek(at)
        return self.f.read(n)

    def http_head(self) -> bytes:
        """The start of the block up to the end of its HTTP headers."""
        while (cut := self.plain.find(b"\r\n\r\n", self.block_at)) < 0 and len(self.plain) < self.block_at + self.length:
            if not self._more(HEAD_BYTES):
                break
        return self.plain[self.block_at : cut + 4] if 0 <= cut < self.block_at + self.length else b""

    def rest(self) -> bytes:
        """The whole block."""
        parts = [self.plain]
        have = len(self.plain)
        while have < self.block_at + self.length:
            self.plain = b""
            if not self._more(1 << 18):
                raise ValueError("record is cut short")
            parts.append(self.plain)
            have += len(self.plain)
        self.plain = b"".join(parts)
        return self.plain[self.block_at : self.block_at + self.length]

    def next(self) -> None:
        if self.skip:
            self.at += self.skip
        elif self.z is None:
            self.at += self.block_at + self.length + 4
        else:
            while not self.z.eof:
                self.plain = b""
                if not self._more(1 << 18):
                    break
            self.at += self.taken


class WarcPartition(InputPartition):
    def __init__(self, uri: str):
        self.uri = uri


class WarcReader(DataSourceReader):
    def __init__(self, options: dict):
        self.uri = options["path"]
        self.payload = str(options.get("payload", "true")).lower() == "true"
        self.verify = str(options.get("verify", "false")).lower() == "true"
        self.wanted: dict[str, set] = {}

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        """Predicates on record type and on headers are decided before a payload is decoded; others stay with Spark."""
        for f in filters:
            column = f.attribute[0] if len(f.attribute) == 1 else ""
            if isinstance(f, (EqualTo, In)) and column in ("record_type", "record_id", "target_uri", "payload_digest", "refers_to"):
                values = {f.value} if isinstance(f, EqualTo) else set(f.value)
                self.wanted[column] = values & self.wanted.get(column, values)
            elif not (isinstance(f, IsNotNull) and column in self.wanted):
                yield f

    def partitions(self) -> list[WarcPartition]:
        fs, path = pafs.FileSystem.from_uri(self.uri)
        info = fs.get_file_info(path)
        if info.type == pafs.FileType.File:
            return [WarcPartition(self.uri)]
        if info.type == pafs.FileType.NotFound:
            return []
        found = fs.get_file_info(pafs.FileSelector(path))
        names = sorted(x.base_name for x in found if x.base_name.endswith((".warc", ".warc.gz")))
        return [WarcPartition(f"{self.uri}/{n}") for n in names]

    def read(self, partition: WarcPartition | None) -> Iterator[pa.RecordBatch]:
        if partition is None:  # no archive was planned
            return
        fs, path = pafs.FileSystem.from_uri(partition.uri)
        with fs.open_input_file(path) as f:
            yield from self._batches(Members(f))

    def _batches(self, members: Members) -> Iterator[pa.RecordBatch]:
        rows, held = [], 0
        while (h := members.head()) is not None:
            row = {
                "record_id": h.get("warc-record-id"),
                "record_type": h.get("warc-type"),
                "target_uri": h.get("warc-target-uri"),
                "payload_digest": h.get("warc-payload-digest", "").removeprefix("sha1:") or None,
                "refers_to": h.get("warc-refers-to"),
            }
            if all(row[k] in v for k, v in self.wanted.items()):
                http, payload = members.http_head(), None
                if row["record_type"] == "response" and (self.payload or self.verify):
                    payload = members.rest()[len(http) :]
                    if self.verify and digest32(payload) != row["payload_digest"]:
                        raise ValueError(f"payload of {row['record_id']} has another digest")
                sizes = [x.split(b":")[1] for x in http.split(b"\r\n") if x.lower().startswith(b"content-length:")]
                row["payload_bytes"] = int(sizes[0]) if payload is None and sizes else len(payload or b"")
                row["payload"] = payload if self.payload else None
                held += len(row["payload"] or b"")
                rows.append(row)
            members.next()
            if len(rows) >= 10_000 or held > 1 << 25:
                yield self._batch(rows)
                rows, held = [], 0
        if rows:
            yield self._batch(rows)

    @staticmethod
    def _batch(rows: list[dict]) -> pa.RecordBatch:
        kinds = [pa.string()] * 4 + [pa.int64(), pa.string(), pa.binary()]
        return pa.RecordBatch.from_arrays([pa.array([r[c] for r in rows], k) for c, k in zip(COLUMNS, kinds, strict=True)], names=COLUMNS)


class WarcDataSource(DataSource):
    """spark.read.format("warc"): options path, payload (decode it, default true), verify (check digests)."""

    @classmethod
    def name(cls) -> str:
        return "warc"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> WarcReader:
        return WarcReader(self.options)


def read(spark: SparkSession, uri: str, payload: bool = True, verify: bool = False) -> DataFrame:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(WarcDataSource)
    return spark.read.format("warc").option("payload", payload).option("verify", verify).load(uri)
