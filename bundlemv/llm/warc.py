"""WARC archives as a Spark data source, and deduplicated archiving of pages.

Reading plans one partition per archive file. Filters on the record type and on headers are
pushed into the reader, which parses a record's headers first and seeks past the block of a
record that no filter wants; the payload is decoded only if the asked schema has it (or
``verify`` is on, which recomputes each stored payload's digest). Ask for fewer columns with
``spark.read.format("warc").schema(...)``.

Writing takes rows of ``WRITE_SCHEMA``; every task writes archive files of bounded size, and the
files become visible together through a manifest, so lost or repeated task attempts leave
nothing that a read sees. A folder without a manifest is read as it is.

Paths are URIs that ``pyarrow.fs`` opens (file, hdfs, s3, gs), in a folder that driver and
executors share.

``archive_pages``: of records with equal payloads of at least ``min_bytes``, the one with
the largest page id is stored as a response and the others as revisits of it; smaller ones
are all responses. Defined cases: a null payload is empty; null urls have no target header;
rows with a null page id never become the stored copy of a named page; in a group of null
ids only, and among repeated rows of the largest id, all are responses; an empty table
makes an empty archive.
Columns beside the named ones are not read, whatever they are called; functions that
return whole rows return them as they are.
"""

from __future__ import annotations

import hashlib
import io
import json
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from urllib.parse import quote

import pyarrow as pa
from pyarrow import fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import (
    DataSource, DataSourceArrowWriter, DataSourceReader, EqualNullSafe, EqualTo, GreaterThan, GreaterThanOrEqual, In, InputPartition,
    IsNotNull, IsNull, LessThan, LessThanOrEqual, StringContains, StringEndsWith, StringStartsWith, WriterCommitMessage,
)
from pyspark.sql.types import StructType

from bundlemv.session import drop_at_exit, materialise, scratch_path

READ_SCHEMA = (
    "record_type string, record_id string, target_uri string, warc_date string, content_type string, content_length long, "
    "payload_digest string, refers_to string, page_id long, refers_to_page long, file string, offset long, "
    "http_status int, payload_bytes long, payload binary"
)
WRITE_SCHEMA = "page_id long, url string, payload binary, payload_digest string, record_type string, refers_to long"
#: Archive files are closed at this size.
FILE_BYTES = 256 << 20
#: Duplicate groups of up to so many are broadcast (a row is below 100 bytes); beyond, they are joined by shuffle.
BROADCAST_GROUPS = 100_000
# Fixed values of the format.
VERSION = b"WARC/1.1"
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
HTTP_TYPE = "application/http; msgtype=response"
PAGE_HEADER, PAGE_REFERS_HEADER = "X-Page-ID", "X-Refers-To-Page-ID"


def open_fs(uri: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(uri)


# --- records ------------------------------------------------------------------


def record_urn(page_id: int | None, digest: str) -> str:
    return f"<{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{page_id}:{digest}').urn}>"


def record_bytes(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None, date: str) -> bytes:
    """One record; with ``refers_to`` a revisit, whose block ends behind the HTTP headers."""
    revisit = refers_to is not None
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http if revisit else http + payload
    head = [("WARC-Type", "revisit" if revisit else "response"), ("WARC-Record-ID", record_urn(page_id, digest)), ("WARC-Date", date)]
    if url is not None:
        head.append(("WARC-Target-URI", quote(url, safe="%/:=&?~#+!$,;'@()*[]")))
    head.append(("WARC-Payload-Digest", f"sha1:{digest}"))
    if page_id is not None:
        head.append((PAGE_HEADER, str(page_id)))
    if revisit:
        head += [("WARC-Profile", REVISIT_PROFILE), ("WARC-Refers-To", record_urn(refers_to, digest)), (PAGE_REFERS_HEADER, str(refers_to))]
    head += [("Content-Type", HTTP_TYPE), ("Content-Length", str(len(block)))]
    return b"".join([VERSION, b"\r\n", *[f"{k}: {v}\r\n".encode() for k, v in head], b"\r\n", block, b"\r\n\r\n"])


def read_headers(f: io.BufferedIOBase) -> dict[str, str] | None:
    """The headers of the record at hand, by lower-case name; None at the end of the archive."""
    line = f.readline()
    while line in (b"\r\n", b"\n"):
        line = f.readline()
    if not line:
        return None
    if not line.startswith(b"WARC/"):
        raise ValueError(f"no record where one should begin: {line[:40]!r}")
    out, last = {}, ""
    while (line := f.readline().rstrip(b"\r\n")):
        text = line.decode("utf-8", "replace")
        if text[0] in " \t" and last:  # a folded line
            out[last] += " " + text.strip()
        else:
            name, _, value = text.partition(":")
            last = name.strip().lower()
            out[last] = value.strip()
    return out


def http_head(block: bytes) -> tuple[int | None, int | None, int]:
    """(status, stated content length, where the payload begins) of an HTTP response."""
    end = block.find(b"\r\n\r\n")
    if end < 0 or not block.startswith(b"HTTP/"):
        return None, None, 0
    lines = block[:end].decode("latin-1").split("\r\n")
    first = lines[0].split()
    stated = next((x.partition(":")[2].strip() for x in lines[1:] if x.lower().startswith("content-length:")), "")
    return int(first[1]) if len(first) > 1 and first[1].isdigit() else None, int(stated) if stated.isdigit() else None, end + 4


class _Inflated(io.RawIOBase):
    """The concatenated members of a gzip archive as one stream; seeks forward only."""

    def __init__(self, raw):
        self.raw, self.z, self.left, self.at = raw, zlib.decompressobj(31), b"", 0

    def readable(self) -> bool:
        return True

    def readinto(self, into) -> int:
        while True:
            data = self.left or self.raw.read(1 << 16)
            if not data:
                return 0
            got = self.z.decompress(data, len(into))
            self.left = self.z.unconsumed_tail
            if self.z.eof:
                self.left, self.z = self.z.unused_data, zlib.decompressobj(31)
            if got:
                into[: len(got)] = got
                return len(got)


def _skip(f: io.BufferedReader, n: int, seekable: bool) -> None:
    if seekable:
        f.seek(n, io.SEEK_CUR)
        return
    while n > 0 and (got := f.read(min(n, 1 << 16))):
        n -= len(got)


# --- reading ------------------------------------------------------------------


@dataclass
class ArchiveFile(InputPartition):
    path: str
    size: int

    def __init__(self, path: str, size: int):
        super().__init__(path)
        self.path, self.size = path, size


def _bare(digest: str | None) -> str | None:
    return digest.partition(":")[2].lower() if digest and ":" in digest else digest


def _number(s: str | None) -> int | None:
    return int(s) if s and s.lstrip("-").isdigit() else None


#: Columns that headers alone decide, so that filters on them come before a block is read.
FROM_HEADERS = {
    "record_type": lambda h: h.get("warc-type"),
    "record_id": lambda h: h.get("warc-record-id"),
    "target_uri": lambda h: h.get("warc-target-uri"),
    "warc_date": lambda h: h.get("warc-date"),
    "content_type": lambda h: h.get("content-type"),
    "content_length": lambda h: _number(h.get("content-length")),
    "payload_digest": lambda h: _bare(h.get("warc-payload-digest")),
    "refers_to": lambda h: h.get("warc-refers-to"),
    "page_id": lambda h: _number(h.get(PAGE_HEADER.lower())),
    "refers_to_page": lambda h: _number(h.get(PAGE_REFERS_HEADER.lower())),
}
_TESTS = {
    EqualTo: lambda x, v: x is not None and x == v,
    EqualNullSafe: lambda x, v: x == v,
    GreaterThan: lambda x, v: x is not None and x > v,
    GreaterThanOrEqual: lambda x, v: x is not None and x >= v,
    LessThan: lambda x, v: x is not None and x < v,
    LessThanOrEqual: lambda x, v: x is not None and x <= v,
    In: lambda x, v: x is not None and x in v,
    IsNull: lambda x, v: x is None,
    IsNotNull: lambda x, v: x is not None,
    StringStartsWith: lambda x, v: x is not None and x.startswith(v),
    StringEndsWith: lambda x, v: x is not None and x.endswith(v),
    StringContains: lambda x, v: x is not None and v in x,
}


class WarcReader(DataSourceReader):
    def __init__(self, schema: StructType, options: dict):
        self.path, self.names = options["path"], schema.names
        self.arrow = {f.name: f.dataType.simpleString() for f in schema}
        self.verify = options.get("verify", "false").lower() == "true"
        self.tests: list[tuple[str, type, object]] = []
        unknown = set(self.names) - {f.split()[0] for f in READ_SCHEMA.split(", ")}
        if unknown:
            raise ValueError(f"no such columns in an archive: {sorted(unknown)}")

    def pushFilters(self, filters):  # noqa: N802 - Spark's name
        for f in filters:
            name = f.attribute[0] if len(f.attribute) == 1 else ""
            if name in FROM_HEADERS and type(f) in _TESTS:
                self.tests.append((name, type(f), getattr(f, "value", None)))
            else:
                yield f

    def partitions(self):
        fs, root = open_fs(self.path)
        info = fs.get_file_info(root)
        if info.type == pafs.FileType.File:
            return [ArchiveFile(root, info.size)]
        found = fs.get_file_info(pafs.FileSelector(root, recursive=True))
        sizes = {f.path: f.size for f in found if f.path.endswith((".warc", ".warc.gz"))}
        manifests = [f.path for f in found if f.base_name.startswith("_committed-")]
        if manifests:
            names = {n for m in manifests for n in json.loads(fs.open_input_stream(m, compression=None).read())}
            sizes = {p: n for p, n in sizes.items() if p.rpartition("/")[2] in names}
        return [ArchiveFile(p, n) for p, n in sorted(sizes.items())]

    def read(self, partition):
        if partition is None:  # Spark asks once even if no file was planned
            return
        fs, _ = open_fs(self.path)
        packed = partition.path.endswith(".gz")
        want_block = self.verify or not {"payload", "payload_bytes", "http_status"}.isdisjoint(self.names)
        want_payload = self.verify or "payload" in self.names
        columns: dict[str, list] = {n: [] for n in self.names}
        held = 0
        with fs.open_input_file(partition.path) as raw:
            f = io.BufferedReader(_Inflated(raw) if packed else raw, 1 << 18)
            while True:
                offset = -1 if packed else f.tell()
                head = read_headers(f)
                if head is None:
                    break
                length = _number(head.get("content-length")) or 0
                if not all(_TESTS[kind](FROM_HEADERS[name](head), value) for name, kind, value in self.tests):
                    _skip(f, length, not packed)
                    continue
                row = {n: FROM_HEADERS[n](head) for n in self.names if n in FROM_HEADERS} | {"file": partition.path, "offset": offset}
                if want_block:
                    first = f.read(length if want_payload else min(length, 1 << 13))
                    if len(first) < (length if want_payload else min(length, 1 << 13)):
                        raise ValueError(f"{partition.path} ends within a record")
                    status, stated, begin = http_head(first)
                    _skip(f, length - len(first), not packed)
                    revisit = head.get("warc-type") == "revisit"
                    row |= {"http_status": status, "payload_bytes": stated if revisit or stated is not None and not want_payload else length - begin, "payload": None if revisit else first[begin:] if want_payload else None}
                    if self.verify and not revisit and (known := _bare(head.get("warc-payload-digest"))) and hashlib.sha1(first[begin:]).hexdigest() != known:
                        raise ValueError(f"a payload in {partition.path} does not have the digest {known}")
                else:
                    _skip(f, length, not packed)
                for n in self.names:
                    columns[n].append(row.get(n))
                held += 200 + (length if "payload" in self.names else 0)
                if held > 8 << 20:
                    yield self._batch(columns)
                    columns, held = {n: [] for n in self.names}, 0
        if held:
            yield self._batch(columns)

    def _batch(self, columns: dict[str, list]) -> pa.RecordBatch:
        kinds = {"string": pa.string(), "bigint": pa.int64(), "int": pa.int32(), "binary": pa.binary()}
        return pa.RecordBatch.from_arrays([pa.array(columns[n], kinds[self.arrow[n]]) for n in self.names], names=self.names)


# --- writing ------------------------------------------------------------------


@dataclass
class Written(WriterCommitMessage):
    files: list[str]
    records: int


class WarcWriter(DataSourceArrowWriter):
    def __init__(self, options: dict):
        self.path = options["path"]
        self.packed = options.get("compression", "none") == "gzip"
        self.date = options.get("date", "1970-01-01T00:00:00Z")
        self.most = int(options.get("filebytes", FILE_BYTES))

    def write(self, iterator):
        fs, root = open_fs(self.path)
        fs.create_dir(root, recursive=True)
        files, records, out, size = [], 0, None, 0
        for b in iterator:
            cols = [b.column(n) for n in ("page_id", "url", "payload", "payload_digest", "record_type", "refers_to")]
            for row in zip(*cols):
                page, url, payload, digest, kind, refers = (x.as_py() for x in row)
                data = record_bytes(page, url, payload or b"", digest, refers if kind == "revisit" else None, self.date)
                if self.packed:
                    z = zlib.compressobj(6, wbits=31)
                    data = z.compress(data) + z.flush()
                if out is None or size >= self.most:
                    if out:
                        out.close()
                    files.append(f"{uuid.uuid4().hex}.warc" + ".gz" * self.packed)
                    out, size = fs.open_output_stream(f"{root}/{files[-1]}", compression=None), 0
                out.write(data)
                size += len(data)
                records += 1
        if out:
            out.close()
        return Written(files, records)

    def commit(self, messages):
        fs, root = open_fs(self.path)
        fs.create_dir(root, recursive=True)
        with fs.open_output_stream(f"{root}/_committed-{uuid.uuid4().hex}.json") as f:
            f.write(json.dumps([n for m in messages if m for n in m.files]).encode())

    def abort(self, messages):
        fs, root = open_fs(self.path)
        for n in [n for m in messages if m for n in m.files]:
            fs.delete_file(f"{root}/{n}")


class WarcDataSource(DataSource):
    @classmethod
    def name(cls):
        return "warc"

    def schema(self):
        return READ_SCHEMA

    def reader(self, schema):
        return WarcReader(schema, self.options)

    def writer(self, schema, overwrite):
        if overwrite:
            raise ValueError("archives are appended to; write to a new folder instead")
        return WarcWriter(self.options)


def register(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(WarcDataSource)


# --- archiving pages ------------------------------------------------------------


def classify(pages: DataFrame, min_bytes: int = 1000) -> DataFrame:
    """page_id, url, html -> rows to write: record_type response or revisit, refers_to for revisits."""
    rows = pages.select(
        F.col("page_id").cast("long").alias("page_id"), "url", F.coalesce(F.col("html").cast("binary"), F.lit(b"")).alias("payload"),
    ).withColumn("payload_digest", F.sha1("payload"))
    large = F.length("payload") >= min_bytes
    groups = (
        rows.where(large).groupBy("payload_digest").agg(F.max("page_id").alias("stored"), F.count("*").alias("n"))
        .where("n > 1 and stored is not null").select(F.col("payload_digest").alias("key"), "stored")
    )
    groups = materialise(groups, "warc-groups")
    # small payloads get keys of their own, so that a frequent small one is no hot key
    rows = rows.withColumn("key", F.when(large, F.col("payload_digest")).otherwise(F.concat_ws(":", F.lit("small"), "page_id", F.xxhash64("url"))))
    if groups.count() <= BROADCAST_GROUPS:
        groups = F.broadcast(groups)
    again = F.col("stored").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("stored"))
    return rows.join(groups, "key", "left").select(
        "page_id", "url", "payload", "payload_digest", F.when(again, "revisit").otherwise("response").alias("record_type"), F.when(again, F.col("stored")).alias("refers_to")
    )


def archive_pages(pages: DataFrame, path: str, min_bytes: int = 1000, compression: str = "none") -> None:
    """Write a record per page to archives in the folder ``path``."""
    register(pages.sparkSession)
    classify(pages, min_bytes).write.format("warc").mode("append").option("compression", compression).save(path)


def op3(spark, sf_dir):
    from bundlemv.sources.tables import load_table

    path = scratch_path(spark, "warc")
    archive_pages(load_table(spark, sf_dir, "pages"), path)
    drop_at_exit(spark, path)
    asked = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to_page long"
    read = spark.read.format("warc").schema(asked).option("verify", "true").load(path)
    return read.where(F.col("record_type").isin("response", "revisit")).withColumnRenamed("refers_to_page", "refers_to")


OP3_SQL = """
with p as (select page_id, encode(coalesce(html, '')) as b from pages),
d as (select page_id, octet_length(b) as n, sha1(b) as h from p),
g as (select *, max(page_id) over (partition by h) as top from d)
select page_id, cast(n as bigint) as payload_bytes, h as payload_digest,
       case when n >= 1000 and page_id <> top then 'revisit' else 'response' end as record_type,
       case when n >= 1000 and page_id <> top then top end as refers_to
from g
"""
