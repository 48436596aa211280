"""WARC archives whose records are Zstandard frames under a dictionary that the archive carries itself.

An archive begins with a skippable frame that holds the dictionary, which is built from the first records of that archive; each record
after it is one frame. Of records with equal payloads of at least REVISIT_BYTES, that with the largest page_id is written as response and
the others as revisits that refer to it. Equal payloads are found by digest in narrow rows, pre-aggregated, and joined back between two
tables, so that Spark can split a digest that many pages share.

Null html is an empty payload; null urls are empty; null page_ids are written and read as such. Rows that repeat the responding page_id are
responses too. An empty table gives no archive and an empty result. Archives go to a temporary name and are then renamed, so a task that
is run again replaces its own.
"""

from __future__ import annotations

import base64
import hashlib
import io
import struct
import uuid
from collections.abc import Iterator
from urllib.parse import quote, urlparse

import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import ship_package
from .common import fresh_path, materialise

REVISIT_BYTES = 1000
#: the dictionary is fitted on at most so many bytes of an archive's first records, which wait in memory meanwhile
SAMPLE_BYTES, DICT_BYTES = 2 << 20, 64 << 10
#: an archive is closed after so many bytes of records
ARCHIVE_BYTES = 128 << 20
LEVEL = 3
DICT_MAGIC = 0x184D2A5D  # fixed value: the skippable frame that is reserved for dictionaries of archives
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
SPACE = uuid.UUID("6ba7b811-9dad-11d1-80b4-00c04fd430c8")

RECORD = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long"


# --- files in shared storage, from executors --------------------------------------------------------------------------------


def _store(path: str):
    """A pyarrow file system and the path in it. Paths without a scheme are local ones."""
    from pyarrow import fs

    if not urlparse(path).scheme:
        return fs.LocalFileSystem(), path
    if path.startswith("file:"):
        return fs.LocalFileSystem(), "/" + path[5:].lstrip("/")
    return fs.FileSystem.from_uri(path)


# --- records ----------------------------------------------------------------------------------------------------------------


def record_id(page_id: int | None) -> str:
    return f"<urn:uuid:{uuid.uuid5(SPACE, f'page:{page_id}')}>"


def _head(first: str, fields: list[tuple[str, object]]) -> bytes:
    return "".join([first, "\r\n", *(f"{k}: {v}\r\n" for k, v in fields), "\r\n"]).encode()


def build_record(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None, is_revisit: bool, date: str) -> bytes:
    http = _head("HTTP/1.1 200 OK", [("Content-Type", "text/html; charset=utf-8"), ("Content-Length", len(payload))])
    block = http if is_revisit else http + payload
    fields = [
        ("WARC-Type", "revisit" if is_revisit else "response"), ("WARC-Record-ID", record_id(page_id)), ("WARC-Date", date),
        ("WARC-Target-URI", quote(url or "", safe="!#$%&'()*+,/:;=?@[]~")),
        ("WARC-Payload-Digest", "sha1:" + base64.b32encode(bytes.fromhex(digest)).decode()),
        ("Page-ID", "" if page_id is None else page_id), ("Content-Type", "application/http; msgtype=response"), ("Content-Length", len(block)),
    ]
    if is_revisit:
        fields += [("WARC-Profile", PROFILE), ("WARC-Refers-To", record_id(refers_to)), ("Refers-To-Page-ID", refers_to)]
    return _head("WARC/1.1", fields) + block + b"\r\n\r\n"


def _read_head(f) -> tuple[str, dict[str, str]] | None:
    first = f.readline()
    if not first:
        return None
    fields = {}
    while line := f.readline().rstrip(b"\r\n"):
        k, _, v = line.decode().partition(": ")
        fields[k.lower()] = v
    return first.decode().rstrip("\r\n"), fields


def read_records(raw) -> Iterator[tuple[dict[str, str], dict[str, str], bytes]]:
    """(record fields, HTTP fields, payload) of each record of an open archive, one record in memory at a time."""
    start = raw.read(8)
    dictionary = None
    if len(start) == 8 and struct.unpack("<I", start[:4])[0] == DICT_MAGIC:
        dictionary = zstandard.ZstdCompressionDict(raw.read(struct.unpack("<I", start[4:])[0]))
    else:
        raw.seek(0)
    plain = io.BufferedReader(zstandard.ZstdDecompressor(dict_data=dictionary).stream_reader(raw, read_across_frames=True, closefd=False), 1 << 20)
    while head := _read_head(plain):
        fields = head[1]
        block = plain.read(int(fields["content-length"]))
        if plain.read(4) != b"\r\n\r\n":
            raise ValueError("a record does not end where its length says")
        if fields["warc-type"] in ("response", "revisit"):
            body = io.BytesIO(block)
            http = _read_head(body)[1]
            yield fields, http, body.read()


class ArchiveWriter:
    """Archives of one task: opened when rows come, closed when full."""

    def __init__(self, folder: str, name: str, date: str) -> None:
        self.folder, self.name, self.date, self.n = folder, name, date, 0
        self.done: list[tuple[str, int, int]] = []
        self._clear()

    def _clear(self) -> None:
        self.waiting, self.size, self.records, self.out, self.packer = [], 0, 0, None, None

    def add(self, record: bytes) -> None:
        self.size += len(record)
        self.records += 1
        if self.out is None:
            self.waiting.append(record)
            if self.size >= SAMPLE_BYTES:
                self._open()
        else:
            self.out.write(self.packer.compress(record))
        if self.size >= ARCHIVE_BYTES:
            self.close()

    def _open(self) -> None:
        self.fs, place = _store(f"{self.folder}/{self.name}-{self.n:05d}.warc.zst")
        self.n += 1
        self.place, self.held = place, f"{place}.{uuid.uuid4().hex}.tmp"
        self.fs.create_dir(place.rpartition("/")[0], recursive=True)
        self.out = self.fs.open_output_stream(self.held)
        try:
            dictionary = zstandard.train_dictionary(DICT_BYTES, [r[i : i + (128 << 10)] for r in self.waiting for i in range(0, len(r), 128 << 10)])
            data = dictionary.as_bytes()
            self.out.write(struct.pack("<II", DICT_MAGIC, len(data)) + data)
        except zstandard.ZstdError:  # too few records to learn from: the archive has none, and readers see that
            dictionary = None
        self.packer = zstandard.ZstdCompressor(level=LEVEL, dict_data=dictionary, write_checksum=True)
        info = b"software: halograph\r\nformat: WARC File Format 1.1\r\n"
        self.out.write(self.packer.compress(_head("WARC/1.1", [("WARC-Type", "warcinfo"), ("WARC-Record-ID", f"<urn:uuid:{uuid.uuid5(SPACE, self.place)}>"), ("WARC-Date", self.date), ("Content-Type", "application/warc-fields"), ("Content-Length", len(info))]) + info + b"\r\n\r\n"))
        for r in self.waiting:
            self.out.write(self.packer.compress(r))
        self.waiting = []

    def close(self) -> None:
        if not self.records:
            return
        if self.out is None:
            self._open()
        self.out.close()
        self.fs.move(self.held, self.place)
        self.done.append((f"{self.folder}/{self.place.rpartition('/')[2]}", self.records, self.size))
        self._clear()


def with_revisits(pages: DataFrame) -> DataFrame:
    """page_id, url, payload, digest and, for pages whose payload another page responds with, refers_to."""
    payload = F.encode(F.coalesce("html", F.lit("")), "utf-8")
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", payload.alias("payload")).withColumn("digest", F.sha1("payload"))
    shared = rows.where(F.octet_length("payload") >= REVISIT_BYTES).groupBy("digest").agg(F.max("page_id").alias("rep"), F.count("*").alias("n"))
    shared = materialise(shared.where("n > 1 AND rep IS NOT NULL").select("digest", "rep"), "payloads")
    # null-safe, so that a null page_id refers to the one that has an id
    return rows.join(shared, "digest", "left").withColumn("refers_to", F.when(~F.col("page_id").eqNullSafe(F.col("rep")), F.col("rep"))).drop("rep")


def write_archives(pages: DataFrame, folder: str, date: str = "2000-01-01T00:00:00Z") -> DataFrame:
    """Write the archives; returns the manifest (archive, records, bytes), which is itself a table in shared storage."""
    ship_package(pages.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w = ArchiveWriter(folder, f"part-{TaskContext.get().partitionId():05d}", date)
        for b in batches:
            for page_id, url, payload, digest, refers in zip(*(b.column(c) for c in ("page_id", "url", "payload", "digest", "refers_to")), strict=True):
                w.add(build_record(page_id.as_py(), url.as_py(), payload.as_py(), digest.as_py(), refers.as_py(), refers.is_valid, date))
        w.close()
        if w.done:
            yield pa.record_batch([pa.array(c) for c in zip(*w.done, strict=True)], names=["archive", "records", "bytes"])

    rows = with_revisits(pages).select("page_id", "url", "payload", "digest", "refers_to")
    return materialise(rows.mapInArrow(run, "archive string, records long, bytes long"), "manifest")


def read_archives(manifest: DataFrame, n_archives: int | None = None) -> DataFrame:
    """One row per archived page: RECORD. Payloads are hashed again, and a digest that differs is an error."""
    n = n_archives or max(1, manifest.count())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for path in b.column(0).to_pylist():
                fs, place = _store(path)
                rows: list[tuple] = []
                with fs.open_input_file(place) as raw:
                    for fields, http, payload in read_records(raw):
                        digest = base64.b32decode(fields["warc-payload-digest"].removeprefix("sha1:")).hex()
                        if fields["warc-type"] == "response" and digest != hashlib.sha1(payload).hexdigest():
                            raise ValueError(f"{path}: a payload does not have its digest")
                        page, refers = fields["page-id"], fields.get("refers-to-page-id")
                        rows.append((int(page) if page else None, int(http["content-length"]), digest, fields["warc-type"], int(refers) if refers else None))
                        if len(rows) == 10_000:
                            yield _batch(rows)
                            rows = []
                if rows:
                    yield _batch(rows)

    return manifest.select("archive").repartitionByRange(n, "archive").mapInArrow(run, RECORD)


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64())
    names = ("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
    return pa.record_batch([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)


def op3_warc_dictionary(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html")
    return read_archives(write_archives(pages, fresh_path(spark, "warc")))


ORACLE_OP3 = """
WITH p AS (
  SELECT page_id, encode(coalesce(html, '')) AS payload FROM pages
), d AS (
  SELECT page_id, CAST(octet_length(payload) AS BIGINT) AS payload_bytes, sha1(payload) AS payload_digest FROM p
), r AS (
  SELECT *, CASE WHEN payload_bytes >= 1000 THEN max(page_id) OVER (PARTITION BY payload_digest) ELSE page_id END AS rep FROM d
)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN rep = page_id THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN rep <> page_id THEN rep END AS refers_to
FROM r
"""
