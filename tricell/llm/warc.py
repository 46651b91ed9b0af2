"""A deterministic sharded WARC writer, and its reader.

Records are dealt to shards that are ranges of ids, cut so that shards hold
about equal bytes; the cuts come from exact sums by the ids' leading bits, so
the same table always gives the same shards, however it is partitioned.  In
its shard each task writes records in id order, one gzip member each, and
starts a new file once the compressed size reaches the limit.  A file is
written under a temporary name and renamed when it is whole; task retries write
the same bytes under the same name.  The manifest, again written under a
temporary name, comes last and makes the archive visible: the reader opens
exactly the files that it lists.

Of the records with equal payloads (by SHA-256 and length) of at least
`least_revisit` bytes, the least id is the response and the others revisit it.

Defined results: a null payload is empty; rows with a null id come first, are
always responses, and are never referred to; rows that tie on the least id of
a payload are all responses; an empty table gives a manifest without files; no
column of the table but id, address and payload is read, so none can clash.
"""

from __future__ import annotations

import base64
import hashlib
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .ranges import id_cells
from .storage import fresh_path, materialise

# Fixed values of the archive format.
VERSION = b"WARC/1.1"
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
_NAMESPACE = uuid.UUID("6ba7b811-9dad-11d1-80b4-00c04fd430c8")


@dataclass(frozen=True)
class WarcConfig:
    file_bytes: int = 64 << 20
    shard_bytes: int = 128 << 20
    least_revisit: int = 0
    date: str = "2024-01-01T00:00:00Z"
    level: int = 6


def payload_digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_id(page: int | None, digest: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(_NAMESPACE, f'{page}:{digest}')}>"


def _block(fields: list[tuple[str, str]], body: bytes) -> bytes:
    head = b"".join(f"{k}: {v}\r\n".encode() for k, v in [*fields, ("Content-Length", str(len(body)))])
    return VERSION + b"\r\n" + head + b"\r\n" + body + b"\r\n\r\n"


def encode_record(page: int | None, url: str | None, payload: bytes, refers_to: int | None, config: WarcConfig) -> bytes:
    """One record with headers made anew; a revisit carries no payload."""
    digest = payload_digest(payload)
    target = "".join(c for c in url or "" if c not in "\r\n") or f"urn:page:{page}"
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    body = http if refers_to is not None else http + payload
    fields = [
        ("WARC-Type", "response" if refers_to is None else "revisit"),
        ("WARC-Record-ID", record_id(page, digest)),
        ("WARC-Date", config.date),
        ("WARC-Target-URI", target),
        ("WARC-Payload-Digest", f"sha1:{digest}"),
        ("WARC-Block-Digest", f"sha1:{payload_digest(body)}"),
        ("Content-Type", "application/http; msgtype=response"),
    ]
    if page is not None:
        fields.append(("X-Page-Id", str(page)))
    if refers_to is not None:
        fields += [("WARC-Profile", REVISIT_PROFILE), ("WARC-Refers-To", record_id(refers_to, digest)), ("WARC-Truncated", "length")]
    return _block(fields, body)


def _gzip(data: bytes, level: int) -> bytes:
    packer = zlib.compressobj(level, zlib.DEFLATED, 31)
    return packer.compress(data) + packer.flush()


class _Roller:
    """Writes the records of one shard to files of bounded size."""

    def __init__(self, base: str, shard: int, config: WarcConfig):
        self.fs, self.root = pafs.FileSystem.from_uri(base)
        self.shard, self.config, self.turn, self.out = shard, config, 0, None
        self.done: list[tuple[str, int, int]] = []

    def _open(self) -> None:
        self.name = f"shard-{self.shard:06d}-{self.turn:05d}.warc.gz"
        self.temporary = f"{self.root}/.{self.name}.{uuid.uuid4().hex}.tmp"
        self.out, self.size, self.records = self.fs.open_output_stream(self.temporary, compression=None), 0, 0
        info = _block([("WARC-Type", "warcinfo"), ("WARC-Record-ID", record_id(None, self.name)), ("WARC-Date", self.config.date), ("WARC-Filename", self.name), ("Content-Type", "application/warc-fields")], b"format: WARC File Format 1.1\r\n")
        self._write(info)

    def _write(self, data: bytes) -> None:
        packed = _gzip(data, self.config.level)
        self.out.write(packed)
        self.size += len(packed)

    def add(self, record: bytes) -> None:
        if self.out is None:
            self._open()
        self._write(record)
        self.records += 1
        if self.size >= self.config.file_bytes:
            self.close()

    def close(self) -> None:
        if self.out is not None:
            self.out.close()
            self.fs.move(self.temporary, f"{self.root}/{self.name}")
            self.done.append((self.name, self.records, self.size))
            self.turn, self.out = self.turn + 1, None


def _writer(base: str, config: WarcConfig):
    """Takes rows in (shard, page_id) order, a page's marks before the page; yields the files it has made."""

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        roller, done = None, []
        current, originals = None, {}
        for batch in batches:
            columns = [batch.column(c).to_pylist() for c in ("shard", "page_id", "mark", "url", "payload", "original")]
            for shard, page, mark, url, payload, original in zip(*columns, strict=True):
                if page != current:
                    current, originals = page, {}
                if mark is not None:
                    originals[bytes(mark)] = original
                    continue
                if roller is None or roller.shard != shard:
                    if roller:
                        roller.close()
                        done += roller.done
                    roller = _Roller(base, shard, config)
                payload = payload or b""
                refers_to = originals.get(hashlib.sha256(payload).digest()) if originals else None
                roller.add(encode_record(page, url, payload, refers_to, config))
        if roller:
            roller.close()
            done += roller.done
        yield pa.RecordBatch.from_arrays([pa.array([d[i] for d in done], t) for i, t in enumerate((pa.string(), pa.int64(), pa.int64()))], ["file", "records", "bytes"])

    return write


def write_archive(pages: DataFrame, base: str | None = None, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html", config: WarcConfig = WarcConfig()) -> str:
    """Write one record for each row of `pages`; returns the archive's folder.

    A payload column of strings is written as UTF-8.  The payloads are
    shuffled once; the marks that make a record a revisit travel with them.
    """
    spark = pages.sparkSession
    base = base or fresh_path(spark, "warc")
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(payload_col).cast("binary").alias("payload"))
    body = F.coalesce("payload", F.lit(b""))
    slim = materialise(rows.select("page_id", F.unhex(F.sha2(body, 256)).alias("mark"), F.octet_length(body).cast("long").alias("bytes")), "payloads")
    sized = slim.where((F.col("bytes") >= config.least_revisit) & F.col("page_id").isNotNull())
    shared = sized.groupBy("mark", "bytes").agg(F.min("page_id").alias("original"), F.max("page_id").alias("last")).where("original < last")
    marks = sized.join(shared, ["mark", "bytes"]).where("page_id <> original").select("page_id", "mark", "original").distinct()
    blank = lambda kind: F.lit(None).cast(kind)
    dealt = rows.select("page_id", blank("binary").alias("mark"), "url", "payload", blank("long").alias("original")).unionByName(
        marks.select("page_id", "mark", blank("string").alias("url"), blank("binary").alias("payload"), "original")
    )
    shards, _ = id_cells(slim, config.shard_bytes, "page_id", "bytes")
    ordered = (
        shards(dealt, "page_id", "shard")
        .repartition("shard")
        .sortWithinPartitions("shard", F.col("page_id").asc_nulls_first(), F.col("mark").asc_nulls_last(), "url", "payload")
        .select("shard", "page_id", "mark", "url", "payload", "original")
    )
    fs = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(base).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path
    if fs.exists(path(f"{base}/manifest")):
        raise FileExistsError(f"{base} holds an archive already")
    fs.mkdirs(path(base))
    hidden = f"{base}/_manifest-{uuid.uuid4().hex}"
    ordered.mapInArrow(_writer(base, config), "file string, records long, bytes long").write.json(hidden)
    if not fs.rename(path(hidden), path(f"{base}/manifest")):
        raise OSError(f"the manifest of {base} could not be committed")
    return base


def _members(stream) -> Iterator[bytes]:
    """The gzip members of a stream, each one inflated."""
    data, eof = b"", False
    while True:
        unpacker, parts = zlib.decompressobj(31), []
        while not unpacker.eof:
            if not data:
                data = stream.read(1 << 18)
                eof = not data
            if eof:
                break
            parts.append(unpacker.decompress(data))
            data = unpacker.unused_data
        if eof and not parts:
            return
        if not unpacker.eof:
            raise ValueError("the archive ends inside a record")
        yield b"".join(parts)


def decode_record(member: bytes) -> tuple[dict[str, str], dict[str, str], bytes]:
    """(record headers, HTTP headers, payload) of one record."""
    head, _, rest = member.partition(b"\r\n\r\n")
    lines = head.split(b"\r\n")
    if lines[0] != VERSION:
        raise ValueError(f"not a record: {lines[0][:40]!r}")
    fields = dict(x.decode().split(": ", 1) for x in lines[1:])
    body = rest[: int(fields["Content-Length"])]
    if "WARC-Block-Digest" in fields and fields["WARC-Block-Digest"] != f"sha1:{payload_digest(body)}":
        raise ValueError(f"the block of {fields['WARC-Record-ID']} does not match its digest")
    http, payload = {}, body
    if fields["Content-Type"].startswith("application/http"):
        top, _, payload = body.partition(b"\r\n\r\n")
        http = dict(x.decode().split(": ", 1) for x in top.split(b"\r\n")[1:])
    return fields, http, payload


_READ = pa.schema([("page_id", pa.int64()), ("record_id", pa.string()), ("record_type", pa.string()), ("target_uri", pa.string()), ("refers_to_record", pa.string()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("payload", pa.binary())])


def _reader(base: str):
    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = pafs.FileSystem.from_uri(base)
        for batch in batches:
            for name, records in zip(batch.column("file").to_pylist(), batch.column("records").to_pylist(), strict=True):
                rows, held, seen = [], 0, 0
                with fs.open_input_stream(f"{root}/{name}", compression=None) as stream:
                    for member in _members(stream):
                        fields, http, payload = decode_record(member)
                        if fields["WARC-Type"] == "warcinfo":
                            continue
                        seen += 1
                        kind = fields["WARC-Type"]
                        digest = fields["WARC-Payload-Digest"].removeprefix("sha1:")
                        size = int(http["Content-Length"])
                        if kind == "response" and (len(payload) != size or payload_digest(payload) != digest):
                            raise ValueError(f"the payload of {fields['WARC-Record-ID']} does not match its headers")
                        page = fields.get("X-Page-Id")
                        rows.append((int(page) if page else None, fields["WARC-Record-ID"], kind, fields["WARC-Target-URI"], fields.get("WARC-Refers-To"), size, digest, payload if kind == "response" else None))
                        held += len(payload)
                        if held > 4 << 20 or len(rows) >= 2000:
                            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), _READ, strict=True)], schema=_READ)
                            rows, held = [], 0
                if seen != records:
                    raise ValueError(f"{name} holds {seen} records; its manifest says {records}")
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), _READ, strict=True)], schema=_READ)

    return read


def read_archive(spark: SparkSession, base: str) -> DataFrame:
    """One row a record, with digests checked on the way; a revisit has no payload."""
    files = spark.read.schema("file string, records long, bytes long").json(f"{base}/manifest")
    return files.repartition("file").mapInArrow(
        _reader(base),
        "page_id long, record_id string, record_type string, target_uri string, refers_to_record string, payload_bytes long, payload_digest string, payload binary",
    )


def resolved(records: DataFrame) -> DataFrame:
    """The records with `refers_to`, the page that a revisit's record refers to."""
    slim = records.drop("payload")
    responses = slim.where("record_type = 'response'").select(F.col("record_id").alias("refers_to_record"), F.col("page_id").alias("refers_to")).distinct()
    return slim.join(responses, "refers_to_record", "left")
