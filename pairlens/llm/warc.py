"""WARC archives as a Python data source: partitions from file sizes, header predicates before any payload is decoded.

Each record is a gzip member of its own whose extra field "sl" holds its compressed and plain length, so a reader
jumps over a record that it doesn't want. Members without that field, and plain .warc files, can be read too.
"""

from __future__ import annotations

import struct
import uuid
import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, EqualTo, Filter, In, InputPartition, WriterCommitMessage

FORMAT = "pairlens_warc"
SCHEMA = "record_type string, record_id string, target_uri string, date string, refers_to string, payload_digest string, payload_length bigint, content_length bigint, payload binary"
#: Columns and the header fields (lower-cased names) that hold them: fixed values of the WARC format, and one extension field.
FIELDS = {"record_type": "warc-type", "record_id": "warc-record-id", "target_uri": "warc-target-uri", "date": "warc-date", "refers_to": "warc-refers-to", "payload_digest": "warc-payload-digest", "payload_length": "x-payload-length"}
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
BATCH_BYTES, PARTITION_BYTES, HEAD_BYTES = 4 << 20, 64 << 20, 4096


def member(data: bytes, level: int = 1) -> bytes:
    """A gzip member with an extra field of its own length."""
    deflate = zlib.compressobj(level, zlib.DEFLATED, -15)
    body = deflate.compress(data) + deflate.flush()
    size = 12 + 12 + len(body) + 8
    extra = b"sl" + struct.pack("<HII", 8, size & 0xFFFFFFFF, len(data) & 0xFFFFFFFF)
    return b"\x1f\x8b\x08\x04" + bytes(5) + b"\xff" + struct.pack("<H", len(extra)) + extra + body + struct.pack("<II", zlib.crc32(data), len(data) & 0xFFFFFFFF)


def record(fields: list[tuple[str, str | None]], block: bytes) -> bytes:
    """A record in plain form; fields without a value are left out, line ends inside a value are percent-encoded."""
    lines = ["WARC/1.1", *(f"{k}: {v.replace(chr(13), '%0D').replace(chr(10), '%0A')}" for k, v in fields if v is not None), f"Content-Length: {len(block)}"]
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def page_record(row) -> bytes:
    payload = bytes(row["payload"] or b"")
    head = [("WARC-Type", row["record_type"]), ("WARC-Record-ID", row["record_id"]), ("WARC-Date", row["date"]), ("WARC-Target-URI", row["target_uri"]), ("WARC-Refers-To", row["refers_to"]), ("WARC-Payload-Digest", row["payload_digest"]), ("X-Payload-Length", None if row["payload_length"] is None else str(row["payload_length"]))]
    if row["record_type"] == "revisit":
        return record([*head, ("WARC-Profile", PROFILE)], b"")
    if row["record_type"] != "response":
        return record(head, payload)
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    return record([*head, ("Content-Type", "application/http; msgtype=response")], http + payload)


@dataclass
class Files(InputPartition):
    paths: list[str] = field(default_factory=list)


@dataclass
class Written(WriterCommitMessage):
    made: list[tuple[str, str]]


def parse_head(head: bytes) -> dict[str, str]:
    out, last = {}, None
    for line in head.decode("utf-8", "replace").split("\r\n")[1:]:
        if line[:1] in (" ", "\t") and last:
            out[last] += " " + line.strip()
        elif ":" in line:
            k, v = line.split(":", 1)
            last = k.strip().lower()
            out[last] = v.strip()
    return out


def records(stream, wanted) -> Iterator[tuple[dict[str, str], bytes]]:
    """(header fields, block) of the wanted records: wanted(fields) is asked before anything past the header is decoded."""
    pos, size = 0, stream.size()
    while pos < size:
        stream.seek(pos)
        start = stream.read(min(HEAD_BYTES, size - pos))
        if start[:2] != b"\x1f\x8b":  # plain: the header tells where the next record begins
            while b"\r\n\r\n" not in start:
                more = stream.read(HEAD_BYTES)
                if not more:
                    if start.strip():
                        raise ValueError(f"a record at {pos} has no end of its header")
                    return
                start += more
            skip = len(start) - len(start.lstrip(b"\r\n"))
            head = start[skip:].split(b"\r\n\r\n", 1)[0]
            fields = parse_head(head)
            begin, n = pos + skip + len(head) + 4, int(fields.get("content-length", 0))
            if wanted(fields):
                stream.seek(begin)
                yield fields, stream.read(n)
            pos = begin + n + 4
            continue
        long = 0
        if start[3] & 4 and start[12:14] == b"sl":
            long = struct.unpack("<I", start[16:20])[0]
        inflate = zlib.decompressobj(31)
        plain = inflate.decompress(start, HEAD_BYTES)
        while b"\r\n\r\n" not in plain and not inflate.eof:
            more = inflate.unconsumed_tail or stream.read(HEAD_BYTES)
            if not more:
                raise ValueError(f"the record at {pos} is cut off")
            plain += inflate.decompress(more, HEAD_BYTES)
        head = plain.split(b"\r\n\r\n", 1)[0]
        fields = parse_head(head)
        if wanted(fields) or not long:
            parts = [plain]
            while not inflate.eof:
                more = inflate.unconsumed_tail or stream.read(1 << 16)
                if not more:
                    raise ValueError(f"the record at {pos} is cut off")
                parts.append(inflate.decompress(more))
            whole, begin = b"".join(parts), len(head) + 4
            if wanted(fields):
                yield fields, whole[begin : begin + int(fields.get("content-length", 0))]
            long = long or stream.tell() - len(inflate.unused_data) - pos
        pos += long


class WarcReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.options = options["path"], options
        self.equal: dict[str, list] = {}

    def pushFilters(self, filters: list[Filter]) -> Iterable[Filter]:
        for f in filters:
            name = f.attribute[0] if isinstance(f, (EqualTo, In)) and len(f.attribute) == 1 else None
            if name in FIELDS and name != "payload_length":
                among = [f.value] if isinstance(f, EqualTo) else list(f.value)
                self.equal[name] = [v for v in self.equal.get(name, among) if v in among]
            else:
                yield f

    def partitions(self) -> list[Files]:
        store, path = fs.FileSystem.from_uri(self.path)
        files = sorted((f for f in store.get_file_info(fs.FileSelector(path, recursive=True)) if f.is_file and not f.base_name.startswith(("_", ".")) and ".warc" in f.base_name), key=lambda f: f.path)
        out, room = [], 0
        for f in files:
            if not out or f.size > room:
                out.append(Files())
                room = int(self.options.get("partitionbytes", PARTITION_BYTES))
            out[-1].paths.append(f.path)
            room -= f.size
        return out or [Files()]

    def read(self, partition: Files) -> Iterator[pa.RecordBatch]:
        store, _ = fs.FileSystem.from_uri(self.path)
        bare = self.options.get("payload", "true").lower() == "false"
        names = ["record_type", "record_id", "target_uri", "date", "refers_to", "payload_digest"]
        schema = pa.schema([*((n, pa.string()) for n in names), ("payload_length", pa.int64()), ("content_length", pa.int64()), ("payload", pa.binary())])
        passes = lambda h: all(h.get(FIELDS[k]) in v for k, v in self.equal.items())
        rows, size = [], 0
        for path in partition.paths:
            with store.open_input_file(path) as stream:
                found: Iterator = ((h, b) for h, b in records(stream, passes)) if not bare else heads(stream, passes)
                for h, block in found:
                    if block is not None and h.get("content-type", "").startswith("application/http"):
                        block = block.split(b"\r\n\r\n", 1)[-1]
                    length = h.get("x-payload-length")
                    rows.append([*(h.get(FIELDS[n]) for n in names), int(length) if length else None, int(h.get("content-length", 0)), block])
                    size += len(block or b"") + 200
                    if size >= BATCH_BYTES:
                        yield pa.RecordBatch.from_pylist([dict(zip(schema.names, r, strict=True)) for r in rows], schema=schema)
                        rows, size = [], 0
        if rows:
            yield pa.RecordBatch.from_pylist([dict(zip(schema.names, r, strict=True)) for r in rows], schema=schema)


def heads(stream, passes) -> Iterator[tuple[dict[str, str], None]]:
    """Headers alone: no payload is decoded."""
    found: list = []
    for _ in records(stream, lambda h: bool(passes(h) and found.append(h))):
        pass
    yield from ((h, None) for h in found)


class WarcWriter(DataSourceWriter):
    def __init__(self, options: dict, overwrite: bool):
        self.path, self.overwrite = options["path"], overwrite

    def write(self, iterator: Iterator) -> Written:
        store, path = fs.FileSystem.from_uri(self.path)
        store.create_dir(path, recursive=True)
        name = uuid.uuid4().hex
        with store.open_output_stream(f"{path}/_part-{name}", compression=None) as out:
            for row in iterator:
                out.write(member(page_record(row)))
        return Written([(f"{path}/_part-{name}", f"{path}/part-{name}.warc.gz")])

    def commit(self, messages: list[Written | None]) -> None:
        store, path = fs.FileSystem.from_uri(self.path)
        if self.overwrite:
            for f in store.get_file_info(fs.FileSelector(path, allow_not_found=True)):
                if f.is_file and not f.base_name.startswith("_"):
                    store.delete_file(f.path)
        for m in messages:
            for a, b in m.made if m else []:
                store.move(a, b)

    def abort(self, messages: list[Written | None]) -> None:
        store, _ = fs.FileSystem.from_uri(self.path)
        for m in messages:
            for a, _ in m.made if m else []:
                store.delete_file(a)


class WarcSource(DataSource):
    """spark.read.format("pairlens_warc").load(folder): option payload=false reads headers only."""

    @classmethod
    def name(cls) -> str:
        return FORMAT

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> WarcReader:
        return WarcReader({k.lower(): v for k, v in self.options.items()})

    def writer(self, schema, overwrite: bool) -> WarcWriter:
        return WarcWriter({k.lower(): v for k, v in self.options.items()}, overwrite)


def register(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(WarcSource)


def page_records(pages: DataFrame, key: str = "page_id", url: str = "url", html: str = "html", least: int = 100) -> DataFrame:
    """Rows in the source's schema, a response for each page or a revisit of the page with the smallest key whose
    payload (html in UTF-8; null: empty) is equal and has least bytes or more. Of repeated rows with that key each is
    a response. Equal payloads meet by digest: counted before the shuffle, and joined back only where they repeat."""
    plain = pages.select(F.col(key).alias("key"), F.col(url).alias("target_uri"), F.coalesce(F.col(html).cast("binary"), F.lit(b"")).alias("payload"))
    plain = plain.select("*", F.sha2("payload", 256).alias("digest"), F.octet_length("payload").cast("bigint").alias("payload_length"))
    groups = plain.where(F.col("payload_length") >= least).groupBy("digest").agg(F.min("key").alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1").select("digest", "first")
    both = plain.join(groups, "digest", "left")
    again = F.col("first").isNotNull() & (F.col("key") != F.col("first"))
    name = lambda c: F.concat(F.lit("<urn:page:"), c.cast("string"), F.lit(">"))
    return both.select(
        F.when(again, F.lit("revisit")).otherwise(F.lit("response")).alias("record_type"), name(F.col("key")).alias("record_id"), "target_uri", F.lit("2024-01-01T00:00:00Z").alias("date"),
        F.when(again, name(F.col("first"))).alias("refers_to"), F.concat(F.lit("sha256:"), "digest").alias("payload_digest"), "payload_length", F.lit(0).cast("bigint").alias("content_length"), F.when(~again, F.col("payload")).alias("payload"),
    )


def write_pages(pages: DataFrame, path: str, **names) -> None:
    register(pages.sparkSession)
    page_records(pages, **names).write.format(FORMAT).mode("append").save(path)


def read_pages(spark: SparkSession, path: str) -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type, refers_to of archived pages; length and digest of a response are taken anew from what was read."""
    register(spark)
    number = lambda c: F.regexp_extract(c, r"(-?\d+)>$", 1)
    got, here = spark.read.format(FORMAT).load(path), F.col("record_type") == "response"
    return got.where(F.col("record_type").isin("response", "revisit")).select(
        number("record_id").cast("bigint").alias("page_id"),
        F.when(here, F.octet_length("payload").cast("bigint")).otherwise(F.col("payload_length")).alias("payload_bytes"),
        F.when(here, F.sha2("payload", 256)).otherwise(F.substring_index("payload_digest", ":", -1)).alias("payload_digest"),
        "record_type", F.when(~here, number("refers_to").cast("bigint")).alias("refers_to"),
    )
