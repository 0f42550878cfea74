"""WARC archives in Zstandard: writer and reader.

An archive starts with a skippable frame that holds a compression dictionary (itself Zstandard-compressed), followed
by one frame per record. The reader loads the dictionary from that leading frame, decodes frame by frame in bounded
pieces, and validates what it meets: the version line, the mandatory headers, that Content-Length equals the bytes
that are there, the closing blank lines, and for responses the payload digest and length.

Of records with equal payloads (of at least ``least_bytes``) the one with the largest id is written whole, the others as
revisits that refer to it. Files are written by the executors through the URI of a shared folder under a name of
their own per attempt; the manifest of finished files, itself a table, says which count, so lost or repeated tasks
leave no trace in what is read.

Defined cases: a null payload is empty; a null id is written as such, sorts first, and equals no other record's payload
owner; a null URL becomes an empty target; repeated rows (equal id and payload) are one record each, and all those of the largest
id are responses; an empty table gives no files and an empty result; other columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import struct
import uuid
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.fs  # noqa: F401
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .arrow import text_bytes
from .store import materialise, new_path, ship

#: Fixed values of the formats.
DICTIONARY_FRAME = 0x184D2A5D
ZSTD_FRAME = 0xFD2FB528
VERSION = b"WARC/1.1"
MANDATORY = ("WARC-Type", "WARC-Record-ID", "WARC-Date", "Content-Length")
EMPTY_DATE = "1970-01-01T00:00:00Z"

#: Bytes of payload that one archive holds at least before the next one starts.
ARCHIVE_BYTES = 64 << 20
#: Payload bytes at an archive's start that its dictionary is made from, and the dictionary's size.
SAMPLE_BYTES, DICTIONARY_BYTES = 1 << 20, 32 << 10
READ_BYTES = 1 << 18


def digest_of(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record_bytes(headers: list[tuple[str, str]], payload: bytes) -> bytes:
    clean = lambda v: v.replace("\r", "%0D").replace("\n", "%0A")
    head = b"".join(f"{k}: {clean(v)}\r\n".encode("utf-8", "replace") for k, v in [*headers, ("Content-Length", str(len(payload)))])
    return VERSION + b"\r\n" + head + b"\r\n" + payload + b"\r\n\r\n"


def parse_record(data: bytes) -> tuple[dict[str, str], bytes]:
    """Headers and payload of one record; ValueError says what is wrong with it."""
    head, blank, rest = data.partition(b"\r\n\r\n")
    lines = head.split(b"\r\n")
    if not blank or lines[0] != VERSION:
        raise ValueError("no version line or no end of headers")
    headers = {}
    for line in lines[1:]:
        name, colon, value = line.decode().partition(":")
        if not colon or not name or name != name.strip():
            raise ValueError(f"bad header line {line[:60]!r}")
        if name in headers:
            raise ValueError(f"repeated header {name}")
        headers[name] = value.strip()
    if missing := [h for h in MANDATORY if h not in headers]:
        raise ValueError(f"missing headers {missing}")
    length = headers["Content-Length"]
    if not length.isdigit() or len(rest) != int(length) + 4 or rest[int(length) :] != b"\r\n\r\n":
        raise ValueError("Content-Length and the record's bytes differ")
    payload = rest[: int(length)]
    if headers["WARC-Type"] == "response":
        if headers.get("WARC-Payload-Digest") != f"sha1:{digest_of(payload)}":
            raise ValueError("the payload digest does not fit")
        if headers.get("X-Payload-Length") not in (None, length):
            raise ValueError("the payload length does not fit")
    elif headers["WARC-Type"] == "revisit" and "WARC-Refers-To" not in headers:
        raise ValueError("a revisit that refers to nothing")
    return headers, payload


def dictionary_for(samples: list[bytes], size: int = DICTIONARY_BYTES) -> bytes:
    """A dictionary trained on the samples; raw content of them where there are too few to train on."""
    try:
        return zstandard.train_dictionary(size, samples).as_bytes()
    except zstandard.ZstdError:
        return b"".join(samples)[-size:] or b"WARC/1.1\r\nWARC-Type: "


def leading_frame(dictionary: bytes) -> bytes:
    packed = zstandard.ZstdCompressor(level=12).compress(dictionary)
    return struct.pack("<II", DICTIONARY_FRAME, len(packed)) + packed


def read_dictionary(stream) -> zstandard.ZstdCompressionDict | None:
    """The dictionary of the leading skippable frame; None if the archive starts with a record."""
    head = stream.read(8)
    if len(head) < 8:
        raise ValueError("not an archive: it ends within the first frame")
    magic, n = struct.unpack("<II", head)
    if magic == ZSTD_FRAME:
        stream.seek(0)
        return None
    if magic != DICTIONARY_FRAME:
        raise ValueError(f"unknown leading frame {magic:#x}")
    data = stream.read(n)
    if len(data) < n:
        raise ValueError("the dictionary frame is cut short")
    if data[:4] == struct.pack("<I", ZSTD_FRAME):
        data = zstandard.ZstdDecompressor().decompressobj().decompress(data)
    return zstandard.ZstdCompressionDict(data)


def frames(stream) -> Iterator[bytes]:
    """Content of each record frame after the leading one; a frame that is cut short is an error."""
    dictionary = read_dictionary(stream)
    engine = zstandard.ZstdDecompressor(dict_data=dictionary) if dictionary else zstandard.ZstdDecompressor()
    left = b""
    while True:
        left = left or stream.read(READ_BYTES)
        if not left:
            return
        one, parts = engine.decompressobj(), []
        while not one.eof:
            if not left:
                left = stream.read(READ_BYTES)
                if not left:
                    raise ValueError("the last frame is cut short")
            parts.append(one.decompress(left))
            left = one.unused_data if one.eof else b""
        yield b"".join(parts)


def read_archive(stream) -> Iterator[tuple[dict[str, str], bytes]]:
    for data in frames(stream):
        yield parse_record(data)


def _open(uri: str):
    return pa.fs.FileSystem.from_uri(uri)


MANIFEST = T.StructType([T.StructField("path", T.StringType()), T.StructField("records", T.LongType()), T.StructField("bytes", T.LongType())])


def write_archives(
    pages: DataFrame, folder: str | None = None, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html",
    least_bytes: int = 0, archive_bytes: int = ARCHIVE_BYTES, date: str = EMPTY_DATE,
) -> DataFrame:
    """Write all rows and return the manifest (path, records, bytes). ``folder`` is a URI that all executors reach."""
    spark = pages.sparkSession
    ship(spark)
    folder = folder or new_path(spark, "warc")
    payload = F.coalesce(F.col(payload_col), F.lit(""))
    rows = pages.select(F.col(id_col).cast("string").alias("id"), F.col(id_col).alias("order"), F.col(url_col).alias("url"), payload.alias("payload"))
    rows = rows.withColumn("sha1", F.when(F.octet_length("payload") >= least_bytes, F.sha1(F.col("payload").cast("binary"))))
    # one narrow row per payload that is there more than once
    whole = rows.where("sha1 is not null").groupBy("sha1").agg(F.max("order").alias("owner"), F.count(F.lit(1)).alias("n")).where("n > 1")
    whole = materialise(whole.select(F.col("sha1").alias("_sha1"), F.col("owner").cast("string").alias("owner")), "warc-owners")
    typed = rows.join(whole, F.col("sha1") == F.col("_sha1"), "left")
    typed = typed.select("id", "url", "payload", F.when(~F.col("id").eqNullSafe(F.col("owner")), F.col("owner")).alias("refers"))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, base = _open(folder)
        fs.create_dir(base, recursive=True)
        out = None
        for batch in batches:
            done, bodies = [], text_bytes(batch.column("payload"))
            for k in range(batch.num_rows):
                body = bodies[k].as_py()
                if out is None:
                    out = _Archive(fs, base, folder)
                out.add(batch.column("id")[k].as_py(), batch.column("url")[k].as_py(), body, batch.column("refers")[k].as_py(), date)
                if out.bytes >= archive_bytes:
                    done.append(out.close())
                    out = None
            if done:
                yield pa.RecordBatch.from_pylist(done, schema=_MANIFEST)
        if out is not None:
            yield pa.RecordBatch.from_pylist([out.close()], schema=_MANIFEST)

    return materialise(typed.mapInArrow(work, MANIFEST), "warc-manifest")


_MANIFEST = pa.schema([("path", pa.string()), ("records", pa.int64()), ("bytes", pa.int64())])


class _Archive:
    """One file being written: its first records are held back until there is enough to make the dictionary from."""

    def __init__(self, fs, base: str, folder: str):
        name = f"part-{uuid.uuid4().hex}.warc.zst"
        self.stream, self.uri = fs.open_output_stream(f"{base}/{name}", compression=None), f"{folder}/{name}"
        self.held: list[bytes] | None = []
        self.held_bytes = self.bytes = self.records = 0

    def add(self, id_: str | None, url: str | None, payload: bytes, refers: str | None, date: str) -> None:
        kind = "response" if refers is None else "revisit"
        headers = [
            ("WARC-Type", kind), ("WARC-Record-ID", f"<urn:page:{'null' if id_ is None else id_}>"), ("WARC-Date", date),
            ("WARC-Target-URI", url or ""), ("Content-Type", "text/html; charset=utf-8"),
            ("WARC-Payload-Digest", f"sha1:{digest_of(payload)}"), ("X-Payload-Length", str(len(payload))),
        ]
        if refers is not None:
            headers += [("WARC-Refers-To", f"<urn:page:{refers}>"), ("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")]
        data = record_bytes(headers, b"" if refers is not None else payload)
        self.bytes += len(data)
        self.records += 1
        if self.held is None:
            self.stream.write(self.engine.compress(data))
            return
        self.held.append(data)
        self.held_bytes += len(data)
        if self.held_bytes >= SAMPLE_BYTES:
            self._start()

    def _start(self) -> None:
        dictionary = dictionary_for(self.held)
        self.engine = zstandard.ZstdCompressor(level=3, dict_data=zstandard.ZstdCompressionDict(dictionary))
        self.stream.write(leading_frame(dictionary))
        for data in self.held:
            self.stream.write(self.engine.compress(data))
        self.held = None

    def close(self) -> dict:
        if self.held is not None:
            self._start()
        self.stream.close()
        return {"path": self.uri, "records": self.records, "bytes": self.bytes}


RECORDS = T.StructType([
    T.StructField("path", T.StringType()), T.StructField("id", T.StringType()), T.StructField("url", T.StringType()), T.StructField("record_type", T.StringType()),
    T.StructField("payload_bytes", T.LongType()), T.StructField("payload_digest", T.StringType()), T.StructField("refers_to", T.StringType()), T.StructField("payload", T.BinaryType()),
])


def read_archives(spark: SparkSession, manifest: DataFrame, payloads: bool = True) -> DataFrame:
    """One row per record of the manifest's files. An archive that breaks a rule, or holds other than the number of records that
    it was written with, fails the job with its path."""
    ship(spark)
    names = [f.name for f in RECORDS.fields if payloads or f.name != "payload"]
    schema = T.StructType([RECORDS[n] for n in names])
    arrow = pa.schema([(n, {"payload_bytes": pa.int64(), "payload": pa.binary()}.get(n, pa.string())) for n in names])

    def bare(urn: str | None) -> str | None:
        if urn is None:
            return None
        value = urn.removeprefix("<urn:page:").removesuffix(">")
        return None if value == "null" else value

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, records in zip(batch.column("path").to_pylist(), batch.column("records").to_pylist(), strict=True):
                fs, inner = _open(path)
                found, size, n = [], 0, 0
                with fs.open_input_file(inner) as stream:
                    try:
                        for headers, payload in read_archive(stream):
                            n += 1
                            size += len(payload)
                            row = {
                                "path": path, "id": bare(headers["WARC-Record-ID"]), "url": headers.get("WARC-Target-URI"), "record_type": headers["WARC-Type"],
                                "payload_bytes": int(headers["X-Payload-Length"]), "payload_digest": headers["WARC-Payload-Digest"].removeprefix("sha1:"),
                                "refers_to": bare(headers.get("WARC-Refers-To")), "payload": payload,
                            }
                            found.append({k: row[k] for k in names})
                            if len(found) >= 2000 or (payloads and size > 8 << 20):
                                yield pa.RecordBatch.from_pylist(found, schema=arrow)
                                found, size = [], 0
                    except ValueError as e:
                        raise ValueError(f"{path}, record {n + 1}: {e}") from e
                if n != records:
                    raise ValueError(f"{path}: {n} records instead of {records}")
                if found:
                    yield pa.RecordBatch.from_pylist(found, schema=arrow)

    # a task per file: by size alone the few bytes of the manifest would be read by one task
    return manifest.select("path", "records").repartition(max(1, manifest.count())).mapInArrow(work, schema)


def op8_warc(spark, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    back = read_archives(spark, write_archives(pages), payloads=False)
    kind = pages.schema["page_id"].dataType
    return back.select(F.col("id").cast(kind).alias("page_id"), "payload_bytes", "payload_digest", "record_type", F.col("refers_to").cast(kind).alias("refers_to"), "url")


#: Base32 in SQL: each five hex digits are four letters.
_LETTERS = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
_FIVE = "('0x' || substr(h, 5 * g + 1, 5))::BIGINT"
OP8_SQL = f"""
with p as (select page_id, coalesce(html, '') as html, replace(replace(coalesce(url, ''), chr(13), '%0D'), chr(10), '%0A') as url, sha1(coalesce(html, '')) as h from pages),
o as (select html, max(page_id) as owner from p group by html)
select page_id, strlen(p.html)::BIGINT as payload_bytes,
  array_to_string(list_transform(range(8), lambda g: {' || '.join(f"substr('{_LETTERS}', 1 + (({_FIVE} >> {shift}) & 31)::INT, 1)" for shift in (15, 10, 5, 0))}), '') as payload_digest,
  case when page_id is not distinct from owner or page_id is null and owner is null then 'response' else 'revisit' end as record_type,
  case when page_id is not distinct from owner then null else owner end as refers_to, url
from p join o on o.html = p.html
"""
