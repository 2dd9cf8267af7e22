"""WARC archives of individually compressed records that share an embedded Zstandard dictionary.

Each archive starts with a skippable frame that holds a dictionary trained on
a bounded sample of the records; every record is a frame of its own. Equal
payloads are stored once: the page with the smallest id is the response, the
others are revisits that refer to it. Archives lie in shared storage; a task
writes under a name of its own attempt, and only what it reports as finished
is read, so lost or repeated tasks leave no wrong record.

Defined results: null html is an empty payload, which is also stored once;
repeated rows of a response's id are responses again; a null page_id never is
referred to, unless there is no other; null URLs have no target line; an empty
table gives an empty archive set; other columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import struct
from urllib.parse import quote

import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import binary_list, fresh_path, materialize, salted_join

#: Fixed by the archive and compression formats.
DICTIONARY_FRAME, DICTIONARY_MAGIC = 0x184D2A5D, 0xEC30A437
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "2020-01-01T00:00:00Z"
MANIFEST = "path string, records long, bytes long"
#: So many hashes of repeated payloads (40 bytes each) are told to all tasks, and no page moves; beyond, pages meet them by exchange, a common payload split over tasks.
TOLD = 200_000
RECORD = "page_id long, url string, record_type string, refers_to long, payload_bytes long, payload_digest string, payload binary"


def file_system(path: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(path) if ":" in path.split("/")[0] else (fs.LocalFileSystem(), path)


def digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None) -> bytes:
    """One WARC record; its block is an HTTP response, without the body in a revisit."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if refers_to is not None else http + payload
    lines = ["WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: <urn:page:{'' if page_id is None else page_id}>", f"WARC-Date: {DATE}"]
    if url is not None:
        lines.append(f"WARC-Target-URI: {quote(url, safe=''.join(map(chr, range(33, 127))))}")
    lines.append(f"WARC-Payload-Digest: sha1:{digest(payload)}")
    if refers_to is not None:
        lines += [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: <urn:page:{refers_to}>"]
    lines += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def parse(raw: bytes) -> tuple:
    """A RECORD row of one record."""
    head, _, rest = raw.partition(b"\r\n\r\n")
    fields = dict(line.split(": ", 1) for line in head.decode().split("\r\n")[1:])
    block = rest[: int(fields["Content-Length"])]
    http, _, payload = block.partition(b"\r\n\r\n")
    size = next(int(line.split(b":")[1]) for line in http.split(b"\r\n") if line.lower().startswith(b"content-length"))
    own = fields["WARC-Record-ID"][10:-1]
    refers = fields.get("WARC-Refers-To")
    return (int(own) if own else None, fields.get("WARC-Target-URI"), fields["WARC-Type"], int(refers[10:-1]) if refers else None, size, fields["WARC-Payload-Digest"].removeprefix("sha1:"), None if refers else payload)


def train_dictionary(samples: list[bytes], size: int = 64 << 10) -> bytes:
    """A dictionary of the samples; empty where they are too few to train on."""
    try:
        return zstandard.train_dictionary(size, samples).as_bytes() if len(samples) >= 8 else b""
    except zstandard.ZstdError:
        return b""


def leading_frame(dictionary: bytes) -> bytes:
    packed = zstandard.ZstdCompressor(level=19).compress(dictionary)
    return struct.pack("<II", DICTIONARY_FRAME, len(packed)) + packed if dictionary else b""


def read_archive(stream, piece: int = 1 << 16):
    """The records of an open archive one by one; memory holds one record."""
    data = stream.read(8)
    options = {}
    if len(data) == 8 and struct.unpack("<I", data[:4])[0] == DICTIONARY_FRAME:
        raw = stream.read(struct.unpack("<I", data[4:])[0])
        if struct.unpack("<I", raw[:4])[0] != DICTIONARY_MAGIC:
            raw = zstandard.ZstdDecompressor().decompress(raw)
        options, data = {"dict_data": zstandard.ZstdCompressionDict(raw)}, b""
    codec = zstandard.ZstdDecompressor(**options)
    while data or (data := stream.read(piece)):
        frame, parts = codec.decompressobj(), []
        while True:
            parts.append(frame.decompress(data))
            data = frame.unused_data
            if frame.eof:
                break
            if not (data := stream.read(piece)):
                raise EOFError("the archive ends within a record")
        yield b"".join(parts)


def write_archives(pages: DataFrame, path: str | None = None, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", least_bytes: int = 0, sample_records: int = 1_000, sample_bytes: int = 20_000, level: int = 3, roll_bytes: int = 256 << 20) -> DataFrame:
    """Write the archives and return their manifest (path, records, bytes).

    The dictionary is trained on about sample_records pages, of each at most
    sample_bytes. A file is closed beyond roll_bytes.
    """
    spark = pages.sparkSession
    path = path or fresh_path(spark, "warc")
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).alias("url"), F.coalesce(F.col(html_col), F.lit("")).alias("html"))
    keyed = rows.withColumn("sha", F.sha1(F.col("html").cast("binary")))
    stored_once = keyed.select("page_id", "sha", F.octet_length("html").alias("size")).where(F.col("size") >= least_bytes)
    shared = materialize(stored_once.groupBy("sha").agg(F.min("page_id").alias("first"), F.count("*").alias("__copies")).where("__copies > 1").drop("__copies"), "payloads")  # hashes only
    n_shared = shared.count()
    if n_shared <= TOLD:
        joined = keyed.join(F.broadcast(shared), "sha", "left")
    else:
        known = salted_join(keyed, shared, "sha", "page_id", keyed.count())
        joined = keyed.join(shared, "sha", "left_anti").withColumn("first", F.lit(None).cast("long")).unionByName(known)
    own = F.col("page_id").isNull() | (F.col("first") != F.col("page_id"))
    joined = joined.select("page_id", "url", "html", F.when(own, F.col("first")).alias("refers_to"))
    total = max(1, rows.count())
    drawn = rows.where(F.pmod(F.xxhash64("page_id", "url"), F.lit(total)) < sample_records).select("page_id", "url", F.substring("html", 1, sample_bytes).alias("html")).limit(2 * sample_records).collect()
    held = spark.sparkContext.broadcast(train_dictionary([record(r["page_id"], r["url"], r["html"].encode(), None) for r in drawn]))
    file_system(path)[0].create_dir(file_system(path)[1], recursive=True)

    def run(batches):
        shared, folder = file_system(path)
        task = TaskContext.get()
        dictionary = held.value
        options = {"dict_data": zstandard.ZstdCompressionDict(dictionary)} if dictionary else {}
        codec = zstandard.ZstdCompressor(level=level, **options)
        out = name = None
        files = records = 0
        for b in batches:
            for page_id, url, html, refers_to in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), binary_list(b.column(2)), b.column(3).to_pylist()):
                if out is None:
                    name, files, records = f"part-{task.partitionId():06d}-{task.taskAttemptId()}-{files}.warc.zst", files + 1, 0
                    out = shared.open_output_stream(f"{folder}/{name}", compression=None)
                    out.write(leading_frame(dictionary))
                out.write(codec.compress(record(page_id, url, html, refers_to)))
                records += 1
                if out.tell() > roll_bytes:
                    yield _closed(out, path, name, records)
                    out = None
        if out is not None:
            yield _closed(out, path, name, records)

    manifest = joined.mapInArrow(run, MANIFEST)
    manifest.write.parquet(f"{path}/manifest")
    return spark.read.schema(MANIFEST).parquet(f"{path}/manifest")


def _closed(out, path: str, name: str, records: int) -> pa.RecordBatch:
    size = out.tell()
    out.close()
    return pa.RecordBatch.from_arrays([pa.array([f"{path}/{name}"]), pa.array([records], pa.int64()), pa.array([size], pa.int64())], ["path", "records", "bytes"])


def read_archives(manifest: DataFrame, payloads: bool = False) -> DataFrame:
    """RECORD rows of the archives that a manifest lists; a revisit's payload stands with its response. Digests of stored payloads are checked."""

    def run(batches):
        names = [c.split()[0] for c in RECORD.split(", ")]
        kinds = [pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.binary()]
        for b in batches:
            for uri in b.column(0).to_pylist():
                shared, place = file_system(uri)
                with shared.open_input_stream(place, compression=None) as stream:
                    held, size = [], 0
                    for raw in read_archive(stream):
                        row = parse(raw)
                        if row[6] is not None and (len(row[6]) != row[4] or digest(row[6]) != row[5]):
                            raise ValueError(f"{uri}: the payload of page {row[0]} is damaged")
                        held.append(row if payloads else (*row[:6], None))
                        size += len(raw)
                        if size > 8 << 20 or len(held) >= 5_000:
                            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*held), kinds)], names)
                            held, size = [], 0
                    if held:
                        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*held), kinds)], names)

    return manifest.repartition(max(1, min(manifest.count(), 10_000)), "path").mapInArrow(run, RECORD)
