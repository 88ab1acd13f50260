"""Dictionary-compressed web archives.

An archive is a Zstandard file: a leading skippable frame (magic number 0x184D2A5D)
holds a dictionary built from a sample of the archived records; every record is a
frame of its own, compressed with that dictionary. An empty skippable frame stands
between records, where Spark's text writer wants a line end: so archives
are written and committed by Spark to any store it knows.

Records with equal payloads: the one with the largest id is the ``response``, all
others are ``revisit`` records without payload that name it. The dictionary comes from
at most ``sample`` pages, those with the least hash of their id, ``sample_part`` bytes
of each; it never decides what is stored.

Edge cases: a null payload is empty; equal empty payloads are revisits like others
if ``min_bytes`` is 0; rows that repeat the response's id and payload are responses
too; a null id is written as such, loses to any other and, when all are null, none
is a revisit; an empty table writes archives without records. Other columns are not read.
"""

from __future__ import annotations

import base64
import hashlib
import struct
from collections.abc import Iterator

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .arrow import texts
from .scratch import new_path

#: Fixed values of the format.
DICTIONARY_FRAME = 0x184D2A5D
SKIPPABLE = range(0x184D2A50, 0x184D2A60)
ZSTD_FRAME = 0xFD2FB528
BETWEEN = "P*M\u0018\u0000\u0000\u0000\u0000"
LEVEL = 3


def base32_sha1(body: bytes) -> str:
    return base64.b32encode(hashlib.sha1(body).digest()).decode()


def record(page: int | None, url: str | None, body: bytes, refers_to: int | None, revisit: bool) -> bytes:
    """One record: its WARC head and an HTTP answer; a revisit keeps the answer's head only."""
    answer = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(body)}\r\n\r\n".encode()
    block = answer if revisit else answer + body
    head = ["WARC/1.1", f"WARC-Type: {'revisit' if revisit else 'response'}", f"WARC-Record-ID: <urn:page:{'' if page is None else page}>"]
    if url is not None:
        head.append("WARC-Target-URI: " + url.replace("\r", "%0D").replace("\n", "%0A"))
    if revisit:
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: <urn:page:{refers_to}>"]
    head += ["WARC-Date: 1970-01-01T00:00:00Z", f"WARC-Payload-Digest: sha1:{base32_sha1(body)}", "Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def parse(data: bytes) -> dict:
    """The fields of a record; ``payload`` is None in a revisit. Lengths and digest are tested."""
    head, _, rest = data.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    fields = dict(line.split(": ", 1) for line in lines[1:])
    block = rest[: int(fields["Content-Length"])]
    if not lines[0].startswith("WARC/") or rest[len(block) :] != b"\r\n\r\n":
        raise ValueError("broken record")
    answer, _, payload = block.partition(b"\r\n\r\n")
    size = int(answer.decode().rsplit("Content-Length: ", 1)[1])
    revisit = fields["WARC-Type"] == "revisit"
    digest = fields["WARC-Payload-Digest"].removeprefix("sha1:")
    if not revisit and (len(payload) != size or base32_sha1(payload) != digest):
        raise ValueError("the payload is not what its record says")
    number = lambda x: int(x.removeprefix("<urn:page:").removesuffix(">") or 0) if x and x != "<urn:page:>" else None
    return {"page": number(fields["WARC-Record-ID"]), "bytes": size, "digest": digest, "type": fields["WARC-Type"], "refers_to": number(fields.get("WARC-Refers-To")), "url": fields.get("WARC-Target-URI"), "payload": None if revisit else payload}


def frames(data: memoryview) -> Iterator[tuple[int, memoryview]]:
    """Magic number and bytes of each frame (of a skippable one its content), found from the block heads alone."""
    at = 0
    while at < len(data):
        (magic,) = struct.unpack_from("<I", data, at)
        if magic in SKIPPABLE:
            (size,) = struct.unpack_from("<I", data, at + 4)
            yield magic, data[at + 8 : at + 8 + size]
            at += 8 + size
            continue
        if magic != ZSTD_FRAME:
            raise ValueError("no Zstandard frame where one must begin")
        end = at + zstandard.frame_header_size(data[at : at + 18])
        checked = data[at + 4] & 4
        last = 0
        while not last:
            b = int.from_bytes(data[end : end + 3], "little")
            last, kind, size = b & 1, b >> 1 & 3, b >> 3
            end += 3 + (1 if kind == 1 else size)
        end += 4 * bool(checked)
        yield magic, data[at:end]
        at = end


def build_dictionary(pages: DataFrame, *, id_col: str = "page_id", url_col: str = "url", body_col: str = "html", sample: int = 256, sample_part: int = 16384, size: int = 64 << 10) -> bytes:
    """From the records of a bounded sample of the pages."""
    ids = pages.select(id_col).where(F.col(id_col).isNotNull()).orderBy(F.xxhash64(id_col), id_col).limit(sample)
    rows = pages.join(F.broadcast(ids.distinct()), id_col).select(id_col, url_col, F.substring(F.col(body_col).cast("binary"), 1, sample_part).alias("b")).limit(4 * sample).collect()
    records = sorted(record(p, u, bytes(b or b""), None, False) for p, u, b in rows)
    try:
        return zstandard.train_dictionary(size, records, level=LEVEL).as_bytes()
    except (zstandard.ZstdError, MemoryError):  # too few records to train on
        return b"".join(records)[:size] or b"WARC/1.1\r\n"


def _compressor(dictionary: bytes) -> zstandard.ZstdCompressor:
    kept = zstandard.ZstdCompressionDict(dictionary)
    kept.precompute_compress(level=LEVEL)
    return zstandard.ZstdCompressor(level=LEVEL, dict_data=kept, write_checksum=True)


def _pack(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        dictionary = shared.value
        squeeze = _compressor(dictionary)
        yield pa.RecordBatch.from_arrays([pa.array([struct.pack("<II", DICTIONARY_FRAME, len(dictionary)) + dictionary], pa.binary())], ["frame"])
        for batch in batches:
            for a in range(0, batch.num_rows, 128):
                part = batch.slice(a, 128)
                columns = (part.column("page").to_pylist(), part.column("url").to_pylist(), texts(part.column("body")), part.column("refers_to").to_pylist())
                out = [squeeze.compress(record(p, u, b, r, r is not None)) for p, u, b, r in zip(*columns, strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(out, pa.binary())], ["frame"])

    return run


def _unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    kinds = [pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.binary()]
    names = ["page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to", "payload"]
    for batch in batches:
        for i in range(batch.num_rows):
            data, opener, rows, held = memoryview(batch.column(0)[i].as_buffer()), None, [], 0
            for magic, body in frames(data):
                if magic == DICTIONARY_FRAME:
                    opener = zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(bytes(body)))
                elif magic == ZSTD_FRAME:
                    x = parse(opener.decompress(body))
                    rows.append((x["page"], x["url"], x["bytes"], x["digest"], x["type"], x["refers_to"], x["payload"]))
                    held += x["bytes"]
                    if held > 4 << 20:
                        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names)
                        rows, held = [], 0
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names)


def _listing(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in _unpack(batches):
        yield batch.select(["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"])


def revisits(pages: DataFrame, *, id_col: str = "page_id", body_col: str = "html", min_bytes: int = 0) -> DataFrame:
    """``page, digest, refers_to`` of the pages that are to be revisits. Bodies stay where they are: only digests move."""
    body = F.coalesce(F.col(body_col).cast("binary"), F.lit(b""))
    seen = pages.where(F.octet_length(body) >= min_bytes).select(F.col(id_col).cast("bigint").alias("page"), F.sha1(body).alias("digest"))
    first = seen.groupBy("digest").agg(F.max("page").alias("refers_to"), F.count(F.lit(1)).alias("n")).where("n > 1").drop("n")
    # A row without an id loses to any that has one.
    return seen.join(first.where("refers_to IS NOT NULL"), "digest").where("page IS NULL OR page < refers_to").select("page", "digest", "refers_to").distinct()


def _stored_bytes(df: DataFrame, body_col: str) -> int:
    """Spark's own estimate, from file sizes without a job; where it knows none, the bodies' bytes."""
    known = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    if known < 1 << 60:
        return known
    return df.agg(F.coalesce(F.sum(F.octet_length(F.col(body_col).cast("binary"))), F.lit(0))).first()[0]


def write_archives(pages: DataFrame, path: str, *, id_col: str = "page_id", url_col: str = "url", body_col: str = "html", min_bytes: int = 0, dictionary: bytes | None = None, archive_bytes: int = 128 << 20) -> str:
    """Archives under ``path``, one for each task, of about ``archive_bytes`` of the input's stored bytes: a reader holds one whole."""
    dictionary = build_dictionary(pages, id_col=id_col, url_col=url_col, body_col=body_col) if dictionary is None else dictionary
    shared = pages.sparkSession.sparkContext.broadcast(dictionary)
    body = F.coalesce(F.col(body_col).cast("binary"), F.lit(b""))
    rows = pages.select(F.col(id_col).cast("bigint").alias("page"), F.col(url_col).cast("string").alias("url"), body.alias("body")).withColumn("digest", F.sha1("body"))
    spark = pages.sparkSession
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-_stored_bytes(pages, body_col) // archive_bytes))
    own = F.coalesce("page", F.lit(-(1 << 63))).alias("own")
    again = revisits(pages, id_col=id_col, body_col=body_col, min_bytes=min_bytes).select(own, "digest", "refers_to")
    marked = rows.withColumn("own", own).repartition(parts, "own", "digest").join(again, ["own", "digest"], "left").select("page", "url", "body", "refers_to")
    marked.mapInArrow(_pack(shared), "frame binary").select(F.col("frame").cast("string").alias("value")).write.option("lineSep", BETWEEN).text(path)
    return path


def read_archives(spark: SparkSession, path: str, *, payload: bool = True) -> DataFrame:
    """The records of all archives under ``path``; with ``payload`` also url and payload."""
    files = spark.read.format("binaryFile").load(path).select("content")
    listed = "page_id bigint, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint"
    if not payload:
        return files.mapInArrow(_listing, listed)
    return files.mapInArrow(_unpack, "page_id bigint, url string, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint, payload binary")


def op6_warc(spark, sf_dir: str) -> DataFrame:
    path = write_archives(spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html"), new_path(spark, "warc"))
    return read_archives(spark, path, payload=False)
