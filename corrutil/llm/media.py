"""Media columns: PNG images written and read without an image library, and their cosine-transform hashes.

``png_encode`` stores bytes as the samples of an 8-bit grey image of 64 columns;
``png_decode`` reads any non-interlaced 8-bit grey image: it walks the chunks, tests
each checksum, inflates the data and undoes the row filters in numpy. The hash is
the sign pattern of the 8 x 8 lowest frequencies of the cosine transform of the image
averaged down to 32 x 32, against their median.

Edge cases: a null text is empty; an empty payload is stored as one row of zeros
(padding goes up to a positive multiple of 64); equal texts give equal values.
A chunk with a wrong checksum, a missing end or a short image raises ``ValueError``.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .arrow import bounded_batches, pieces, texts
from .scratch import written

SIGNATURE = b"\x89PNG\r\n\x1a\n"
WIDTH = 64
#: Columns of the small image and of the kept low frequencies.
SIDE, LOW = 32, 8
#: Bytes of texts or images that are worked on at once; a longer one is alone.
PART = 2 << 20


def _chunk(kind: bytes, body: bytes) -> bytes:
    return struct.pack(">I", len(body)) + kind + body + struct.pack(">I", zlib.crc32(kind + body))


def filtered(rows: np.ndarray) -> np.ndarray:
    """Rows with the filter byte in front: of none, left and up the one with the least sum of absolute values."""
    left, up = rows.copy(), rows.copy()
    left[:, 1:] -= rows[:, :-1]
    up[1:] -= rows[:-1]
    choices = np.stack([rows, left, up])
    weight = np.abs(choices.view(np.int8).astype(np.int16)).sum(axis=2)
    best = weight.argmin(axis=0).astype(np.uint8)
    return np.concatenate([best[:, None], choices[best, np.arange(len(rows))]], axis=1)


def unfiltered(data: np.ndarray) -> np.ndarray:
    """Samples from filtered rows (one byte a sample), for all five filters."""
    kinds, out = data[:, 0], data[:, 1:].copy()
    if kinds.max(initial=0) > 4:
        raise ValueError("unknown row filter")
    left = kinds == 1
    out[left] = np.cumsum(out[left], axis=1, dtype=np.uint8)
    # Runs of rows that add up down a column are one cumulative sum each.
    slow = np.flatnonzero(kinds >= 2)
    for i in slow.tolist() if not np.all(kinds[slow] == 2) else []:
        above = out[i - 1] if i else np.zeros_like(out[0])
        if kinds[i] == 2:
            out[i] += above
            continue
        row, prior = out[i].tolist(), above.tolist()
        a = c = 0
        for x, b in enumerate(prior):
            if kinds[i] == 3:
                guess = (a + b) // 2
            else:
                p = a + b - c
                pa_, pb, pc = abs(p - a), abs(p - b), abs(p - c)
                guess = a if pa_ <= pb and pa_ <= pc else b if pb <= pc else c
            a = row[x] = (row[x] + guess) & 255
            c = b
        out[i] = row
    if len(slow) and np.all(kinds[slow] == 2):
        starts = np.flatnonzero((kinds == 2) & np.r_[True, kinds[:-1] != 2])
        stops = np.flatnonzero((kinds == 2) & np.r_[kinds[1:] != 2, True])
        for a, b in zip(starts.tolist(), stops.tolist(), strict=True):
            first = max(a - 1, 0)
            out[first : b + 1] = np.cumsum(out[first : b + 1], axis=0, dtype=np.uint8)
    return out


def png_encode(payload: bytes, level: int = 1) -> bytes:
    """A grey image of ``WIDTH`` columns; the payload's length is a positive multiple of WIDTH."""
    rows = np.frombuffer(payload, np.uint8).reshape(-1, WIDTH)
    head = struct.pack(">IIBBBBB", WIDTH, len(rows), 8, 0, 0, 0, 0)
    return SIGNATURE + _chunk(b"IHDR", head) + _chunk(b"IDAT", zlib.compress(filtered(rows).tobytes(), level)) + _chunk(b"IEND", b"")


def png_decode(image: bytes) -> np.ndarray:
    if image[:8] != SIGNATURE:
        raise ValueError("no PNG signature")
    at, shape, body = 8, None, []
    while True:
        if at + 12 > len(image):
            raise ValueError("the image has no end chunk")
        (size,), kind = struct.unpack_from(">I", image, at), image[at + 4 : at + 8]
        data = image[at + 8 : at + 8 + size]
        if len(data) < size or image[at + 8 + size : at + 12 + size] != struct.pack(">I", zlib.crc32(kind + data)):
            raise ValueError(f"wrong checksum in chunk {kind!r}")
        at += 12 + size
        if kind == b"IHDR":
            width, height, *form = struct.unpack(">IIBBBBB", data)
            if form != [8, 0, 0, 0, 0]:
                raise ValueError("only 8-bit grey images without interlace")
            shape = height, width + 1
        elif kind == b"IDAT":
            body.append(data)
        elif kind == b"IEND":
            break
    raw = np.frombuffer(zlib.decompress(b"".join(body)), np.uint8)
    if shape is None or raw.size != shape[0] * shape[1]:
        raise ValueError("the image data has another size than its head says")
    return unfiltered(raw.reshape(shape))


def _cosine(n: int, m: int) -> np.ndarray:
    """The first m rows of the orthonormal cosine transform of length n."""
    k, x = np.arange(m)[:, None], np.arange(n)[None, :]
    return np.cos(np.pi * k * (2 * x + 1) / (2 * n)) * np.where(k == 0, np.sqrt(1 / n), np.sqrt(2 / n))


_BASIS = _cosine(SIDE, LOW)


def cosine_hash(samples: np.ndarray) -> str:
    """16 hex digits. Rows are averaged into 32 bands of near-equal height, columns likewise."""
    def banded(a: np.ndarray) -> np.ndarray:
        n = len(a)
        if n < SIDE:
            return a[np.arange(SIDE) * n // SIDE]
        cuts = np.arange(SIDE) * n // SIDE
        return np.add.reduceat(a, cuts, axis=0) / np.diff(np.r_[cuts, n])[:, None]

    small = banded(banded(samples.astype(np.float64)).T).T
    low = np.round(_BASIS @ small @ _BASIS.T, 6)
    bits = (low > np.median(low)).ravel()
    return np.packbits(bits).tobytes().hex()


def encode_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for part in pieces(batch, "text", PART):
            bodies = texts(part.column(1))
            images = [png_encode(t + bytes(-len(t) % WIDTH or (0 if t else WIDTH))) for t in bodies]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array([len(t) for t in bodies], pa.int64()), pa.array(images, pa.binary())], ["id", "n_bytes", "media"])


def decode_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for part in pieces(batch, "media", PART):
            rows = []
            for image in texts(part.column(2)):
                samples = png_decode(image)
                payload = samples.tobytes()
                rows.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), len(image), hashlib.sha256(image).hexdigest(), cosine_hash(samples)))
            columns = list(zip(*rows, strict=True)) or [[]] * 6
            kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), *(pa.array(c, t) for c, t in zip(columns, kinds, strict=True))], ["id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])


def store_images(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id, n_bytes, media``: each text's bytes as a PNG in a binary column."""
    bounded_batches(docs.sparkSession)
    id_type = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")).mapInArrow(encode_batches, f"id {id_type}, n_bytes bigint, media binary")


def image_features(media: DataFrame) -> DataFrame:
    id_type = media.schema["id"].dataType.simpleString()
    return media.mapInArrow(decode_batches, f"id {id_type}, n_bytes bigint, payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, media_bytes bigint, media_sha256 string, feature string")


def op8_media_columns(spark, sf_dir: str) -> DataFrame:
    stored = written(store_images(spark.read.parquet(f"{sf_dir}/documents.parquet")), "media")
    return image_features(stored).withColumnRenamed("id", "doc_id")
