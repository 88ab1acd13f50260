"""Token counts by scanning flat token files for end-of-document identifiers.

A flat file is nothing but unsigned 16-bit big-endian ids, one document after another, each closed
by the identifier ``eod``; there is no index. ``write_flat`` makes such files from texts,
with no shuffle. ``count_flat`` reads any: files are cut into blocks of ``block_tokens``;
a vectorised search in each block finds its separators; a prefix scan over the
blocks' summaries (separators before a block, place of the last one) stitches
documents that cross blocks; a second read gives a row for each document.

Ids past the vocabulary (``LABEL`` and up) may open a document: they spell its
integer label in digits to the base 4096 after a sign, so that counts can name documents
whatever order the files are in. They are not counted.

The prefix scan has two levels (blocks within a run of ``RUN`` blocks, then runs), so a
file of any length is stitched without one task seeing all its blocks.

Edge cases: null and empty texts have count 0; a null id is kept as null; repeated
rows give as many documents; a file whose last document is not closed gives a row
with ``closed`` false; an empty file or folder gives no row.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .arrow import pieces, texts
from .scratch import new_path
from .tokens import tokenizer_path, word_ids

WIDTH = 2
EOD = 49407
#: Signs that open a label (none, positive, negative), and its digits from DIGIT on.
LABEL, DIGIT, BASE = 50000, 50010, 4096
LABEL_TOKENS = 7
RUN = 256


def label_ids(value: int | None) -> bytes:
    if value is None:
        return np.array([LABEL], ">u2").tobytes()
    digits, rest = [], abs(value)
    while rest:
        digits.append(DIGIT + rest % BASE)
        rest //= BASE
    return np.array([LABEL + 1 + (value < 0), *digits], ">u2").tobytes()


def read_label(ids: np.ndarray) -> tuple[int | None, int]:
    """The label at the start of a document and how many ids it takes."""
    if not len(ids) or not LABEL <= ids[0] <= LABEL + 2:
        return None, 0
    if ids[0] == LABEL:
        return None, 1
    value, n = 0, 1
    while n < len(ids) and DIGIT <= ids[n] < DIGIT + BASE:
        value += int(ids[n] - DIGIT) * BASE ** (n - 1)
        n += 1
    return (-value if ids[0] == LABEL + 2 else value), n


def _flatten(path: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, end = word_ids(path), np.array([EOD], ">u2").tobytes()
        for batch in batches:
            for part in pieces(batch, "text", 4 << 20):
                found = ids(texts(part.column("text")))
                labels = part.column("id").to_pylist()
                rows = [label_ids(k) + np.frombuffer(x, "<u4").astype(">u2").tobytes() + end for k, x in zip(labels, found, strict=True)]
                # A file is written line by line; what closes a line is a padding id, which the scan skips.
                yield pa.RecordBatch.from_arrays([pa.array([b"".join(rows)], pa.binary())], ["ids"])

    return run


#: Closes what the writer calls a line: one character whose two bytes are one unused id.
PAD = "\u07ff"
PAD_ID = 0xDFBF


def write_flat(docs: DataFrame, path: str, *, tokenizer: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> str:
    """Flat files of all texts under ``path``. Spark's own writer commits them, so lost tasks leave nothing behind."""
    flat = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).cast("string").alias("text")).mapInArrow(_flatten(tokenizer or tokenizer_path()), "ids binary")
    flat.select(F.col("ids").cast("string").alias("value")).write.option("lineSep", PAD).text(path)
    return path


def list_blocks(spark: SparkSession, path: str, block_tokens: int) -> DataFrame:
    """``file, size, block`` without reading any content."""
    files = spark.read.format("binaryFile").load(path).select(F.col("path").alias("file"), (F.col("length") / WIDTH).cast("bigint").alias("size"))
    n = F.ceil(F.col("size") / block_tokens)
    return files.where("size > 0").select("file", "size", F.explode(F.sequence(F.lit(0).cast("bigint"), n - 1)).alias("block"))


class _Reader:
    """Ranges of ids of files, through pyarrow's file systems (local, HDFS, S3, GCS)."""

    def __init__(self) -> None:
        self.name, self.file = None, None

    def __call__(self, name: str, start: int, stop: int) -> np.ndarray:
        if name != self.name:
            from pyarrow import fs

            store, inner = fs.FileSystem.from_uri(name if "://" in name else name.replace("file:/", "file:///", 1))
            self.name, self.file = name, store.open_input_file(inner)
        return np.frombuffer(self.file.read_at((stop - start) * WIDTH, start * WIDTH), ">u2").astype(np.uint16)


def _summaries(block_tokens: int, eod: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        read = _Reader()
        for batch in batches:
            rows = []
            for f, size, block in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                base = block * block_tokens
                seps = np.flatnonzero(read(f, base, min(size, base + block_tokens)) == eod)
                rows.append((f, size, block, len(seps), base + int(seps[-1]) if len(seps) else None))
            kinds = [pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*rows, strict=True)) or [[]] * 5, kinds, strict=True)], ["file", "size", "block", "n", "last"])

    return run


def _documents(block_tokens: int, eod: int, pad: int | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        read = _Reader()
        for batch in batches:
            for f, size, block, before, last in zip(*(batch.column(k).to_pylist() for k in ("file", "size", "block", "before", "open_after")), strict=True):
                base, stop = block * block_tokens, min(size, (block + 1) * block_tokens)
                ids = read(f, base, stop)
                ends = np.flatnonzero(ids == eod) + base
                final = stop == size and (not len(ends) or ends[-1] != size - 1)
                tail = ends[-1] + 1 if len(ends) else (0 if last is None else last + 1)
                first = 0 if last is None else last + 1
                starts = np.r_[first, ends + 1][: len(ends)]
                pads = ids == pad if pad is not None else np.zeros(len(ids), bool)
                carried = 0
                if first < base and (len(ends) or final):  # padding in the part that lies in earlier blocks
                    for a in range(first, base, block_tokens):
                        carried += int((read(f, a, min(base, a + block_tokens)) == pad).sum()) if pad is not None else 0
                sums = np.r_[0, np.cumsum(pads)]
                rows = []
                spans = [(int(s), int(e), True) for s, e in zip(starts, ends, strict=True)] + ([(int(tail), size, False)] if final else [])
                for k, (s, e, closed) in enumerate(spans):
                    head = ids[s - base : s - base + LABEL_TOKENS + 1] if s >= base else read(f, s, min(size, s + LABEL_TOKENS + 1))
                    skip = int(len(head) > 0 and head[0] == pad)
                    label, n = read_label(head[skip:])
                    padding = int(sums[e - base] - sums[max(s, base) - base]) + (carried if s < base else 0)
                    if not closed and e - s == padding:
                        continue
                    rows.append((f, before + k, s, label, e - s - n - padding, closed))
                kinds = [pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.bool_()]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*rows, strict=True)) or [[]] * 6, kinds, strict=True)], ["file", "ordinal", "start", "label", "n_tokens", "closed"])

    return run


def count_flat(spark: SparkSession, path: str, *, block_tokens: int = 1 << 19, task_blocks: int = 16, eod: int = EOD, pad: int | None = PAD_ID) -> DataFrame:
    """``file, ordinal, start, label, n_tokens, closed``: a row for each document of the flat files under ``path``."""
    blocks = list_blocks(spark, path, block_tokens)
    # A row here stands for a block's bytes, which Spark cannot see: the number of tasks is set from the number of blocks.
    tasks = max(1, -(-blocks.count() // task_blocks))
    blocks = blocks.repartition(tasks, "file", "block")
    found = blocks.mapInArrow(_summaries(block_tokens, eod), "file string, size bigint, block bigint, n bigint, last bigint")
    run = F.floor(F.col("block") / RUN).alias("run")
    inner = Window.partitionBy("file", "run").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    outer = Window.partitionBy("file").orderBy("run").rowsBetween(Window.unboundedPreceding, -1)
    found = found.withColumn("run", run)
    runs = found.groupBy("file", "run").agg(F.sum("n").alias("n"), F.max("last").alias("last")).select("file", "run", F.coalesce(F.sum("n").over(outer), F.lit(0)).alias("run_before"), F.max("last").over(outer).alias("run_last"))
    stitched = (
        found.withColumn("in_run", F.coalesce(F.sum("n").over(inner), F.lit(0)))
        .withColumn("in_last", F.max("last").over(inner))
        .join(runs, ["file", "run"])
        .select("file", "size", "block", (F.col("in_run") + F.col("run_before")).alias("before"), F.coalesce("in_last", "run_last").alias("open_after"))
    )
    return stitched.repartition(tasks, "file", "block").mapInArrow(_documents(block_tokens, eod, pad), "file string, ordinal bigint, start bigint, label bigint, n_tokens bigint, closed boolean")


def op10_token_counts(spark, sf_dir: str) -> DataFrame:
    """``doc_id, n_tokens`` of every document, with the file, ordinal and place it was found at."""
    path = write_flat(spark.read.parquet(f"{sf_dir}/documents.parquet"), new_path(spark, "flat-tokens"))
    return count_flat(spark, path).select(F.col("label").alias("doc_id"), "n_tokens", F.regexp_extract("file", r"([^/]+)$", 1).alias("file"), "ordinal", "start", "closed")
