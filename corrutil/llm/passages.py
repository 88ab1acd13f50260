"""Passages of a number of words that occur more than once, however few bytes they take.

A word is what stands between white space, without the ASCII punctuation around it; a passage runs
from the first byte of its first word to the last byte of its last, and equal means equal bytes.

The word of least hash among the first ``WINDOW`` of a passage is its anchor. Equal
passages have the same anchor, and the words from there that every passage of the anchor
holds (its core) are equal too. So only passages of shared cores are hashed one by one, with 128 bits.

Passages in a row with one anchor are a run. A run whose bytes (128-bit hash) occur elsewhere is repeated as a
whole: it is a span as it stands, and one place of it, the least, stands for all of them in what follows.
A passage that thousands of texts share so leaves one run of each kind inside, and only the runs at its edges, which differ, are opened.
Equal runs of a task's texts are one row where they are found, as a text that repeats itself word by word has a run for each word.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .arrow import bounded_batches, pieces, raw
from .scratch import discard, written
from .suffixdedup import PART, _hash, _joined, _keyed_docs, firsts, stretches

#: Share of a passage's words among which its anchor is found.
WINDOW = 0.6
_SPACE = np.isin(np.arange(256), [9, 10, 11, 12, 13, 32])
_LETTER = np.array([i >= 128 or chr(i).isalnum() for i in range(256)])


def spelled(data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First byte, byte after the last, and text of every word."""
    space = _SPACE[data]
    new = ~space
    new[1:] &= space[:-1]
    new[at[:-1][np.diff(at) > 0]] |= ~space[at[:-1][np.diff(at) > 0]]
    run = np.cumsum(new)
    letters = np.flatnonzero(_LETTER[data])
    if not len(letters):
        return letters, letters, letters
    head = np.r_[True, np.diff(run[letters]) > 0]
    start, stop = letters[head], letters[np.r_[head[1:], True]] + 1
    return start, stop, np.searchsorted(at, start, side="right") - 1


def _passage_anchors(words: int):
    window = int(words * WINDOW)
    core = words - window + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        one, two = _hash("one"), _hash("two")
        for batch in batches:
            for part in pieces(batch, "text", PART):
                data, at = raw(part.column("text"))
                start, stop, text = spelled(data, at)
                if len(start) < words:
                    continue
                with np.errstate(over="ignore"):
                    prefix = one.prefix(data)
                    key = one.span(prefix, start, stop)
                    n = len(start) - words + 1
                    anchor = np.lib.stride_tricks.sliding_window_view(key, window)[:n].argmin(axis=1) + np.arange(n)
                    low = np.flatnonzero(text[:n] == text[words - 1 :])
                    if not len(low):
                        continue
                    head = np.r_[True, (anchor[low[1:]] != anchor[low[:-1]]) | (np.diff(low) > 1) | (text[low[1:]] != text[low[:-1]])]
                    first, last = low[head], low[np.r_[head[1:], True]]
                    a = anchor[first]
                    found = one.span(prefix, start[a], stop[a + core - 1]).view(np.int64)
                    a, b = start[first], stop[last + words - 1]
                    x, y = one.span(prefix, a, b).view(np.int64), two.span(two.prefix(data), a, b).view(np.int64)
                same, times = firsts(x, y)
                mine = same == np.arange(len(x))
                # The others leave their spans, joined where they follow one another, without hashes.
                u, v = stretches(np.flatnonzero(~mine), text[first])
                rows, ends = np.r_[np.flatnonzero(mine), u], np.r_[np.flatnonzero(mine), v]
                owner = text[first[rows]]
                base = np.searchsorted(text, owner)  # words are numbered within their text
                take = pa.array(owner, pa.int64())
                blank = np.arange(len(rows)) >= mine.sum()
                yield pa.RecordBatch.from_arrays(
                    [
                        part.column("doc_id").take(take), part.column("mark").take(take), pa.array((first[rows] - base).astype(np.int32)), pa.array((last[ends] - base).astype(np.int32)), pa.array(found[rows]),
                        pa.array((a[rows] - at[owner]).astype(np.int32)), pa.array((b[ends] - at[owner]).astype(np.int32)), pa.array(x[rows], mask=blank), pa.array(y[rows], mask=blank), pa.array(np.where(blank, 1, times[rows])),
                    ],
                    ["doc_id", "mark", "low", "high", "core", "start", "stop", "x", "y", "times"],
                )

    return run


def _passages(words: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        one, two = _hash("one"), _hash("two")
        for batch in batches:
            for part in pieces(batch, "text", PART):
                data, at = raw(part.column("text"))
                start, stop, text = spelled(data, at)
                wanted = part.column("wanted")
                flat, edges = wanted.flatten(), wanted.offsets.to_numpy()
                owner = np.repeat(np.arange(part.num_rows), np.diff(edges))
                low, high = (flat.field(f).to_numpy().astype(np.int64) + np.searchsorted(text, owner) for f in ("low", "high"))
                alone = flat.field("alone").to_numpy(zero_copy_only=False).astype(bool)
                n = high - low + 1
                first = np.repeat(low - np.r_[0, np.cumsum(n)[:-1]], n) + np.arange(n.sum())
                a, b, row = start[first], stop[first + words - 1], np.repeat(owner, n)
                with np.errstate(over="ignore"):
                    x, y = one.span(one.prefix(data), a, b).view(np.int64), two.span(two.prefix(data), a, b).view(np.int64)
                take = pa.array(row, pa.int64())
                yield pa.RecordBatch.from_arrays(
                    [part.column("doc_id").take(take), part.column("mark").take(take), pa.array((a - at[row]).astype(np.int32)), pa.array((b - at[row]).astype(np.int32)), pa.array(x), pa.array(y), pa.array(np.repeat(alone, n))],
                    ["doc_id", "mark", "start", "stop", "x", "y", "alone"],
                )

    return run


def _stretched(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The spans of each text, joined where they overlap or touch."""
    for batch in batches:
        spans = batch.column("spans")
        flat, edges = spans.flatten(), spans.offsets.to_numpy()
        edges = edges - edges[0]
        both = np.column_stack([flat.field("start").to_numpy(), flat.field("stop").to_numpy()]).astype(np.int64)
        rows = [(i, a, b) for i in range(batch.num_rows) for a, b in _joined(both[edges[i] : edges[i + 1]])]
        owner, start, stop = (list(c) for c in zip(*rows, strict=True)) if rows else ([], [], [])
        take = pa.array(owner, pa.int64())
        yield pa.RecordBatch.from_arrays([batch.column("doc_id").take(take), batch.column("mark").take(take), pa.array(start, pa.int32()), pa.array(stop, pa.int32())], ["doc_id", "mark", "start", "stop"])


def repeated_passages(docs: DataFrame, words: int, *, id_col: str = "doc_id", text_col: str = "text", settle: bool = False) -> DataFrame:
    """``doc_id, mark, start, stop`` as ``suffixdedup.repeated_spans`` gives them: bytes of passages that occur again.

    With ``settle`` they are written, stretches joined, and the tables that they come from are freed.
    """
    bounded_batches(docs.sparkSession)
    texts = _keyed_docs(docs, id_col, text_col).where(F.octet_length("text") >= 2 * words - 1)
    who = "doc_id bigint, mark bigint"
    found = written(texts.mapInArrow(_passage_anchors(words), f"{who}, low int, high int, core bigint, start int, stop int, x bigint, y bigint, times bigint"), "passage-runs")
    # Copies are counted where they are before they are shuffled.
    hashed = found.where("x IS NOT NULL")
    many = hashed.groupBy("x", "y").agg(F.sum("times").alias("n"), F.min(F.struct("doc_id", "mark", "low")).alias("least")).where("n > 1").select("x", "y", "least")
    placed = written(hashed.join(many, ["x", "y"], "left").drop("x", "y", "times"), "placed-runs")
    settled = written(found.where("x IS NULL").select("doc_id", "mark", "start", "stop"), "settled-runs")
    discard(found)
    whole = settled.unionByName(placed.where("least IS NOT NULL").select("doc_id", "mark", "start", "stop"))
    stands = F.col("least").isNull() | F.col("least").eqNullSafe(F.struct("doc_id", "mark", "low"))
    runs = placed.where(stands).select("doc_id", "mark", "low", "high", "core", F.col("least").isNull().alias("alone"))
    shared = runs.groupBy("core").agg(F.count(F.lit(1)).alias("n"), F.bool_or("alone").alias("open")).where("n > 1 AND open").select("core")
    wanted = runs.join(shared, "core", "left_semi").groupBy("doc_id", "mark").agg(F.collect_set(F.struct("low", "high", "alone")).alias("wanted")).select(F.col("doc_id").alias("d"), F.col("mark").alias("m"), "wanted")
    asked = texts.join(wanted, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("mark") == F.col("m"))).select("doc_id", "mark", "text", "wanted")
    strings = written(asked.mapInArrow(_passages(words), f"{who}, start int, stop int, x bigint, y bigint, alone boolean"), "passages")
    # A passage of a repeated run stands for more than one place.
    again = strings.groupBy("x", "y").agg(F.sum(F.when(F.col("alone"), 1).otherwise(2)).alias("n")).where("n > 1").select("x", "y")
    spans = whole.unionByName(strings.where("alone").join(again, ["x", "y"], "left_semi").select("doc_id", "mark", "start", "stop"))
    if not settle:
        return spans
    joined = written(spans.groupBy("doc_id", "mark").agg(F.collect_set(F.struct("start", "stop")).alias("spans")).mapInArrow(_stretched, f"{who}, start int, stop int"), "passage-spans")
    discard(placed, settled, strings)
    return joined
