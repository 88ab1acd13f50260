"""Quality classification by compression.

Two Zstandard dictionaries are built, from good and from bad labelled text. A text
is compressed with each, block by block so that a long text keeps using the
dictionary; the difference of the two sizes over the text's length, and the better
of the two sizes over the length, are turned into a probability by a logistic
regression fitted on labelled texts that the dictionaries have not seen.

Fitting reads at most ``per_label_rows`` documents of each label, those with the
least hash of their id; scoring reads whole texts.

Edge cases: a null or empty text gets the score of zero difference at the mean length
ratio; with one label missing in the sample every score is the share of label 1
(0.5 without labels). Repeated rows stay. Other columns than id and text are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .arrow import pieces, texts
from .sample import fold, labelled_sample

#: Bytes that are compressed together.
BLOCK = 2048
DICT_BYTES = 96 << 10
LEVEL = 3
CUT = 0.3


@dataclass
class CompressionModel:
    good: bytes
    bad: bytes
    mean: np.ndarray
    spread: np.ndarray
    weights: np.ndarray
    constant: float | None = None


class Sizer:
    """Compressed bytes of a text under one dictionary."""

    def __init__(self, dictionary: bytes) -> None:
        kept = zstandard.ZstdCompressionDict(dictionary)
        kept.precompute_compress(level=LEVEL)
        self.one = zstandard.ZstdCompressor(level=LEVEL, dict_data=kept, write_content_size=False, write_dict_id=False)

    def __call__(self, text: bytes) -> int:
        squeeze = self.one.compress
        return sum(len(squeeze(text[a : a + BLOCK])) for a in range(0, len(text), BLOCK))


def _dictionary(samples: list[bytes]) -> bytes:
    blocks = [t[a : a + BLOCK] for t in samples for a in range(0, len(t), BLOCK)]
    blocks = [b for b in blocks if len(b) >= 64]
    try:
        return zstandard.train_dictionary(DICT_BYTES, blocks, level=LEVEL).as_bytes()
    except (zstandard.ZstdError, MemoryError):  # too little text to train on: the text itself serves as dictionary
        return b"".join(blocks)[:DICT_BYTES] or b"\n" * 64


def features(sizers: tuple[Sizer, Sizer], bodies: list[bytes]) -> np.ndarray:
    out = np.zeros((len(bodies), 2))
    for i, t in enumerate(bodies):
        if t:
            good, bad = sizers[0](t), sizers[1](t)
            out[i] = (bad - good) / len(t), min(good, bad) / len(t)
        else:
            out[i] = 0.0, np.nan
    return out


def _design(model: CompressionModel, x: np.ndarray) -> np.ndarray:
    z = np.clip((np.where(np.isnan(x), model.mean, x) - model.mean) / model.spread, -8, 8)
    return np.column_stack([np.ones(len(z)), z, z[:, 0] * z[:, 1], z**2])


def fit(samples: list[tuple[int, bytes]], *, share: float = 0.5, ridge: float = 1.0, steps: int = 60) -> CompressionModel:
    """Half of the sample builds the dictionaries, the other half calibrates. ``share``: of label 1 among all labelled rows."""
    sides = {q: [t for y, t in samples if y == q] for q in (0, 1)}
    if not sides[0] or not sides[1]:
        return CompressionModel(b"", b"", np.zeros(2), np.ones(2), np.zeros(6), share)
    good, bad = _dictionary(sides[1][::2]), _dictionary(sides[0][::2])
    rest = [(q, t) for q in (0, 1) for t in (sides[q][1::2] or sides[q])]
    x, y = features((Sizer(good), Sizer(bad)), [t for _, t in rest]), np.array([q for q, _ in rest], float)
    model = CompressionModel(good, bad, np.nanmean(x, axis=0), np.maximum(np.nanstd(x, axis=0), 1e-6), np.zeros(6))
    d = _design(model, x)
    w = np.zeros(d.shape[1])
    # The sample is bounded for each label; weights restore the labels' shares.
    weight = np.where(y == 1, share / y.mean(), (1 - share) / (1 - y.mean()))
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(d @ w, -30, 30)))
        h = d.T @ (d * (weight * p * (1 - p))[:, None]) + ridge * np.eye(len(w))
        step = np.linalg.solve(h, d.T @ (weight * (y - p)) - ridge * w)
        w += step
        if np.abs(step).max() < 1e-8:
            break
    model.weights = w
    return model


def scores(model: CompressionModel, bodies: list[bytes], sizers: tuple[Sizer, Sizer] | None = None) -> np.ndarray:
    if model.constant is not None:
        return np.full(len(bodies), model.constant)
    x = features(sizers or (Sizer(model.good), Sizer(model.bad)), bodies)
    return 1 / (1 + np.exp(-np.clip(_design(model, x) @ model.weights, -30, 30)))


def _scorer(model, text_col: str, keep: list[str]):
    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fitted: CompressionModel = model.value
        sizers = None if fitted.constant is not None else (Sizer(fitted.good), Sizer(fitted.bad))
        for batch in batches:
            for part in pieces(batch, text_col, 4 << 20):
                s = scores(fitted, texts(part.column(text_col)), sizers)
                yield pa.RecordBatch.from_arrays([*(part.column(k) for k in keep), pa.array(s, pa.float64())], [*keep, "__score"])

    return score


def score_quality(docs: DataFrame, model: CompressionModel, *, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """The columns ``keep`` (all of ``docs`` if None) and ``__score``."""
    keep = docs.columns if keep is None else keep
    shared = docs.sparkSession.sparkContext.broadcast(model)
    schema = "".join(f"`{k}` {docs.schema[k].dataType.simpleString()}, " for k in keep)
    return docs.select(*dict.fromkeys([*keep, text_col])).mapInArrow(_scorer(shared, text_col, keep), f"{schema}__score double")


def fit_on(docs: DataFrame, labels: DataFrame, *, label: str = "quality", per_label_rows: int = 1000) -> CompressionModel:
    """Learned from labelled documents outside the held-out fold (crc32 of the id modulo 5 is 0)."""
    learn = labels.where((fold(F.col("doc_id"), 5) != 0) & F.col(label).isin(0, 1)).select("doc_id", F.col(label).cast("int").alias(label))
    share = learn.agg(F.avg(label)).first()[0]
    return fit([(int(q), bytes(t)) for q, t in labelled_sample(docs, learn, label, per_label_rows).toLocalIterator()], share=0.5 if share is None else share)


def op3_quality(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    model = fit_on(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    scored = score_quality(docs, model, keep=["doc_id"])
    return scored.select("doc_id", (fold(F.col("doc_id"), 5) == 0).alias("held_out"), F.col("__score").alias("score"), (F.col("__score") >= CUT).cast("int").alias("predicted"))
