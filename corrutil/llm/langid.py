"""Language identification by prediction by partial matching.

One context tree over bytes is kept for each language: up to ``order`` preceding
bytes select a node; a symbol's probability there is its share of the node's counts,
and an escape (distinct symbols over distinct symbols plus count) passes to the node
of the next shorter context, without the symbols already offered. After training
the counts are frozen, so every (node, symbol) has one exact code length. A text's
code length in a language is a sum of table entries, and the shortest one wins.

Symbols: the commonest bytes of the sample have one each, all other bytes share one
and are told apart by frozen order-0 counts. Nodes are shared by the languages: a
context is a node if the sample of all languages shows it ``least`` times.

Fitting reads at most ``per_language`` documents of each language, those with the least
hash of their id, until ``sample_bytes`` of them are read; no other step is bounded.

Edge cases: a null text or one without a letter is ``und`` with score 0; the empty
text likewise; ties go to the language first in code-point order; with no learned
language every text is ``und``. Repeated rows stay. Other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .arrow import pieces, raw
from .sample import fold, labelled_sample

BITS = 7
SIZE = 1 << BITS
#: Code lengths are kept in 1/256 bit.
UNIT = 256


@dataclass
class ContextTrees:
    languages: list[str]
    symbol: np.ndarray  # byte -> symbol
    rare: np.ndarray  # byte, language -> extra length of a byte within the shared symbol
    node: np.ndarray  # packed context -> node
    cost: np.ndarray  # node * SIZE + symbol, language -> length
    order: int


def _contexts(data: np.ndarray, at: np.ndarray, order: int) -> np.ndarray:
    """Before each position its preceding symbols, packed, the nearest lowest; before a text there are zeros."""
    out = np.zeros(len(data), np.int64)
    start = np.repeat(at[:-1], np.diff(at))
    where = np.arange(len(data)) - start
    for k in range(1, order + 1):
        shifted = np.zeros(len(data), np.int64)
        shifted[k:] = data[:-k] if len(data) > k else []
        shifted[where < k] = 0
        out |= shifted << (BITS * (k - 1))
    return out


def fit(samples: dict[str, list[bytes]], *, order: int = 3, least: int = 24) -> ContextTrees:
    languages = sorted(samples)
    flat = {k: (np.frombuffer(b"".join(v), np.uint8), np.cumsum([0, *map(len, v)])) for k, v in samples.items()}
    by_byte = np.stack([np.bincount(flat[k][0], minlength=256) for k in languages], axis=1) if languages else np.zeros((256, 0), int)
    common = np.argsort(-by_byte.sum(axis=1), kind="stable")[: SIZE - 2]
    symbol = np.full(256, SIZE - 1, np.uint8)
    symbol[common] = np.arange(1, SIZE - 1)  # 0 stands before a text
    shared = symbol == SIZE - 1
    inside = (by_byte + 1.0) * shared[:, None]
    rare = np.where(shared[:, None], -np.log2(np.maximum(inside, 1e-300) / np.maximum(inside.sum(axis=0), 1e-300)), 0) if languages else np.zeros((256, 0))

    seen = {k: symbol[flat[k][0]] for k in languages}
    packed = {k: _contexts(seen[k].astype(np.int64), flat[k][1], order) for k in languages}
    node = np.zeros(1 << (BITS * order), np.int32)
    uniform = np.full((1, SIZE), 1 / (SIZE - 1))
    uniform[:, 0] = 0
    counts0 = np.stack([np.bincount(seen[k], minlength=SIZE) for k in languages], axis=0) if languages else np.zeros((0, SIZE))
    table = [np.stack([_escape(c[None, :], uniform)[0] for c in counts0], axis=0)[None]] if languages else [np.zeros((1, 0, SIZE))]
    parents = np.zeros(1, np.int64)  # nodes of the contexts one shorter, by packed context
    total = 1
    for k in range(1, order + 1):
        mask = (1 << (BITS * k)) - 1
        pairs = {g: ((packed[g] & mask) << BITS) | seen[g] for g in languages}
        whole = np.bincount(np.concatenate([packed[g] & mask for g in languages]), minlength=mask + 1) if languages else np.zeros(mask + 1, int)
        kept = np.flatnonzero(whole >= least)
        here = parents[np.arange(mask + 1) & (mask >> BITS)]
        up = here[kept]
        above = np.concatenate(table)
        rows = np.zeros((len(kept), len(languages), SIZE))
        place = np.full(mask + 1, -1, np.int64)
        place[kept] = np.arange(len(kept))
        for j, g in enumerate(languages):
            r = place[pairs[g] >> BITS]
            flatkey = (r * SIZE + (pairs[g] & (SIZE - 1)))[r >= 0]
            c = np.bincount(flatkey, minlength=len(kept) * SIZE).reshape(len(kept), SIZE)
            rows[:, j] = _escape(c, above[up, j])
        table.append(rows)
        here = here.copy()
        here[kept] = total + np.arange(len(kept))
        total += len(kept)
        parents = here
    node[:] = parents
    p = np.concatenate(table)
    cost = np.minimum(np.round(-np.log2(np.maximum(p, 1e-30)) * UNIT), 30000).astype(np.int16)
    return ContextTrees(languages, symbol, np.round(rare * UNIT).astype(np.int32), node, np.ascontiguousarray(cost.transpose(0, 2, 1).reshape(len(p) * SIZE, len(languages))), order)


def _escape(counts: np.ndarray, shorter: np.ndarray) -> np.ndarray:
    """Probabilities of a node's symbols from its counts and those of the shorter context."""
    n, d = counts.sum(axis=1, keepdims=True), (counts > 0).sum(axis=1, keepdims=True)
    rest = np.where(counts > 0, 0, shorter)
    mass = rest.sum(axis=1, keepdims=True)
    new = np.where(mass > 0, d / np.maximum(n + d, 1), 0)
    return np.where(n > 0, counts * (1 - new) / np.maximum(n, 1) + new * rest / np.where(mass > 0, mass, 1), shorter)


def code_lengths(model: ContextTrees, data: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Bits of each text in each language."""
    out = np.zeros((len(at) - 1, len(model.languages)))
    if not len(data) or not model.languages:
        return out
    s = model.symbol[data].astype(np.int32)
    context = np.zeros(len(s), np.int32)
    starts = at[:-1][np.diff(at) > 0]
    for k in range(1, model.order + 1):
        if len(s) > k:
            context[k:] |= s[:-k] << (BITS * (k - 1))
    for j in range(model.order):  # what lies before a text is zero
        p = starts + j
        p = p[p < len(s)]
        context[p] &= (1 << (BITS * j)) - 1
    at_node = model.node[context].astype(np.int64) * SIZE + s
    full = np.flatnonzero(np.diff(at) > 0)
    for j in range(len(model.languages)):
        bits = model.cost[:, j][at_node].astype(np.int64) if model.cost.ndim == 2 else 0
        odd = s == SIZE - 1
        if odd.any():
            bits[odd] += model.rare[data[odd], j]
        out[full, j] = np.add.reduceat(bits, at[:-1][full]) / UNIT
    return out


def _predictor(model):
    def predict(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trees: ContextTrees = model.value
        trees.cost = np.asfortranarray(trees.cost)
        for batch in batches:
            for part in pieces(batch, "text", 2 << 20):
                data, at = raw(part.column("text"))
                lettered = part.column("lettered").to_numpy(zero_copy_only=False).astype(bool)
                bits = code_lengths(trees, data, at)
                if trees.languages:
                    best = bits.argmin(axis=1)
                    gap = np.minimum((bits - bits.min(axis=1, keepdims=True)) * np.log(2), 700)
                    score = 1 / np.exp(-gap).sum(axis=1)
                    names = np.array(trees.languages, object)[best]
                else:
                    names, score = np.full(len(at) - 1, "und", object), np.zeros(len(at) - 1)
                names[~lettered] = "und"
                score = np.where(lettered & (names != "und"), score, 0.0)
                yield pa.RecordBatch.from_arrays([part.column("id"), pa.array(names, pa.string()), pa.array(score, pa.float64())], ["id", "lang_pred", "score"])

    return predict


def fit_rows(docs: DataFrame, labels: DataFrame, *, per_language: int = 600, sample_bytes: int = 4 << 20, order: int = 3, least: int = 24) -> ContextTrees:
    """From texts and the rows ``doc_id, lang`` to learn from."""
    taken: dict[str, list[bytes]] = {}
    room: dict[str, int] = {}
    for lang, text in labelled_sample(docs, labels, "lang", per_language).toLocalIterator():
        if room.get(lang, 0) < sample_bytes:
            taken.setdefault(lang, []).append(bytes(text))
            room[lang] = room.get(lang, 0) + len(text)
    return fit(taken, order=order, least=least)


def predict_languages(docs: DataFrame, model: ContextTrees, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id, lang_pred, score`` of every text."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    id_type = docs.schema[id_col].dataType.simpleString()
    lettered = F.coalesce(F.col(text_col).rlike(r"\p{L}"), F.lit(False))
    return docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"), lettered.alias("lettered")).mapInArrow(_predictor(shared), f"id {id_type}, lang_pred string, score double")


def op7_language_id(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = fit_rows(docs, docs.where(fold(F.col("doc_id"), 3) != 1))
    return predict_languages(docs.select("doc_id", "text"), model).select(F.col("id").alias("doc_id"), (fold(F.col("id"), 3) == 1).alias("held_out"), "lang_pred", "score")
