"""Benchmark decontamination with a BM25 inverted index and block-max WAND.

The test items are indexed with normalised impacts: a term's BM25 weight in an item over
the item's score for its own text, so a passage that holds the whole item scores 1.
Postings are cut into blocks that carry their largest impact. Every position of every
document is covered by passages; ``BlockMaxIndex.retrieve`` gives all items at or above the
threshold by WAND with block maxima. Which passages need the walk at all is decided for
a whole batch at once: an item's frequent terms can add no more than their sum, so
its rare terms must reach the rest of the threshold within a window; the impacts of
rare terms along a document are summed over such windows, and a passage that stays below
for every item cannot score the threshold. Hits are verified by word 5-gram
containment of the item's question and answer.

Items are indexed in shards of at most ``shard_bytes`` of text, one pass over the documents for
each, with document frequencies counted over all items; so what is broadcast is bounded.

Edge cases: items without words are skipped, items of fewer words than a shingle
are one shingle; null and empty texts have no hit; repeated rows of items count once, of
documents as often as they are; empty tables give no rows.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .arrow import pieces

K1, B = 1.2, 0.75
THRESHOLD, OVERLAP, SHINGLE = 0.5, 0.8, 5
#: Terms in at most this share of the items (or in ``RARE_LEAST`` items) are rare.
RARE_SHARE, RARE_LEAST = 0.02, 4
BLOCK = 64
_WORD = re.compile(r"\w+")


def words(text: str | None) -> list[str]:
    return _WORD.findall(text.lower()) if text else []


def question_answer(text: str) -> tuple[str, str]:
    """An item up to its last question mark and what follows; without one, all but the last sentence and that one."""
    cut = text.rfind("?")
    if 0 <= cut < len(text.rstrip()) - 1:
        return text[: cut + 1], text[cut + 1 :]
    body = text.rstrip().rstrip(".!?")
    cut = max(body.rfind(m) for m in (". ", "! ", "? ", ".\n"))
    return (text[: cut + 1], text[cut + 1 :]) if cut > 0 else (text, "")


def shingles(found: list[str]) -> set[tuple[str, ...]]:
    n = min(SHINGLE, len(found))
    return {tuple(found[i : i + n]) for i in range(len(found) - n + 1)} if found else set()


class BlockMaxIndex:
    """Items and their postings, by term."""

    def __init__(self, items: list[tuple[int | None, str]], total: int, mean_words: float, frequency: dict[str, int]) -> None:
        self.ids = [i for i, _ in items]
        found = [words(t) for _, t in items]
        self.lengths = np.array([len(x) for x in found], np.int64)
        self.parts = [tuple(shingles(words(p)) for p in question_answer(t)) for _, t in items]
        self.whole = [shingles(x) for x in found]
        postings: dict[str, list[tuple[int, float]]] = {}
        for d, x in enumerate(found):
            raw = {w: self._idf(total, frequency[w]) * n * (K1 + 1) / (n + K1 * (1 - B + B * len(x) / mean_words)) for w, n in Counter(x).items()}
            own = sum(raw.values())
            for w, v in raw.items():
                postings.setdefault(w, []).append((d, v / own))
        self.terms = {w: i for i, w in enumerate(postings)}
        self.items = [np.array([d for d, _ in p], np.int64) for p in postings.values()]
        self.impacts = [np.array([v for _, v in p]) for p in postings.values()]
        self.most = np.array([v.max() for v in self.impacts]) if postings else np.zeros(0)
        self.blocks = [np.maximum.reduceat(v, np.arange(0, len(v), BLOCK)) for v in self.impacts]
        rare = max(RARE_LEAST, int(RARE_SHARE * total))
        self.rare = np.array([frequency[w] <= rare for w in postings], bool)
        self.frequent_sum = np.zeros(len(items))
        for t in np.flatnonzero(~self.rare):
            np.add.at(self.frequent_sum, self.items[t], self.impacts[t])
        # Postings of the rare terms in flat form, for the batch-wise bound.
        sizes = np.array([len(p) if r else 0 for p, r in zip(self.items, self.rare, strict=True)], np.int64)
        self.rare_at = np.r_[0, np.cumsum(sizes)]
        pick = [t for t in range(len(sizes)) if sizes[t]]
        self.rare_item = np.concatenate([self.items[t] for t in pick]) if pick else np.zeros(0, np.int64)
        self.rare_impact = np.concatenate([self.impacts[t] for t in pick]) if pick else np.zeros(0)

    @staticmethod
    def _idf(total: int, n: int) -> float:
        return math.log(1 + (total - n + 0.5) / (n + 0.5))

    def retrieve(self, query: list[int], threshold: float) -> list[tuple[int, float]]:
        """All items whose summed impacts over the distinct query terms reach the threshold."""
        cursor = {t: 0 for t in set(query)}
        out = []
        while cursor:
            live = sorted(cursor, key=lambda t: self.items[t][cursor[t]])
            bound, pivot = 0.0, None
            for k, t in enumerate(live):
                bound += self.most[t]
                if bound >= threshold - 1e-12:
                    pivot = k
                    break
            if pivot is None:
                break
            at = self.items[live[pivot]][cursor[live[pivot]]]
            while pivot + 1 < len(live) and self.items[live[pivot + 1]][cursor[live[pivot + 1]]] == at:
                pivot += 1
            ahead = live[: pivot + 1]
            tight, edge = 0.0, None
            for t in ahead:  # the blocks in which the pivot item would be
                p = int(np.searchsorted(self.items[t], at))
                if p < len(self.items[t]):
                    b = p // BLOCK
                    tight += self.blocks[t][b]
                    last = int(self.items[t][min(len(self.items[t]), (b + 1) * BLOCK) - 1])
                    edge = last if edge is None else min(edge, last)
            if tight >= threshold - 1e-12:
                if self.items[live[0]][cursor[live[0]]] == at:
                    score = float(sum(self.impacts[t][cursor[t]] for t in ahead))
                    if score >= threshold - 1e-12:
                        out.append((int(at), score))
                    goal = at + 1
                else:
                    goal = at
            else:
                beyond = int(self.items[live[pivot + 1]][cursor[live[pivot + 1]]]) if pivot + 1 < len(live) else None
                goal = max(at + 1, (edge if edge is not None else int(at)) + 1)
                if beyond is not None:
                    goal = max(at + 1, min(goal, beyond))
            for t in ahead:
                p = int(np.searchsorted(self.items[t], goal))
                if p < len(self.items[t]):
                    cursor[t] = max(cursor[t], p)
                else:
                    del cursor[t]
        return out

    def windows(self) -> np.ndarray:
        """Words that a passage for each item has."""
        return np.maximum(64, np.ceil(1.25 * self.lengths)).astype(np.int64)

    def suspects(self, terms: np.ndarray, at: np.ndarray, threshold: float) -> list[tuple[int, int, int]]:
        """(text, first word, last word + 1) of passages in which some item's bound reaches the threshold.

        ``terms``: the term of each word of a batch of texts, or -1; ``at``: where each text begins.
        """
        hit = np.flatnonzero(terms >= 0)
        hit = hit[self.rare[terms[hit]]] if len(self.rare) else hit[:0]
        n = self.rare_at[terms[hit] + 1] - self.rare_at[terms[hit]]
        place = np.repeat(hit, n)
        if not len(place):
            return self._frequent_only(at, threshold)
        first = np.repeat(self.rare_at[terms[hit]] - np.r_[0, np.cumsum(n)[:-1]], n) + np.arange(len(place))
        item, impact = self.rare_item[first], self.rare_impact[first]
        text = np.searchsorted(at, place, side="right") - 1
        order = np.lexsort((place, text, item))
        item, impact, place, text = item[order], impact[order], place[order], text[order]
        total = np.r_[0, np.cumsum(impact)]
        # Positions of one (item, text) are kept apart from the next by more than any window.
        step = int(at[-1]) + int(self.windows().max()) + 1
        group = np.cumsum(np.r_[0, (item[1:] != item[:-1]) | (text[1:] != text[:-1])])
        key = group * step + place
        stop = np.searchsorted(key, key + self.windows()[item])
        near = total[stop] - total[np.arange(len(key))] + self.frequent_sum[item] >= threshold - 1e-9
        out: dict[tuple[int, int], list[list[int]]] = {}
        for d, x, p in zip(item[near].tolist(), text[near].tolist(), place[near].tolist(), strict=True):
            a, b = max(int(at[x]), p - int(self.lengths[d])), min(int(at[x + 1]), p + int(self.windows()[d]))
            runs = out.setdefault((x, d), [])
            if runs and a <= runs[-1][1]:
                runs[-1][1] = b
            else:
                runs.append([a, b])
        return self._frequent_only(at, threshold) + [(x, a, b) for (x, _), runs in out.items() for a, b in runs]

    def _frequent_only(self, at: np.ndarray, threshold: float) -> list[tuple[int, int, int]]:
        """Where frequent terms alone can reach the threshold (items of nothing else), every passage is walked."""
        odd = np.flatnonzero(self.frequent_sum >= threshold - 1e-9)
        if not len(odd):
            return []
        w = int(self.windows()[odd].max())
        return [(x, a, min(a + 2 * w, int(at[x + 1]))) for x in range(len(at) - 1) for a in range(int(at[x]), int(at[x + 1]), w)]


def _search(shared, threshold: float, overlap: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index: BlockMaxIndex = shared.value
        term = index.terms.get
        for batch in batches:
            for part in pieces(batch, "text", 2 << 20):
                split = [words(t) for t in part.column("text").to_pylist()]
                at = np.r_[0, np.cumsum([len(x) for x in split])]
                terms = np.fromiter((term(w, -1) for x in split for w in x), np.int64, int(at[-1]))
                best: dict[tuple[int, int], tuple] = {}
                for x, a, b in index.suspects(terms, at, threshold):
                    known = terms[a:b]
                    hits = index.retrieve(known[known >= 0].tolist(), threshold)
                    here = shingles_of(split[x][a - int(at[x]) : b - int(at[x])]) if hits else {}
                    for d, score in hits:
                        share = [len(s & here[min(SHINGLE, max(map(len, s)))]) / len(s) if s else None for s in (index.whole[d], *index.parts[d])]
                        whole, question, answer = share
                        if whole >= overlap or (question is not None and question >= overlap and (answer is None or answer >= overlap)):
                            row = (whole, score, question, answer, a - int(at[x]), b - int(at[x]))
                            if (x, d) not in best or best[x, d] < row:
                                best[x, d] = row
                keys = sorted(best)
                rows = [best[k] for k in keys]
                kinds = [("score", 1, pa.float64()), ("overlap", 0, pa.float64()), ("question_overlap", 2, pa.float64()), ("answer_overlap", 3, pa.float64()), ("first_word", 4, pa.int64()), ("last_word", 5, pa.int64())]
                yield pa.RecordBatch.from_arrays(
                    [part.column("id").take(pa.array([x for x, _ in keys], pa.int64())), pa.array([index.ids[d] for _, d in keys], pa.int64()), *(pa.array([r[i] for r in rows], t) for _, i, t in kinds)],
                    ["id", "item_id", *(n for n, _, _ in kinds)],
                )

    return run


class shingles_of(dict):
    """A passage's shingles by their number of words, made when first asked for."""

    def __init__(self, found: list[str]) -> None:
        self.found = found

    def __missing__(self, n: int) -> set[tuple[str, ...]]:
        self[n] = {tuple(self.found[i : i + n]) for i in range(len(self.found) - n + 1)}
        return self[n]


def _item_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        found = [words(t) for t in batch.column("text").to_pylist()]
        rows = [(w, len(x) if k == 0 else 0, int(k == 0)) for x in found for k, w in enumerate(dict.fromkeys(x))]
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.string(), pa.int64(), pa.int64()))], ["word", "n", "item"])


def indexes(items: DataFrame, *, shard_bytes: int = 16 << 20) -> Iterator[BlockMaxIndex]:
    """Indexes of bounded shards of the items (``item_id, text``), with statistics of all of them."""
    items = items.select(F.col("item_id").cast("bigint").alias("item_id"), "text").where(F.col("text").isNotNull()).distinct()
    counted = items.select("text").mapInArrow(_item_words, "word string, n bigint, item bigint")
    total, length, size = counted.agg(F.coalesce(F.sum("item"), F.lit(0)), F.coalesce(F.sum("n"), F.lit(0))).crossJoin(items.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0)))).first()
    if not total:
        return
    shards = max(1, math.ceil(size / shard_bytes))
    frequency = counted.groupBy("word").count()
    for k in range(shards):
        part = items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(shards)) == k)
        rows = sorted(((r[0], r[1]) for r in part.toLocalIterator()), key=lambda r: (r[0] is None, r[0] or 0, r[1]))
        rows = [r for r in rows if words(r[1])]
        here = part.select("text").mapInArrow(_item_words, "word string, n bigint, item bigint").select("word").distinct()
        found = {w: n for w, n in frequency.join(here, "word", "left_semi").toLocalIterator()}
        if rows:
            yield BlockMaxIndex(rows, total, length / total, found)


def contaminated(docs: DataFrame, items: DataFrame, *, threshold: float = THRESHOLD, overlap: float = OVERLAP, id_col: str = "doc_id", text_col: str = "text", shard_bytes: int = 16 << 20) -> DataFrame:
    """``id, item_id, score, overlap, question_overlap, answer_overlap, first_word, last_word`` of verified hits.

    One row for each document row and item, with the passage that holds most of the item.
    """
    spark = docs.sparkSession
    id_type = docs.schema[id_col].dataType.simpleString()
    schema = f"id {id_type}, item_id bigint, score double, overlap double, question_overlap double, answer_overlap double, first_word bigint, last_word bigint"
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    out = None
    for index in indexes(items, shard_bytes=shard_bytes):
        found = rows.mapInArrow(_search(spark.sparkContext.broadcast(index), threshold, overlap), schema)
        out = found if out is None else out.unionByName(found)
    return spark.createDataFrame([], schema) if out is None else out


def op1_decontaminate(spark, sf_dir: str) -> DataFrame:
    docs, items = spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    return contaminated(docs, items).withColumnRenamed("id", "doc_id")
