"""SimHash near-duplicates, found with pivot distance tables.

A text's fingerprint has the majority of each bit over the 64-bit hashes of its word
shingles. Only distinct fingerprints are compared. Candidates share all bits of
``bands - radius`` of ``bands`` blocks: with at most ``radius`` differing bits that many blocks
are untouched, so no link is missed. Each fingerprint carries a table of its
Hamming distances to the ``PIVOTS`` reference fingerprints; in a block group a pair whose tables
differ anywhere by more than the radius cannot link and is discarded, and what
survives is verified bit by bit. A group never holds more than ``group_limit``
distinct fingerprints: the fingerprints of a larger one (thousands of near copies) go
through their one-bit neighbours instead. Two fingerprints are within two bits if and
only if they share one of these 65 keys, and no key has more than 65 holders,
so that path is as exact and needs no pairs at all.

Links are reduced to components over distinct fingerprints.

Edge cases: null and empty texts have fingerprint zero and link like any other; fewer
words than a shingle: the whole sequence is one; repeated rows stay and share a component;
a null id takes part, and is nobody's component id unless all ids are null. Other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .arrow import keyed, pieces, texts
from .components import components
from .scratch import discard, written

SHINGLE, SEED, RADIUS = 3, 42, 2
#: Reference fingerprints of the distance table: well-mixed words from a fixed rule.
PIVOTS = np.array([xxhash.xxh64_intdigest(f"pivot {i}".encode(), seed=SEED) for i in range(16)], np.uint64)


def shingle_hashes(text: bytes, words: int = SHINGLE) -> list[int]:
    """Hashes of the word shingles in their order, repeats included."""
    found = text.lower().split()
    if not found:
        return []
    joined = b" ".join(found)
    digest = xxhash.xxh64_intdigest
    if len(found) <= words:
        return [digest(joined, SEED)]
    ends = np.cumsum(np.fromiter(map(len, found), np.int64, len(found)) + 1) - 1
    starts = np.r_[0, ends[: -words] + 1].tolist()
    return [digest(joined[a:b], SEED) for a, b in zip(starts, ends[words - 1 :].tolist(), strict=True)]


def majority(hashes: list[int] | np.ndarray) -> int:
    """Bits that are set in over half of the hashes."""
    if not len(hashes):
        return 0
    bits = np.zeros(64, np.int64)
    wide = np.array(hashes, np.uint64).astype(">u8")
    for a in range(0, len(wide), 8192):
        bits += np.unpackbits(wide[a : a + 8192].view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * bits > len(wide)).tobytes(), "big")


def fingerprint(text: bytes, words: int = SHINGLE) -> int:
    return majority(shingle_hashes(text, words))


def _fingerprints(words: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in pieces(batch, "text", 2 << 20):
                prints = np.array([fingerprint(t, words) for t in texts(part.column("text"))], np.uint64).view(np.int64)
                yield pa.RecordBatch.from_arrays([part.column("id"), pa.array(prints, pa.int64())], ["id", "print"])

    return run


def fingerprints(docs: DataFrame, *, words: int = SHINGLE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id, print`` (the 64 bits as a signed integer) of every row."""
    id_type = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")).mapInArrow(_fingerprints(words), f"id {id_type}, print bigint")


def block_keys(bits: Column, radius: int = RADIUS, bands: int = 5) -> Column:
    """For each choice of untouched blocks, its number and the bits outside them set to zero, hashed."""
    edges = [64 * i // bands for i in range(bands + 1)]
    masks = []
    for kept in combinations(range(bands), bands - radius):
        m = sum(((1 << (edges[i + 1] - edges[i])) - 1) << edges[i] for i in kept)
        masks.append(m - (1 << 64) if m >> 63 else m)
    return F.array(*(F.xxhash64(F.lit(i), bits.bitwiseAND(F.lit(m))) for i, m in enumerate(masks)))


def linked_pairs(prints: np.ndarray, radius: int = RADIUS) -> np.ndarray:
    """Pairs of a group within the radius: pivot tables first, then the bits."""
    u = prints.view(np.uint64)
    table = np.bitwise_count(u[:, None] ^ PIVOTS[None, :]).astype(np.int8)
    out = []
    for i in range(len(u) - 1):
        near = np.flatnonzero(np.abs(table[i + 1 :] - table[i]).max(axis=1) <= radius) + i + 1
        near = near[np.bitwise_count(u[near] ^ u[i]) <= radius]
        if len(near):
            out.append(np.column_stack([np.full(len(near), prints[i]), prints[near]]))
    return np.concatenate(out) if out else np.zeros((0, 2), np.int64)


def _verify(radius: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            flat, at = batch.column("prints").flatten().to_numpy(), batch.column("prints").offsets.to_numpy()
            at = at - at[0]
            found = [linked_pairs(flat[a:b], radius) for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]
            pairs = np.unique(np.concatenate(found), axis=0) if found else np.zeros((0, 2), np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0], pa.int64()), pa.array(pairs[:, 1], pa.int64())], ["a", "b"])

    return run


def neighbour_links(prints: DataFrame) -> DataFrame:
    """Links within two bits through shared one-bit neighbours: a star for each key, no pairs."""
    flips = F.array(F.lit(0).cast("bigint"), *(F.lit((1 << i) - (1 << 64) if i == 63 else 1 << i).cast("bigint") for i in range(64)))
    keys = prints.select("print", F.explode(F.transform(flips, lambda m: F.col("print").bitwiseXOR(m))).alias("key"))
    stars = keys.groupBy("key").agg(F.collect_list("print").alias("held")).where("size(held) > 1")
    return stars.select(F.explode("held").alias("a"), F.array_min("held").alias("b")).where("a <> b").distinct()


def link(prints: DataFrame, *, radius: int = RADIUS, bands: int = 5, group_limit: int = 256) -> DataFrame:
    """Links ``a, b`` between distinct fingerprints (column ``print``), enough to give all components."""
    if radius > 2:
        raise ValueError("crowded groups are linked exactly up to radius 2")
    keys = prints.select("print", F.explode(block_keys(F.col("print"), radius, bands)).alias("key"))
    sizes = keys.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    shared = written(keys.join(sizes, "key").select("key", "print", "n"), "blocks")
    small = shared.where(F.col("n") <= group_limit).groupBy("key").agg(F.collect_list("print").alias("prints"))
    pairs = small.select("prints").mapInArrow(_verify(radius), "a bigint, b bigint")
    crowded = shared.where(F.col("n") > group_limit).select("print").distinct()
    # Two members of a crowded group are both in ``crowded``, so their link is found there.
    return pairs.unionByName(neighbour_links(crowded) if radius == 2 else _one_bit(crowded))


def _one_bit(prints: DataFrame) -> DataFrame:
    flips = F.array(*(F.lit((1 << i) - (1 << 64) if i == 63 else 1 << i).cast("bigint") for i in range(64)))
    near = prints.select(F.col("print").alias("a"), F.explode(F.transform(flips, lambda m: F.col("print").bitwiseXOR(m))).alias("b"))
    return near.join(prints.withColumnRenamed("print", "b"), "b", "left_semi").where("a > b").select("a", "b")


def near_duplicates(docs: DataFrame, *, words: int = SHINGLE, radius: int = RADIUS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id, print, component``: component is the smallest id of all documents that links reach."""
    prints = written(fingerprints(docs, words=words, id_col=id_col, text_col=text_col), "prints")
    classes = written(prints.groupBy("print").agg(F.min("id").alias("first")), "classes")
    roots = components(link(classes.select("print"), radius=radius))
    rooted = classes.join(roots.withColumnRenamed("node", "print"), "print", "left").select("print", "first", F.coalesce("root", "print").alias("root"))
    least = rooted.groupBy("root").agg(F.min("first").alias("component"))
    named = rooted.join(least, "root").select("print", "component")
    return prints.join(named, "print").select("id", "print", "component")


def op5_simhash(spark, sf_dir: str) -> DataFrame:
    found = near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return found.select(F.col("id").alias("doc_id"), F.lower(F.lpad(F.hex("print"), 16, "0")).alias("fingerprint"), F.col("component").alias("component_id"))
