"""Bounded, repeatable samples of labelled rows for fitting."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def fold(doc_id: Column, n: int) -> Column:
    """crc32 of the id's decimal digits modulo n; a null id is in fold 0."""
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(n)), F.lit(0)).cast("int")


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, limit: int, *, max_labels: int = 64) -> DataFrame:
    """``label, text`` of at most ``limit`` documents of each label, those with the least hash of their id.

    ``labels``: ``doc_id, <label>``. Only ids are ranked; at most ``limit * max_labels`` of them are broadcast
    to the scan of the texts: of more labels than ``max_labels`` each has fewer documents (one
    at least), none is left out. Ids whose hash is far beyond a label's share are dropped before any are
    ranked, so ranking sees about ``3 * limit + 50`` of each label at any size.
    """
    one = labels.where(F.col("doc_id").isNotNull() & F.col(label).isNotNull()).select("doc_id", label).dropDuplicates(["doc_id"])
    different = one.agg(F.countDistinct(label)).first()[0]
    limit = max(1, min(limit, limit * max_labels // max(1, different)))
    top = one.groupBy(label).count().select(label, F.least(F.lit(1.0), (3.0 * limit + 50) / F.col("count")).alias("__share"))
    w = Window.partitionBy(label).orderBy(F.xxhash64("doc_id"), "doc_id")
    near = F.xxhash64("doc_id") / float(1 << 64) + 0.5 <= F.col("__share")
    ids = one.join(top, label).where(near).withColumn("__k", F.row_number().over(w)).where(F.col("__k") <= limit).select("doc_id", label)
    texts = docs.where(F.col("text").isNotNull()).select("doc_id", F.col("text").cast("binary").alias("text"))
    return texts.join(F.broadcast(ids), "doc_id").orderBy(F.xxhash64("doc_id"), F.xxhash64("text")).select(label, "text")
