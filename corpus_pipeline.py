"""From raw documents to packed sequences: five stages, each an operator of ``corrutil.llm``.

Each stage takes the documents that its predecessor kept (as written Parquet) and returns
the columns of ``documents``; the last one returns the packing.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corrutil.llm import decontaminate, packing, quality, simhash, similar, suffixdedup
from corrutil.llm.scratch import written

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the compression classifier does not reject (score 0.3 or more)."""
    model = quality.fit_on(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    scored = quality.score_quality(docs.select(*COLUMNS), model)
    return scored.where(F.col("__score") >= quality.CUT).select(*COLUMNS)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group; the smallest id stays.

    Texts link if their SimHash fingerprints differ in two bits or fewer, found with pivot tables. Near copies that are further
    apart than fingerprints can tell are added: five-word shingles of a similarity of 0.8 or more. Groups are joined over both.
    Rows without an id have no place in a group and stay.
    """
    prints = simhash.near_duplicates(docs.select(F.xxhash64(F.coalesce(F.col("text").cast("string"), F.lit(""))).alias("mark"), "text"), id_col="mark")
    links = written(prints.where("id <> component").select(F.col("id").alias("a"), F.col("component").alias("b")).distinct(), "simhash-links")
    found = similar.similar_documents(docs, words=5, similarity=0.8, marks=True, links=links)
    leaders = found.where(F.col("id").isNotNull() & (F.col("id") != F.col("component"))).select(F.col("id").alias("doc_id"), "mark").distinct()
    marked = docs.select(*COLUMNS).withColumn("mark", F.xxhash64(F.coalesce(F.col("text").cast("string"), F.lit(""))))
    kept = marked.join(leaders, ["doc_id", "mark"], "left_anti")
    # Rows that repeat an id are copies of each other or nothing is known of them: equal rows count once.
    return kept.dropDuplicates(["doc_id", "text"]).select(*COLUMNS)


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Without the bytes of strings of 400, and of passages of over 50 words, that occur elsewhere; documents of which nothing is left go."""
    cut = suffixdedup.remove_repeats(docs.select(*COLUMNS), words=51)
    # What was empty before stays: only what this stage emptied goes.
    cut = cut.where((F.col("kept") != "") | (F.col("n_removed") == 0))
    return cut.select("doc_id", F.col("kept").alias("text"), "lang", "source", F.char_length("kept").cast("bigint").alias("n_chars")).select(*COLUMNS)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no item of the benchmark."""
    hits = decontaminate.contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    bad = hits.select(F.col("id").alias("__bad")).distinct()
    return docs.select(*COLUMNS).join(bad, F.col("doc_id").eqNullSafe(F.col("__bad")), "left_anti").select(*COLUMNS)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents in sequences of at most 2048 tokens."""
    return packing.pack(written(packing.cut_pieces(docs), "pieces")).select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")


STAGES = [
    ("quality classifier", keep_good),
    ("SimHash near-dedup", drop_near_duplicates),
    ("suffix-array dedup", cut_repeats),
    ("benchmark decontamination", drop_contaminated),
    ("best-fit packing", pack_sequences),
]

#: Scores, fingerprints, hashes of strings and tokens are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), "stage")
    return STAGES[-1][1](spark, docs, sf_dir)
