"""Rows that repeat an id with another text."""

import random

import corpus_pipeline as cp


def prose(seed: int, n: int) -> str:
    rng = random.Random(seed)
    return " ".join("".join(rng.choice("abcdefghij") for _ in range(5)) for _ in range(n))


def test_other_text_of_a_repeated_id_stays(spark):
    rows = [(i, t, "en", "s", len(t)) for i, t in ((1, prose(1, 80)), (2, prose(1, 80)), (2, prose(2, 80)))]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    got = sorted((r["doc_id"], r["text"]) for r in cp.drop_near_duplicates(spark, docs, "").collect())
    assert got == [(1, prose(1, 80)), (2, prose(2, 80))]
