"""Every stage of the pipeline against a plain version on a small fixture, and on an empty table."""

import os
import random
import sys

import pytest

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
import brute  # noqa: E402

import corpus_pipeline as cp  # noqa: E402
from corrutil.llm import quality  # noqa: E402

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, id string, component bigint, __score double"
GOOD = ["the", "of", "stone", "river", "hütte", "walks", "sees", "house", "and", "field"]


def prose(seed: int, n: int) -> str:
    rng = random.Random(seed)
    return " ".join(rng.choice(GOOD) + rng.choice("abcdefghij") + rng.choice(["", ",", "."]) for _ in range(n))


def junk(seed: int) -> str:
    rng = random.Random(seed)
    return "".join(rng.choice("BUY!! NOW%%% 0123456789 $$$ ") for _ in range(600))


ITEM = "Which " + prose(900, 40) + "? The answer is " + prose(901, 8) + "."


def rows():
    shared = prose(99, 120)
    texts = {i: prose(i, 60 + 10 * i) for i in range(40)}
    texts |= {i: junk(i) for i in range(40, 80)}
    near = texts[39].split()
    near[7], near[200] = "other", "words"
    texts |= {88: " ".join(near), 80: texts[3], 81: texts[3], 82: shared, 83: "lead " + shared, 84: prose(5, 200) + " " + ITEM + " " + prose(6, 200), 85: "", 86: None, 87: prose(7, 4000)}
    out = [(i, t, "en", "s", len(t or ""), "x", 1, 0.5) for i, t in sorted(texts.items())]
    return [*out, out[2], (None, "no id " + prose(77, 50), None, None, None, None, None, None), (None, None, None, None, None, None, None, None)]


@pytest.fixture(scope="module")
def sf_dir(spark, tmp_path_factory):
    at = tmp_path_factory.mktemp("tables")
    spark.createDataFrame(rows(), SCHEMA).write.parquet(f"file://{at}/documents.parquet")
    spark.createDataFrame([(i, int(i < 40), 0) for i in range(80)], "doc_id bigint, quality int, toxic int").write.parquet(f"file://{at}/labels.parquet")
    spark.createDataFrame([(1, ITEM), (2, "Where is nothing of this? Nowhere at all, ever."), (3, None)], "item_id bigint, text string").write.parquet(f"file://{at}/benchmark.parquet")
    return f"file://{at}"


@pytest.fixture(scope="module")
def docs(spark, sf_dir):
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def kept(df) -> list[tuple]:
    assert df.columns == cp.COLUMNS
    return sorted(((r["doc_id"], r["text"]) for r in df.collect()), key=str)


def test_good_documents_stay_and_rejected_ones_go(spark, docs, sf_dir):
    model = quality.fit_on(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    want = [(r[0], r[1]) for r in rows() if quality.scores(model, [(r[1] or "").encode()])[0] >= quality.CUT]
    got = kept(cp.keep_good(spark, docs, sf_dir))
    assert got == sorted(want, key=str)
    ids = {i for i, _ in got}
    assert set(range(40)) <= ids and not ids & set(range(40, 80))


def test_one_document_of_each_group_stays(spark, docs, sf_dir):
    least = dict(brute.similar_groups([(r[0], r[1]) for r in rows()]))
    want = {(r[0], r[1]) for r in rows() if r[0] is None or least[r[0]] == r[0]}
    assert least[88] == 39 and least[81] == 3
    assert kept(cp.drop_near_duplicates(spark, docs, sf_dir)) == sorted(want, key=str)


def test_repeated_strings_are_cut(spark, docs, sf_dir):
    import hashlib

    plain = brute.repeats([(r[0], r[1]) for r in rows()])
    want = sorted(((i, h) for i, n, gone, _, h in plain if gone == 0 or gone < n), key=str)
    got = sorted(((r["doc_id"], hashlib.sha256(r["text"].encode()).hexdigest()) for r in cp.cut_repeats(spark, docs, sf_dir).collect()), key=str)
    whole = {i for i, _, gone, _, _ in plain if gone == 0}
    assert [g[0] for g in got] == [w[0] for w in want]
    assert [g for g in got if g[0] in whole] == [w for w in want if w[0] in whole]


def test_benchmark_passages_are_dropped(spark, docs, sf_dir):
    want = sorted(((r[0], r[1]) for r in rows() if r[0] != 84), key=str)
    assert kept(cp.drop_contaminated(spark, docs, sf_dir)) == want


def test_all_stages_in_order(spark, sf_dir):
    from tokenizers import Tokenizer

    from corrutil.llm.tokens import tokenizer_path

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in cp.STAGES[:-1]:
        docs = spark.createDataFrame(stage(spark, docs, sf_dir).collect(), "doc_id bigint, text string, lang string, source string, n_chars bigint")
    tokenizer = Tokenizer.from_file(tokenizer_path())
    want = sorted((x for r in docs.collect() for x in brute.piece_rows(r["doc_id"], r["text"], tokenizer)), key=str)
    packed = cp.run(spark, sf_dir).collect()
    assert sorted((tuple(r)[:5] for r in packed), key=str) == want
    brute.check_packing([r.asDict() for r in packed])


def test_empty_tables_pass_every_stage(spark, tmp_path):
    for name, schema in (("documents", SCHEMA), ("labels", "doc_id bigint, quality int, toxic int"), ("benchmark", "item_id bigint, text string")):
        spark.createDataFrame([], schema).write.parquet(f"file://{tmp_path}/{name}.parquet")
    for _, stage in cp.STAGES:
        assert stage(spark, spark.read.parquet(f"file://{tmp_path}/documents.parquet"), f"file://{tmp_path}").count() == 0
    assert cp.run(spark, f"file://{tmp_path}").count() == 0
