"""Every operator against brute force on a small fixture with nulls, empty and repeated rows, and on an empty table."""

import hashlib
import os
import random
import sys
import zlib

import pytest
from pyspark.sql import functions as F

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
import brute  # noqa: E402

from corrutil.llm import decontaminate, langid, media, packing, quality, simhash, suffixdedup, tokencount, urlfilter, warc  # noqa: E402
from corrutil.llm.scratch import new_path  # noqa: E402

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, part int, `key` string, id string"


def prose(seed: int, n: int) -> str:
    rng = random.Random(seed)
    return " ".join(rng.choice(["the", "of", "and", "to", "stone", "river", "hütte", "été", "walks", "sees"]) + rng.choice("abcdefghij") + rng.choice(["", ",", "."]) for _ in range(n))


def rows():
    passage = prose(99, 120)
    texts = [prose(i, 50 + 40 * i) for i in range(12)]
    texts += [texts[3], texts[3][:-5] + "zzzz", "x" + passage + "y", "q " + passage, "lead " + passage + " tail", None, "", " ", "a" * 3000, prose(5, 3000)]
    out = [(i, t, "en", "s", 1, 1, "k", "x") for i, t in enumerate(texts)]
    return [*out, out[2], (None, "no id here", None, None, None, None, None, None)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(rows(), SCHEMA).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def tuples(df, *cols):
    return sorted((tuple(r) for r in df.select(*cols).collect()), key=str)


def test_suffix_dedup(docs, empty):
    want = sorted(brute.repeats([(r[0], r[1]) for r in rows()]), key=str)
    for crowd in (suffixdedup.CROWD, 1):
        assert tuples(suffixdedup.remove_repeats(docs.select("doc_id", "text"), digest=True, crowd=crowd), "doc_id", "n_bytes", "n_removed", "n_spans", "kept") == want
    assert suffixdedup.remove_repeats(empty).count() == 0


def test_simhash(docs, empty):
    got = {r["id"]: (r["print"] & (1 << 64) - 1, r["component"]) for r in simhash.near_duplicates(docs).where("id IS NOT NULL").collect()}
    prints = [(r[0], brute.fingerprint(r[1])) for r in rows() if r[0] is not None]
    least = brute.groups(prints)
    assert got == {i: (p, least[i]) for i, p in prints}
    assert simhash.near_duplicates(empty).count() == 0


def test_crowded_groups_link_like_small_ones(spark):
    rng = random.Random(4)
    base = rng.getrandbits(64)
    prints = list({base ^ (1 << rng.randrange(64)) ^ (1 << rng.randrange(64)) ^ (1 << rng.randrange(64)) for _ in range(80)})
    df = spark.createDataFrame([(p - (1 << 64) if p >> 63 else p,) for p in prints], "print bigint")
    from corrutil.llm.components import components

    want = brute.groups(list(enumerate(prints)))
    groups = {frozenset(i for i in want if want[i] == k) for k in want.values()}
    for limit in (256, 4):
        roots = {r["node"] & (1 << 64) - 1: r["root"] for r in components(simhash.link(df, group_limit=limit)).collect()}
        found = [roots.get(p, p) for p in prints]
        assert {frozenset(i for i, f in enumerate(found) if f == k) for k in found} == groups


def test_packing_and_token_counts(docs, empty, spark):
    from tokenizers import Tokenizer

    from corrutil.llm.tokens import tokenizer_path

    tokenizer = Tokenizer.from_file(tokenizer_path())
    want = sorted((x for r in rows() for x in brute.piece_rows(r[0], r[1], tokenizer)), key=str)
    cut = packing.cut_pieces(docs).cache()
    assert tuples(cut, "doc_id", "piece", "start", "length", "ids_crc32") == want
    for target in (1 << 23, 3000):
        packed = packing.pack(cut, target_tokens=target)
        assert tuples(packed, "doc_id", "piece", "start", "length", "ids_crc32") == want
        assert brute.check_packing([r.asDict() for r in packed.collect()]) <= -(-sum(x[3] for x in want) // 2048) + 1
    assert packing.pack(packing.cut_pieces(empty)).count() == 0
    counts = sorted(((r[0], len(brute.token_bytes(r[1], tokenizer)) // 4) for r in rows()), key=str)
    path = tokencount.write_flat(docs, new_path(spark, "flat"))
    for block in (1 << 19, 97):
        assert tuples(tokencount.count_flat(spark, path, block_tokens=block), "label", "n_tokens") == counts


def test_lower_bound_never_exceeds_a_packing():
    import numpy as np

    rng = np.random.default_rng(1)
    for _ in range(200):
        lengths = rng.integers(1, 101, rng.integers(1, 40))
        bins, offsets, left = packing.best_fit(lengths, 100)
        assert packing.lower_bound(lengths, 100) <= len(left) and (left >= 0).all()
    assert packing.lower_bound(np.array([51, 51, 51]), 100) == 3


def test_media(docs, empty):
    found = media.image_features(media.store_images(docs))
    want = []
    for r in rows():
        b = (r[1] or "").encode()
        p = b + bytes(-len(b) % 64 or (0 if b else 64))
        want.append((r[0], len(b), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:])))
    assert tuples(found, "id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32") == sorted(want, key=str)
    assert media.image_features(media.store_images(empty)).count() == 0
    image = bytearray(media.png_encode(bytes(range(64)) * 3))
    image[-20] ^= 1
    with pytest.raises(ValueError):
        media.png_decode(bytes(image))


def test_language(spark, docs, empty):
    train = {"en": [b"the cat sat on the mat and the dog ran"] * 30, "de": ["der hund und die katze über dem haus".encode()] * 30}
    model = langid.fit(train, least=2)
    some = spark.createDataFrame([(1, "the dog sat"), (2, "die katze und der hund"), (3, None), (4, "123 !"), (5, "")], "doc_id bigint, text string")
    assert {r["id"]: r["lang_pred"] for r in langid.predict_languages(some, model).collect()} == {1: "en", 2: "de", 3: "und", 4: "und", 5: "und"}
    assert langid.predict_languages(docs, model).count() == len(rows())
    none = langid.fit_rows(empty, empty)
    assert {r["lang_pred"] for r in langid.predict_languages(docs, none).collect()} == {"und"}


def test_quality(spark, docs, empty):
    good, bad = [(1, prose(i, 80).encode()) for i in range(60)], [(0, ("BUY!! NOW%%% " * 30 + str(i)).encode()) for i in range(60)]
    model = quality.fit(good + bad)
    s = quality.scores(model, [prose(500, 60).encode(), b"BUY!! NOW%%% " * 20, b""])
    assert s[0] > 0.7 > 0.3 > s[1] and 0 <= s[2] <= 1
    assert quality.score_quality(docs, model).count() == len(rows())
    labels = spark.createDataFrame([], "doc_id bigint, quality int")
    assert {r["__score"] for r in quality.score_quality(docs, quality.fit_on(docs, labels)).collect()} == {0.5}


def test_warc(spark):
    pages = spark.createDataFrame([(1, "http://a/", "same"), (7, "http://b/", "same"), (3, None, "same"), (4, "u", None), (5, "u", ""), (6, "u", "é" * 5000), (6, "u", "é" * 5000)], "page_id bigint, url string, html string")
    path = warc.write_archives(pages, new_path(spark, "warc"))
    got = {(r["page_id"], r["payload_bytes"], r["record_type"], r["refers_to"]) for r in warc.read_archives(spark, path).collect()}
    assert got == {(1, 4, "revisit", 7), (3, 4, "revisit", 7), (7, 4, "response", None), (4, 0, "revisit", 5), (5, 0, "response", None), (6, 10000, "response", None)}
    assert {bytes(r["payload"]).decode() for r in warc.read_archives(spark, path).where("record_type = 'response'").collect()} == {"same", "", "é" * 5000}
    assert warc.read_archives(spark, warc.write_archives(pages.limit(0), new_path(spark, "warc"))).count() == 0


def test_urls(spark):
    urls = ["http://www.example.com/en/x", "http://EXAMPLE.com/en/", "http://a.b.example.com/fr?x", "http://example.com", "ftp://x.net/es/1#a", "net/es/", None, "", "http://com/", "http://notexample.com/en/", "http://example.com/en", "://", "a://b://c/"] * 2
    pages = [(i, u) for i, u in enumerate(urls)] + [(0, urls[0])]
    df = spark.createDataFrame(pages, "page_id bigint, url string")
    rules = spark.createDataFrame(urlfilter.RULES, "host string, path string, verdict string")
    got = tuples(urlfilter.judge_urls(df, rules), "page_id", "host", "path", "rule", "verdict")
    assert got == sorted(brute.urls(pages, urlfilter.RULES), key=str)
    plan = urlfilter.judge_urls(df, rules)._jdf.queryExecution().optimizedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_decontamination(spark, docs, empty):
    items = spark.createDataFrame([(1, prose(99, 120)[:300]), (2, "unseen words entirely. here they are"), (3, None), (4, "")], "item_id bigint, text string")
    for size in (16 << 20, 100):
        assert tuples(decontaminate.contaminated(docs, items, shard_bytes=size), "id", "item_id") == [(14, 1), (15, 1), (16, 1)]
    assert decontaminate.contaminated(empty, items).count() == 0 and decontaminate.contaminated(docs, items.limit(0)).count() == 0


def test_wand_finds_all_above_the_threshold():
    from collections import Counter

    rng = random.Random(2)
    texts = [(i, " ".join(rng.choice("abcdefghijklmnopqrst") for _ in range(rng.randint(3, 12)))) for i in range(150)]
    frequency = Counter(w for _, t in texts for w in set(t.split()))
    index = decontaminate.BlockMaxIndex(texts, len(texts), 8.0, frequency)
    for _ in range(60):
        query = [index.terms[w] for w in rng.sample("abcdefghijklmnopqrst", 6)]
        scores = Counter()
        for t in query:
            for d, v in zip(index.items[t].tolist(), index.impacts[t].tolist(), strict=True):
                scores[d] += v
        for least in (0.3, 0.6):
            assert {d for d, _ in index.retrieve(query, least)} == {d for d, v in scores.items() if v >= least - 1e-12}
