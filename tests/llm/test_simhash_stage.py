"""The near-duplicate stage links by SimHash fingerprints, and by the similarity that these cannot tell."""

import random

import corpus_pipeline as cp
from corrutil.llm.simhash import fingerprint
from corrutil.llm.similar import shingle_set

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def prose(seed: int, n: int) -> list[str]:
    rng = random.Random(seed)
    return ["".join(rng.choice("abcdefghij") for _ in range(5)) for _ in range(n)]


def similarity(a: str, b: str) -> float:
    x, y = (set(shingle_set(t.encode(), 5).tolist()) for t in (a, b))
    return len(x & y) / len(x | y)


def test_fingerprints_and_similarity_are_joined(spark):
    # Three hundred copies of one sentence decide every bit; what follows them makes the sets unlike.
    base = " ".join(prose(1, 9) * 300)
    far = base + " " + " ".join(prose(2, 20))
    bits = (fingerprint(base.encode()) ^ fingerprint(far.encode())).bit_count()
    assert bits <= 2 and similarity(base, far) < 0.8
    # Like ``far`` in its words, unlike in how often they stand: only similarity links it.
    like = " ".join(prose(1, 9) * 2 + prose(2, 20))
    assert similarity(far, like) >= 0.8 and (fingerprint(far.encode()) ^ fingerprint(like.encode())).bit_count() > 2
    texts = {1: base, 2: far, 3: like, 4: " ".join(prose(3, 60)), 5: None, 6: ""}
    rows = [(i, t, "en", "s", len(t or "")) for i, t in texts.items()]
    got = {r["doc_id"] for r in cp.drop_near_duplicates(spark, spark.createDataFrame(rows, SCHEMA), "").collect()}
    assert got == {1, 4, 5}
