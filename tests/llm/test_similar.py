"""Near copies of a stated similarity against a comparison of all pairs."""

import os
import random
import sys

import pytest

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
import brute  # noqa: E402

from corrutil.llm import similar  # noqa: E402

WORDS = [a + b for a in ("sto", "riv", "hüt", "wal", "fie", "sky") for b in ("ne", "er", "te", "ks", "ld", "x", "ra")]


def prose(seed: int, n: int) -> list[str]:
    rng = random.Random(seed)
    return [rng.choice(WORDS) for _ in range(n)]


def edited(words: list[str], seed: int, edits: int) -> str:
    rng, out = random.Random(seed), list(words)
    for at in rng.sample(range(len(out)), edits):
        out[at] = f"edit{seed}"
    return " ".join(out)


def table() -> list[tuple]:
    base, other = prose(1, 300), prose(2, 120)
    rows = [(i, " ".join(prose(100 + i, 80))) for i in range(40)]
    rows += [(100 + i, edited(base, i, 1 + i % 8)) for i in range(60)]  # most within 0.8 of each other, some only through others
    rows += [(200 + i, edited(other, i, i)) for i in range(12)]  # from copies to beyond the threshold
    rows += [(300, " ".join(other)), (301, " ".join(other).upper()), (302, "two words"), (303, "Two\tWORDS"), (304, "two words more"), (305, ""), (306, None), (307, " \n ")]
    # Four of five shingles shared is 0.8 exactly; three of four is less.
    rows += [(400, "a b c d e f g h"), (401, "a b c d e f g h i"), (402, "q r s t u v w"), (403, "q r s t u v w x")]
    rows += [rows[3], rows[45], (None, " ".join(other)), (None, None), (500, " ".join(prose(7, 30_000)))]
    return rows


@pytest.mark.parametrize("group", [similar.GROUP, 7])
def test_components_equal_all_pairs(spark, group):
    rows = table()
    docs = spark.createDataFrame([(i, t, "x", 3, 4) for i, t in rows], "doc_id bigint, text string, id string, component int, key int")
    got = sorted(((r["id"], r["component"]) for r in similar.similar_documents(docs, group=group).collect()), key=str)
    assert got == sorted(brute.similar_groups(rows), key=str)


def test_buckets_hold_pairs_at_the_threshold():
    base = prose(5, 400)
    for seed in range(200):
        a = similar.shingle_set(" ".join(base).encode(), 5)
        b = similar.shingle_set(edited(base, seed, 8).encode(), 5)
        both = len(set(a.tolist()) & set(b.tolist()))
        assert both >= 0.8 * (len(a) + len(b) - both)
        assert set(similar.bucket_keys(a).tolist()) & set(similar.bucket_keys(b).tolist())


def test_empty_table(spark):
    assert similar.similar_documents(spark.createDataFrame([], "doc_id bigint, text string")).count() == 0


def test_sketches_keep_what_links_and_discard_what_does_not():
    import numpy as np
    import pyarrow as pa

    base = prose(8, 1500)
    bodies = [" ".join(base).encode()] + [edited(base, s, 10 * s).encode() for s in range(1, 30)] + [edited(base[:200], s, s % 9).encode() for s in range(30, 60)] + [b"", b"one"]
    sets = [similar.shingle_set(b, 5) for b in bodies]
    batch = pa.RecordBatch.from_arrays([pa.array(range(len(bodies)), pa.int64()), pa.array([b.decode() for b in bodies])], ["mark", "text"])
    sketches = similar.Sketches(pa.concat_arrays([b.column("sketch") for b in similar._sketches(5)([batch])]))
    for i, a in enumerate(sets):
        may = sketches.may_link(i, 0.8)
        for j, b in enumerate(sets):
            both = len(np.intersect1d(a, b))
            share = both / max(len(a) + len(b) - both, 1)
            assert may[j] or share < 0.8
            assert not (may[j] and share < 0.6)
