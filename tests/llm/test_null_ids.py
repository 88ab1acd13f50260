"""Strings of rows without an id, in crowded cores."""

import os
import random
import sys

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
import brute  # noqa: E402

from corrutil.llm import suffixdedup  # noqa: E402


def prose(seed: int, n: int) -> str:
    rng = random.Random(seed)
    return " ".join("".join(rng.choice("abcdefghij") for _ in range(5)) for _ in range(n))


def test_null_ids_in_a_crowded_core(spark):
    rows = [(None, prose(i, 40 + i) + " " + prose(99, 100) + " " + prose(20 + i, 30)) for i in range(3)]
    got = suffixdedup.remove_repeats(spark.createDataFrame(rows, "doc_id bigint, text string"), digest=True, crowd=1)
    assert sorted(tuple(r)[1:] for r in got.select("doc_id", "n_bytes", "n_removed", "n_spans", "kept").collect()) == sorted(r[1:] for r in brute.repeats(rows))
