"""op4 notes passages of over 50 words that its strings of 400 bytes can't show, and removes what its contract names only."""

import os
import sys

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
import brute  # noqa: E402
from test_passages import SCHEMA, fixture, plain, prose  # noqa: E402

from corrutil.llm.queries import QUERIES  # noqa: E402


def test_op4_notes_short_passages(spark, tmp_path):
    texts = fixture()
    planted, copy = prose(801, 53), " ".join(prose(802, 120))
    for i in range(20, 24):
        texts[i] = " ".join(prose(810 + i, 80) + planted + prose(830 + i, 80))
    texts |= {30: copy, 31: copy, 40: " ".join(prose(803, 300)), 41: " ".join(prose(804, 50)), 42: ""}
    rows = [(i, t, "en", "s", len(t)) for i, t in texts.items()] + [(43, None, "en", "s", 0)]
    spark.createDataFrame(rows, SCHEMA).write.parquet(f"{tmp_path}/documents.parquet")
    got = {r["doc_id"]: r for r in QUERIES["op4_suffix_dedup"](spark, str(tmp_path)).collect()}
    want = {r[0]: r for r in brute.repeats([r[:2] for r in rows])}
    assert {i: tuple(r)[:5] for i, r in got.items()} == want
    noted = plain(texts, 51)
    assert {i: r["n_passage_bytes"] for i, r in got.items()} == {i: len(noted.get(i, ())) for i in want}
    assert all(want[i][2] == 0 < got[i]["n_passage_bytes"] for i in range(20, 24))
    assert got[30]["n_passage_bytes"] == len(copy.encode())
    assert not any(got[i]["n_passage_bytes"] for i in (4, 5, 40, 41, 42, 43))


def test_rows_without_ids_and_repeated_ids(spark):
    from corrutil.llm import suffixdedup

    planted = prose(841, 51)
    texts = [" ".join(prose(850 + i, 20) + planted + prose(860 + i, 20)) for i in range(3)] + [" ".join(prose(870, 90))]
    rows = list(zip((None, None, 7, 7), texts, strict=True))
    got = suffixdedup.remove_repeats(spark.createDataFrame(rows, "doc_id bigint, text string"), digest=True, note_words=51).collect()
    size = len(" ".join(planted).encode())
    assert {r["text"]: (r["doc_id"], r["n_removed"], r["n_passage_bytes"]) for r in got} == {t: (i, 0, size if t != texts[3] else 0) for i, t in rows}
    empty = spark.createDataFrame([], "doc_id bigint, text string")
    assert suffixdedup.remove_repeats(empty, digest=True, note_words=51).count() == 0
