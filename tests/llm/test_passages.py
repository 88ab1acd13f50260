"""Repeated passages of over 50 words that are shorter than the 400 bytes of the suffix operator."""

import random

import corpus_pipeline as cp
from corrutil.llm.passages import repeated_passages

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def prose(seed: int, n: int, size: int = 5) -> list[str]:
    rng = random.Random(seed)
    return ["".join(rng.choice("abcdefghij\u00fc") for _ in range(size)) for _ in range(n)]


def plain(texts: dict, words: int) -> dict:
    """Bytes of passages that occur again; the texts have single spaces and no punctuation."""
    seen: dict = {}
    for i, t in texts.items():
        w = t.split(" ")
        for p in range(len(w) - words + 1):
            seen.setdefault(" ".join(w[p : p + words]), []).append((i, len(" ".join(w[:p]).encode()) + (p > 0)))
    out: dict = {}
    for x, places in seen.items():
        for i, at in places if len(places) > 1 else []:
            out.setdefault(i, set()).update(range(at, at + len(x.encode())))
    return out


def fixture() -> dict:
    tiny, short, fifty, longer = prose(1, 51, 1), prose(2, 51), prose(3, 50), prose(4, 72, 3)
    texts = {}
    for n, passage in enumerate((tiny, short, fifty, longer)):
        for j in range(2):
            texts[2 * n + j] = " ".join(prose(100 + 10 * n + j, 90 + 31 * j) + passage + prose(200 + 10 * n + j, 40))
    texts[8] = " ".join(prose(300, 60) + longer[5:62] + prose(301, 9) + short)
    texts[9] = " ".join(prose(302, 500, 2) + prose(1, 51, 1))
    return texts


def test_bytes_of_short_passages(spark):
    texts = fixture()
    rows = [(i, t, "en", "s", len(t)) for i, t in texts.items()]
    got: dict = {}
    for r in repeated_passages(spark.createDataFrame(rows, SCHEMA), 51).collect():
        got.setdefault(r["doc_id"], set()).update(range(r["start"], r["stop"]))
    want = plain(texts, 51)
    assert got == want and set(want) == {0, 1, 2, 3, 6, 7, 8, 9}


def test_stage_cuts_short_passages(spark):
    texts = fixture()
    rows = [(i, t, "en", "s", len(t)) for i, t in texts.items()] + [(None, None, None, None, None)]
    gone = plain(texts, 51)
    want = {i: bytes(b for p, b in enumerate(t.encode()) if p not in gone.get(i, ())).decode() for i, t in texts.items()} | {None: ""}
    assert {r["doc_id"]: r["text"] for r in cp.cut_repeats(spark, spark.createDataFrame(rows, SCHEMA), "").collect()} == want


def test_shared_passage_is_opened_at_its_edges(spark, monkeypatch):
    """Texts that share a long passage: what is hashed passage by passage doesn't grow with its length."""
    from corrutil.llm import passages

    opened = {}

    def counted(df, name, write=passages.written):
        out = write(df, name)
        opened[name] = out.count()
        return out

    monkeypatch.setattr(passages, "written", counted)
    shared = prose(500, 600)
    texts = {i: " ".join(prose(600 + i, 30) + shared + prose(700 + i, 30)) for i in range(12)}
    got: dict = {}
    for r in passages.repeated_passages(spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in texts.items()], SCHEMA), 51).collect():
        got.setdefault(r["doc_id"], set()).update(range(r["start"], r["stop"]))
    assert got == plain(texts, 51)
    assert opened["passages"] < 12 * 2 * 110
