"""Texts that repeat themselves in short periods: whole results, and no row for each byte or word."""

import random

import pytest

from corrutil.llm import passages, suffixdedup

SCHEMA = "doc_id bigint, text string"


def prose(seed: int, n: int) -> str:
    rng = random.Random(seed)
    return "".join(rng.choice("abcdefghij ü") for _ in range(n))


def unit(period: int) -> str:
    return "a" if period == 1 else prose(period, period - 1) + "."


def texts() -> dict:
    """Single runs, runs with edges, a run that two texts share, and two texts of which one follows the other's period for a while."""
    out = {p: prose(900 + p, 150) + unit(p) * (4000 // p) + prose(950 + p, 180) for p in (1, 2, 7, 150, 300, 900)}
    out[20] = "b" * 400
    out[21] = "c" * 401
    out[22] = out[7][100:2500] + prose(1, 500)
    out[23] = prose(2, 300) + unit(300) * 3 + prose(3, 30)
    out[24] = prose(2, 300) + unit(300) * 2 + prose(4, 700)
    out[25] = out[24]
    return out


def removed(spans: list) -> dict:
    out: dict = {}
    for r in spans:
        out.setdefault(r["doc_id"], set()).update(range(r["start"], r["stop"]))
    return out


def plain(data: dict, size: int = 400) -> dict:
    places: dict = {}
    for i, t in data.items():
        b = t.encode()
        for p in range(len(b) - size + 1):
            places.setdefault(b[p : p + size], []).append((i, p))
    out: dict = {}
    for found in places.values():
        for i, p in found if len(found) > 1 else []:
            out.setdefault(i, set()).update(range(p, p + size))
    return out


def counted(monkeypatch, module) -> dict:
    sizes: dict = {}

    def write(df, name, real=module.written):
        out = real(df, name)
        sizes[name] = out.count()
        return out

    monkeypatch.setattr(module, "written", write)
    return sizes


@pytest.mark.parametrize("parts, closing", [(1, 1), (1, 1 << 40), (3, 4)])
def test_removed_bytes(spark, monkeypatch, parts, closing):
    """Chunks of one anchor, of a few, and of a whole text."""
    def chunked(batches):
        from corrutil.llm import suffixdedup as there  # that of the worker

        usual, there.CHUNK_ANCHORS = there.CHUNK_ANCHORS, closing
        try:
            yield from there._chunk_rows(batches)
        finally:
            there.CHUNK_ANCHORS = usual

    monkeypatch.setattr(suffixdedup, "_chunk_rows", chunked)
    sizes = counted(monkeypatch, suffixdedup)
    data = texts()
    docs = spark.createDataFrame(list(data.items()), SCHEMA).repartition(parts)
    assert removed(suffixdedup.repeated_spans(docs).collect()) == plain(data)
    # "a" and the period of two alone have over 7,000 anchors.
    assert sizes["shared-anchors"] < 500 and sizes["chunks"] < 1000


def test_passages(spark, monkeypatch):
    sizes = counted(monkeypatch, passages)
    rng = random.Random(5)
    words = lambda n: " ".join("".join(rng.choice("abcdefg") for _ in range(4)) for _ in range(n))
    data = {1: f"{words(40)} {'the ' * 900}{words(40)}", 2: f"{words(9)} {'so it is ' * 300}{words(60)}", 3: f"{words(30)} {'the ' * 70}{words(30)}", 4: words(200), 5: "no " * 51, 6: "yes " * 52}
    got = removed(passages.repeated_passages(spark.createDataFrame(list(data.items()), SCHEMA).coalesce(1), 51).collect())
    places: dict = {}
    for i, t in data.items():
        w = t.split()
        for p in range(len(w) - 50):
            places.setdefault(tuple(w[p : p + 51]), []).append((i, len(" ".join(w[:p])) + (p > 0), len(" ".join(w[: p + 51]))))
    want: dict = {}
    for found in places.values():
        for i, a, b in found if len(found) > 1 else []:
            want.setdefault(i, set()).update(range(a, b))
    assert got == want and set(want) == {1, 2, 3, 6}
    assert sizes["passage-runs"] < 150
