"""Queries that must give every window and every pattern length, against plain Python."""

import itertools
import os
from collections import defaultdict

import pytest

from corrutil import streaming
from corrutil.queries import MINED, QUERIES
from corrutil.types import least_utility
from corrutil.workloads import VIEWS

SF = "/root/testdata/sf0.001"


def all_patterns(rows, min_util: str, min_cor: float) -> dict:
    """Every subset of every transaction, counted; rows are (tid, item, u)."""
    baskets, alone = defaultdict(dict), defaultdict(int)
    for tid, item, u in rows:
        baskets[tid][item] = u
        alone[item] += 1
    least = least_utility(min_util, sum(u for _, _, u in rows))
    sup, util = defaultdict(int), defaultdict(int)
    for b in baskets.values():
        for k in range(1, len(b) + 1):
            for x in itertools.combinations(sorted(b), k):
                sup[x] += 1
                util[x] += sum(b[i] for i in x)
    value = {x: n * sum(1 / alone[i] for i in x) / len(x) for x, n in sup.items()}
    return {(",".join(x), len(x), n, util[x]): value[x] for x, n in sup.items() if util[x] >= least and value[x] >= min_cor - 1e-9}


def same(rows, want: dict) -> bool:
    got = {(r["pattern"], r["k"], r["sup"], r["utility"]): r["kulc"] for r in rows}
    return len(got) == len(rows) and got.keys() == want.keys() and all(abs(got[x] - want[x]) < 1e-6 for x in want)


@pytest.mark.skipif(not os.path.isdir(SF), reason="no test data")
def test_every_window_is_mined(spark):
    windows = defaultdict(list)
    for r in streaming.window_baskets(spark.read.parquet(f"{SF}/events.parquet")).collect():
        windows[r["start"]].append((r["tid"], r["item"], r["u"]))
    got = defaultdict(list)
    for r in QUERIES["stream_window_mine"](spark, SF).collect():
        got[r["start"]].append(r)
    assert len(windows) > 3 and set(got) == set(windows)
    for start, rows in windows.items():
        assert same(got[start], all_patterns(rows, "0.05", 0.3))


@pytest.mark.skipif(not os.path.isdir(SF), reason="no test data")
def test_simulated_quantities_and_profits_are_mined_whole(spark):
    rows = [(r["tid"], r["item"], r["u"]) for r in VIEWS["w6s"](spark, SF).rows.collect()]
    assert same(QUERIES["mine_simulated_w6"](spark, SF).collect(), all_patterns(rows, "0.001", 0.05))


@pytest.mark.skipif(not os.path.isdir(SF), reason="no test data")
def test_effort_in_sql_and_in_runs(spark):
    """On dense transactions each cut saves nodes, and the projection baseline keeps more than any variant; SQL counts the same."""
    import duckdb

    from corrutil.queries import ORACLE_SQL

    con = duckdb.connect()
    con.execute(f"CREATE VIEW benchmark AS SELECT * FROM '{SF}/benchmark.parquet'")
    columns = ["method", "min_util", "min_cor", "visited", "joined", "la_cut", "patterns", "tuples"]
    got = sorted(tuple(r) for r in QUERIES["variant_effort_w13"](spark, SF).select(*columns).collect())
    assert got == sorted(con.execute(f"SELECT {', '.join(columns)} FROM ({ORACLE_SQL['variant_effort_w13']})").fetchall())
    visited = {(m, u): v for m, u, _, v, *_ in got}
    for u in {u for _, u in visited}:
        assert visited["all", u] <= visited["ubu_spk", u] <= visited["ubu", u] <= visited["projection", u] and visited["ubu_la", u] <= visited["ubu", u]


CAPPED = {**{n: MINED[n][:3] for n in ("mine_w4", "mine_w8", "tags_w10", "conv_w11", "mine_w8_low", "labels_w12", "bench_w13")}, **{f"variant_{v}_w2": ("w2", "0.005", "0.1") for v in ("ubu", "ubu_spk", "ubu_la", "all")}}


@pytest.fixture(scope="module")
def long_tables(spark, tmp_path_factory):
    """Six items that meet often, so that patterns of every length up to six qualify."""
    at = tmp_path_factory.mktemp("long")
    words = "one three seven eleven twelve twenty".split()
    texts = [(i, " ".join(words if i < 9 else words[i % 6 :])) for i in range(12)]
    make = lambda name, rows, schema: spark.createDataFrame(rows, schema).write.parquet(f"file://{at}/{name}.parquet")
    make("documents", [(i, t, "en", "web", 9 + i) for i, t in texts], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    make("labels", [(i, q, 0) for i in range(9) for q in (0, 1)], "doc_id bigint, quality int, toxic int")
    make("benchmark", texts, "item_id bigint, text string")
    make("conversations", [(i, 0, "user", t) for i, t in texts], "conv_id bigint, turn int, role string, text string")
    make("pages", [(i, "u", "".join(f"<{w}>" for w in t.split())) for i, t in texts], "page_id bigint, url string, html string")
    make("part", [(i, f"Brand#{i}", 10.0 + i) for i in range(6)], "p_partkey bigint, p_brand string, p_retailprice double")
    make("lineitem", [(i, words.index(w), 2.0) for i, t in texts for w in t.split()], "l_orderkey bigint, l_partkey bigint, l_quantity double")
    make("orders", [(i, i) for i, _ in texts], "o_orderkey bigint, o_custkey bigint")
    return f"file://{at}"


@pytest.mark.parametrize("name", CAPPED)
def test_no_pattern_is_too_long(spark, long_tables, name):
    view, util, cor = CAPPED[name]
    rows = [(r["tid"], r["item"], r["u"]) for r in VIEWS[view](spark, long_tables).rows.collect()]
    want = all_patterns(rows, util, float(cor))
    assert max(x[1] for x in want) > 4, want.keys()
    assert same(QUERIES[name](spark, long_tables).collect(), want)
