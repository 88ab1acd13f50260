"""Queries against DuckDB, streams against batches, sources and plans."""

import os

import pytest
from pyspark.sql import functions as F

import __spark_entry__
from corrutil import sources, streaming
from corrutil.queries import ORACLE_SQL, QUERIES
from corrutil.workloads import VIEWS

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: One of each kind; the driver compares all.
CHECKED = ["item_rank_w3", "remaining_utility_w3", "pair_la_bound_w3", "pair_kulc_w3", "mine_w1", "mine_w3", "mine_levels_w3", "mine_w7", "plain_w3", "plain_projected_w3", "two_phase_w3", "tree_growth_w3", "projection_w3", "projection_candidates_w3", "affinity_w3", "grid_monotone_w3", "class_overlap_w3", "closed_w3", "maximal_w3", "recommend_w3", "measures_w3", "rules_w3", "utility_sets", "class_counts_w3a", "class_overlap_all_w3", "exactness_w3", "affinity_of_patterns_w3", "top_k_by_lift_w3", "utility_share_w3", "segment_mine_w3", "bench_w13", "mine_lists_w4", "mine_hybrid_w2", "stream_item_twu_day", "stream_window_mine", "stream_session_baskets", "stream_item_stats_sliding"]

pytestmark = pytest.mark.skipif(not os.path.isdir(SF), reason="no test data")


@pytest.fixture(scope="module")
def duck():
    import duckdb

    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


def plain(rows):
    return sorted(str([round(float(v), 6) if isinstance(v, float) else None if v is None else str(v) for v in r]) for r in rows)


@pytest.mark.parametrize("name", CHECKED)
def test_query(spark, duck, name):
    got = QUERIES[name](spark, SF)
    cols = sorted(got.columns)
    want = duck.execute(ORACLE_SQL[name])
    place = [d[0] for d in want.description]
    assert sorted(place) == cols
    assert plain(got.select(*cols).collect()) == plain([[r[place.index(c)] for c in cols] for r in want.fetchall()])


def test_entry_and_queries(spark):
    assert __spark_entry__.entry(spark).count() > 0
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


def test_golden_sizes(spark):
    for view, (transactions, rows, items) in {"w3": (1473, 4384, 6), "w2": (1473, 5479, 25), "w7": (397, 792, 5), "w9": (500, 4000, 64), "w10": (50, 900, 18), "w12": (87, 348, 28), "w13": (40, 303, 40)}.items():
        got = VIEWS[view](spark, SF).rows.agg(F.countDistinct("tid"), F.count(F.lit(1)), F.countDistinct("item")).first()
        assert tuple(got) == (transactions, rows, items), view


@pytest.mark.parametrize("make, keys", [(streaming.window_item_stats, ["start", "item"]), (lambda e: streaming.session_baskets(e).drop("record"), ["user_id", "start"])])
def test_stream_equals_batch(spark, tmp_path, make, keys):
    events = spark.read.parquet(f"{SF}/events.parquet")
    events.orderBy("ts").coalesce(1).write.parquet(str(tmp_path / "in"))
    out = str(tmp_path / "out")
    q = make(streaming.read_events(spark, str(tmp_path / "in"))).writeStream.format("memory").queryName("streamed").outputMode("complete" if keys[1] == "item" else "append").option("checkpointLocation", out).trigger(availableNow=True).start()
    q.awaitTermination()
    got, want = spark.table("streamed").orderBy(*keys).collect(), make(events).orderBy(*keys).collect()
    if keys[1] == "item":
        assert got == want
    else:  # sessions that are still open at the end are not given out
        assert got and set(got) <= set(want)


def test_utility_text(spark, tmp_path):
    (tmp_path / "a.txt").write_text("1 2:7:3 4\n2:5:5\nbad line\n1 2:3:1\n")
    got = sources.read_utility_text(spark, str(tmp_path / "a.txt"))
    assert sorted(tuple(r)[1:] for r in got.collect()) == [("1", 3), ("2", 4), ("2", 5)]
    spark.dataSource.register(sources.UtilityTextSource)
    assert sorted(tuple(r)[1:] for r in spark.read.format("utility_text").option("path", str(tmp_path / "*.txt")).load().collect()) == [("1", 3), ("2", 4), ("2", 5)]


def test_price_as_of_and_windows(spark):
    rows = spark.sql("SELECT * FROM VALUES (1L, 'a', timestamp '2024-01-02'), (2L, 'a', timestamp '2024-01-05'), (3L, 'b', timestamp '2024-01-05') AS t(tid, item, ts)")
    prices = spark.sql("SELECT * FROM VALUES ('a', timestamp '2024-01-01', 5L), ('a', timestamp '2024-01-05', 6L) AS t(item, valid_from, unit_profit)")
    assert {r["tid"]: r["unit_profit"] for r in sources.price_as_of(rows, prices).collect()} == {1: 5, 2: 6, 3: None}
    windows = spark.sql("SELECT 'w' AS name, timestamp '2024-01-02' AS start, timestamp '2024-01-05' AS stop")
    assert [r["tid"] for r in sources.within_windows(rows, windows).collect()] == [1]


def test_plans(spark):
    plan = QUERIES["item_twu_w3"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "Python" not in plan and "ReadSchema: struct<l_orderkey:bigint,l_partkey:bigint,l_quantity:double>" in plan
