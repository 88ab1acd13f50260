"""Streams with late rows, restarts and repeated events, against the same rows in one batch."""

import datetime as dt

import pytest
from pyspark.sql import functions as F

from corrutil import streaming

T0 = dt.datetime(2024, 1, 1)


def rows(*events):
    """(hours, user, type, value) or with an id of its own."""
    return [(e[4] if len(e) > 4 else i, T0 + dt.timedelta(hours=e[0]), e[1], e[2], float(e[3]), "{}") for i, e in enumerate(events)]


FIRST = rows((1, 1, "a", 2), (2, 1, "b", 3), (3, 2, "a", 1), (30, 1, "a", 5), (30.1, 1, "b", 7))
#: The next file moves the watermark to hour 59; the last one brings a row of hour 4 that is too late.
SECOND = rows((60, 2, "b", 4, 10), (60.2, 2, "a", 4, 11))
LATE = rows((4, 1, "a", 100, 20), (100, 1, "a", 1, 21), (130, 1, "a", 1, 22))
LAST = rows((200, 3, "z", 1, 30), (200, 3, "z", 1, 30))


def put(spark, path, n, events):
    spark.createDataFrame(events, streaming.EVENTS).coalesce(1).write.mode("append").parquet(f"{path}/{n}")


def run(spark, make, path, out, sink="parquet"):
    source = spark.readStream.schema(streaming.EVENTS).option("recursiveFileLookup", True).option("maxFilesPerTrigger", 1).parquet(path)
    q = make(source).writeStream.format(sink).outputMode("append").option("checkpointLocation", f"{out}/state").option("path", f"{out}/rows").trigger(availableNow=True).start()
    q.awaitTermination()
    return q


def test_late_rows_are_left_out_and_counted_and_a_restart_adds_nothing_twice(spark, tmp_path):
    path, out = str(tmp_path / "in"), f"file://{tmp_path}/out"
    for n, events in enumerate((FIRST, SECOND)):
        put(spark, f"file://{path}", n, events)
    run(spark, streaming.window_item_twu, f"file://{path}", out)
    put(spark, f"file://{path}", 2, LATE)
    late = streaming.late_rows(run(spark, streaming.window_item_twu, f"file://{path}", out))
    put(spark, f"file://{path}", 3, LAST)
    run(spark, streaming.window_item_twu, f"file://{path}", out)
    run(spark, streaming.window_item_twu, f"file://{path}", out)  # nothing new
    got = sorted(map(tuple, spark.read.parquet(f"{out}/rows").collect()))
    assert late >= 1
    kept = spark.createDataFrame(FIRST + SECOND + LATE[1:] + LAST, streaming.EVENTS)
    want = sorted(map(tuple, streaming.window_item_twu(kept).collect()))
    assert got and len(got) == len(set(got)) and set(got) <= set(want)
    day = [g for g in got if g[0] == T0]
    assert day == [(T0, "a", 2, 300, 600), (T0, "b", 1, 300, 500)]


def test_twu_of_windows(spark):
    got = sorted(map(tuple, streaming.window_item_twu(spark.createDataFrame(FIRST, streaming.EVENTS)).collect()))
    second = T0 + dt.timedelta(days=1)
    assert got == [(T0, "a", 2, 300, 600), (T0, "b", 1, 300, 500), (second, "a", 1, 500, 1200), (second, "b", 1, 700, 1200)]


def test_closing_baskets_equal_sessions(spark, tmp_path):
    path, out = f"file://{tmp_path}/in", f"file://{tmp_path}/out"
    events = rows((1, 1, "a", 2), (1.2, 1, "b", 3), (1.4, 1, "a", 1), (3, 1, "a", 5), (1.1, 2, "c", 7), (40, 9, "z", 1))
    put(spark, path, 0, events)
    put(spark, path, 1, rows((90, 9, "z", 1, 50)))
    put(spark, path, 2, rows((190, 9, "z", 1, 51)))
    run(spark, streaming.closing_baskets, path, out)
    got = {tuple(r) for r in spark.read.parquet(f"{out}/rows").collect()}
    want = {tuple(r) for r in streaming.session_baskets(spark.createDataFrame(events, streaming.EVENTS)).select("user_id", "start", "n", "tu").collect()}
    assert got >= {w for w in want if w[0] in (1, 2)} and all(g in want or g[0] == 9 for g in got)


def test_repeated_events_count_once(spark, tmp_path):
    path, out = f"file://{tmp_path}/in", f"file://{tmp_path}/out"
    put(spark, path, 0, FIRST + FIRST)
    put(spark, path, 1, FIRST[:1])
    run(spark, streaming.deduplicated, path, out)
    assert spark.read.parquet(f"{out}/rows").count() == len(FIRST)
    assert streaming.deduplicated(spark.createDataFrame(FIRST + FIRST, streaming.EVENTS)).count() == len(FIRST)


def test_windows_are_mined_as_they_close(spark, tmp_path):
    path = f"file://{tmp_path}/in"
    for n, events in enumerate((FIRST, SECOND, LAST)):
        put(spark, path, n, events)
    seen = {}

    def sink(found, number):
        seen[number] = [tuple(r) for r in found.select("start", "pattern", "k", "sup", "utility").collect()]

    source = spark.readStream.schema(streaming.EVENTS).option("recursiveFileLookup", True).option("maxFilesPerTrigger", 1).parquet(path)
    q = streaming.window_baskets(source).writeStream.outputMode("append").option("checkpointLocation", f"file://{tmp_path}/state").foreachBatch(streaming.window_miner(sink, "0.1", "0.4")).trigger(availableNow=True).start()
    q.awaitTermination()
    got = sorted(x for found in seen.values() for x in found)
    closed = streaming.window_baskets(spark.createDataFrame(FIRST + SECOND, streaming.EVENTS))
    want = sorted(map(tuple, streaming.mine_windows(closed, "0.1", "0.4").select("start", "pattern", "k", "sup", "utility").collect()))
    assert got == want and any(x[2] == 2 for x in got)


def test_no_rows_give_an_empty_frame(spark):
    empty = spark.createDataFrame([], streaming.EVENTS)
    assert streaming.mine_windows(streaming.window_baskets(empty), "0.1", "0.1").count() == 0
    assert streaming.window_item_twu(empty).count() == 0


@pytest.mark.parametrize("form", ["parquet", "json"])
def test_readers_and_sinks(spark, tmp_path, form):
    from corrutil import sources
    from corrutil.operators.basket import build_basket, explode_records
    from corrutil.types import PROFIT, TRANSACTION

    tx = spark.createDataFrame([(1, "u", T0, [("a", 2), ("b", 1)]), (2, "u", T0, [("a", 1)])], TRANSACTION)
    tx.write.format(form).save(f"file://{tmp_path}/tx")
    profit = spark.createDataFrame([("a", 3), ("b", 5)], PROFIT)
    profit.write.option("header", True).csv(f"file://{tmp_path}/profit")
    basket = build_basket(explode_records(sources.read_transactions(spark, f"file://{tmp_path}/tx", form)), sources.read_profits(spark, f"file://{tmp_path}/profit", "csv"))
    assert sorted(map(tuple, basket.rows.select("tid", "item", "u").collect())) == [(1, "a", 6), (1, "b", 5), (2, "a", 3)]
    (tmp_path / "rows.csv").write_text("tid,item,qty\n1,a,2\n2,b,\n")
    assert sorted(map(tuple, sources.read_csv_rows(spark, f"file://{tmp_path}/rows.csv").collect())) == [(1, "a", 2), (2, "b", None)]
    patterns = spark.createDataFrame([("a", 1, 2, 9, 1.0), ("a,b", 2, 1, 11, 0.75)], "pattern string, k int, sup bigint, utility bigint, kulc double")
    sources.write_patterns(patterns, f"file://{tmp_path}/out", run="one", form=form)
    assert spark.read.format(form).load(f"file://{tmp_path}/out").where("run = 'one' AND k = 2").select("pattern").first()[0] == "a,b"
    sources.register(patterns, "found")
    assert spark.sql("SELECT count(*) FROM found WHERE kulc > 0.8").first()[0] == 1


def test_bad_lines_are_set_aside(spark, tmp_path):
    from corrutil import sources

    (tmp_path / "a.txt").write_text("1 2:7:3 4\n1 2:3:1\nbad\n1:x:y\n3:9:9\n")
    lines = sources.read_lines(spark, f"file://{tmp_path}/a.txt")
    assert sorted(tuple(r)[1:] for r in sources.utility_lines(lines).collect()) == [("1", 3), ("2", 4), ("3", 9)]
    assert sorted((r["value"], r["reason"]) for r in sources.rejected_lines(lines).collect()) == [("1 2:3:1", "lists of different length"), ("1:x:y", "not a number"), ("bad", "not three parts")]


def test_simulated_profits_and_quantities(spark):
    from corrutil.functions import simulate_profit, simulate_quantity

    df = spark.range(2000).select("id", simulate_quantity("id").alias("q"), simulate_profit("id").alias("p"))
    assert df.collect() == df.repartition(7).orderBy("id").collect()
    q, low, mean = df.agg(F.collect_set("q"), F.min("p"), F.avg(F.log("p"))).first()
    assert set(q) == {1, 2, 3, 4, 5} and low >= 1 and abs(mean - 4.6) < 0.2
