"""The worked example: every quantity, both mining plans and all baselines."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from corrutil.operators import analysis
from corrutil.operators import basket as ops
from corrutil.plans import baselines
from corrutil.plans.levels import mine, mine_variant
from corrutil.types import Basket, least_utility
from corrutil.workloads import paper_example

CHU = {"e", "a,b", "a,c", "a,e", "b,e", "a,b,e", "b,c,d"}
HUP = {"e", "a,b", "a,c", "a,e", "b,e", "d,e", "a,b,c", "a,b,e", "a,c,d", "a,d,e", "b,c,d", "a,b,c,d", "a,b,c,e", "b,c,d,e", "a,b,c,d,e"}


@pytest.fixture(scope="module")
def example(spark):
    b = paper_example(spark)
    return Basket(b.rows.cache())


def names(df):
    return {r["pattern"] for r in df.select("pattern").collect()}


def test_quantities(example):
    assert {r["tid"]: r["tu"] for r in ops.transaction_utility(example).collect()} == {1: 30, 2: 18, 3: 29, 4: 34, 5: 39}
    assert ops.total_utility(example) == 150
    stats = {r["item"]: (r["sup"], int(r["twu"])) for r in ops.item_stats(example).collect()}
    assert stats == {"a": (5, 150), "b": (4, 121), "c": (2, 52), "d": (3, 81), "e": (4, 132)}
    ranks = ops.rank_items(ops.item_stats(example))
    assert [r["item"] for r in ranks.orderBy("item_rank").collect()] == list("cdbea")
    lists = ops.initial_lists(example, ranks)
    assert sorted((r["tid"], r["iu"], r["ru"]) for r in lists.where("item = 'd'").collect()) == [(2, 2, 9), (3, 6, 23), (4, 2, 18)]
    rows = ops.remaining_utility(example, ranks)
    two = ops.extend_lists(rows.select(F.array("item_rank").alias("ranks"), F.col("item_rank").alias("last"), "tid", F.col("u").alias("iu"), "ru"), rows)
    assert sorted((r["tid"], r["iu"], r["ru"]) for r in two.where("ranks = array(2, 3)").collect()) == [(2, 5, 6), (4, 7, 13)]


def test_given_patterns(spark, example):
    p = spark.createDataFrame([("d,e",), ("a,b,c",), ("a,b,c,d",), ("a,b,c,d,e",), ("b,c,d",)], "pattern string")
    got = {r["pattern"]: (r["utility"], r["sup"], r["twu"]) for r in ops.itemset_utility(example, p).collect()}
    assert got == {"d,e": (38, 2, 63), "a,b,c": (38, 2, 52), "a,b,c,d": (42, 2, 52), "a,b,c,d,e": (34, 1, 34), "b,c,d": (33, 2, 52)}
    kulc = {r["pattern"]: r["kulc"] for r in ops.interest_measures(example, p).collect()}
    assert kulc == {"d,e": 0.583333, "a,b,c": 0.633333, "a,b,c,d": 0.641667, "a,b,c,d,e": 0.306667, "b,c,d": 0.722222}


@pytest.mark.parametrize("how", [{"plan": "levels"}, {"plan": "prefix"}, {"plan": "auto"}, {"unit_tuples": 3}, {"kernel": "lists"}, {"plan": "levels", "la_start": "prefix"}, {"sibling_filter": True}, {"needed_support": True, "plan": "levels"}, {"unit_tuples": 2, "kernel": "lists"}])
def test_correlated_miner(example, how):
    assert names(mine(example, "0.2", "0.7", **how).patterns) == CHU


def test_threshold_is_inclusive_and_pair_bound_kills_only_the_pair(example):
    assert {"a,c", "a,b,e"} <= names(mine(example, "0.2", "0.7").patterns)
    assert "d,e" in names(mine(example, "0.2333", "0", use_spk=False).patterns)
    assert least_utility("0.2", 150) == 30


@pytest.mark.parametrize("name, effort", [("ubu", (28, 23, 0)), ("ubu_spk", (23, 18, 0)), ("ubu_la", (27, 23, 1)), ("all", (23, 18, 0))])
def test_variants_and_their_effort(example, name, effort):
    r = mine_variant(example, "0.2", "0.7", name)
    assert names(r.patterns) == CHU
    assert (r.total("visited"), r.total("joined"), r.total("la_cut")) == effort
    levels, mixed = (mine_variant(example, "0.2", "0.7", name, **how) for how in ({"plan": "levels"}, {"unit_tuples": 3}))
    for other in (levels, mixed):
        for c in ("visited", "joined", "la_cut", "ubu_cut", "spk_cut", "emitted", "expanded", "tuples"):
            assert other.total(c) == r.total(c), c
        other.close()
    assert not levels.held


def test_baselines(example):
    assert names(baselines.mine_plain(example, "0.2").patterns) == HUP
    assert names(baselines.mine_plain(example, "0.2", pair_twu=False, plan="levels").patterns) == HUP
    assert names(baselines.mine_plain_projected(example, "0.2").patterns) == HUP
    assert names(baselines.mine_tree_growth(example, "0.2").patterns) == HUP
    assert names(baselines.mine_tree_growth(example, "0.2", unit_paths=1).patterns) == HUP
    two = baselines.mine_two_phase(example, "0.2")
    assert names(two.patterns) == HUP and two.total("candidates") == 31
    proj = baselines.mine_projection(example, "0.2", "0.7")
    assert names(proj.patterns) == CHU and proj.total("candidates") == 14
    au = {r["pattern"]: r["au"] for r in baselines.mine_affinity(example, "0.2").patterns.collect()}
    assert au == {"e": 80, "a,e": 78, "b,e": 55, "d,e": 36, "a,b,e": 56, "a,d,e": 30}
    assert baselines.mine_exhaustive(example).count() == 31


def test_bad_rows_and_arguments(spark, example):
    rows = spark.createDataFrame([(1, "a", 2), (1, "a", 1), (1, None, 1), (2, "b", 0), (3, "c", 1), (4, "z", 1), (None, "a", 1)], "tid bigint, item string, qty bigint")
    profit = spark.createDataFrame([("a", 3), ("b", 1), ("c", -1)], "item string, unit_profit bigint")
    b = ops.build_basket(rows, profit)
    assert [tuple(r) for r in b.rows.select("tid", "item", "u").collect()] == [(1, "a", 9)]
    assert b.rejected.count() == 5
    for bad in ({"min_cor": "1.5"}, {"min_util": "-0.1"}):
        with pytest.raises(ValueError):
            mine(example, **({"min_util": "0.1", "min_cor": "0.1"} | bad))
    with pytest.raises(ValueError):
        mine(example, "0.1", "0.1", item_order="lexicographic")
    with pytest.raises(ValueError):
        mine(example, "0", "0")
    assert len(names(mine(example, "0", "0", max_k=2).patterns)) == 15
    empty = Basket(spark.createDataFrame([], "tid bigint, item string, u bigint"))
    for plan in ("levels", "prefix"):
        assert mine(empty, "0.1", "0.1", plan=plan).settled().count() == 0
    for run in (baselines.mine_two_phase, baselines.mine_plain, baselines.mine_plain_projected, baselines.mine_tree_growth):
        assert run(empty, "0.1").patterns.count() == 0
    assert baselines.mine_projection(empty, "0.1", "0.1").patterns.count() == 0
    assert analysis.segment_mine(empty.rows, spark.createDataFrame([], "tid bigint, segment string"), "0.1", "0.1").count() == 0
    assert mine(empty, "0.1", "0.1").patterns.count() == 0
    one = Basket(spark.createDataFrame([(1, "a", 5)], "tid bigint, item string, u bigint"))
    assert names(mine(one, "1", "1").patterns) == {"a"}


def brute(rows, util, cor):
    total = sum(u for _, _, u in rows)
    by = {}
    for t, i, u in rows:
        by.setdefault(t, {})[i] = u
    sup = {}
    for x in by.values():
        for i in x:
            sup[i] = sup.get(i, 0) + 1
    seen = {}
    for x in by.values():
        for k in range(1, len(x) + 1):
            for c in itertools.combinations(sorted(x), k):
                n, u = seen.get(c, (0, 0))
                seen[c] = n + 1, u + sum(x[i] for i in c)
    return {",".join(c) for c, (n, u) in seen.items() if u >= util * total - 1e-9 and n * sum(1 / sup[i] for i in c) / len(c) >= cor - 1e-9}


FLAGS = [
    {"plan": "levels"}, {"plan": "levels", "use_la": False}, {"plan": "levels", "use_spk": False}, {"plan": "levels", "la_start": "prefix", "ratio_cut": False}, {"plan": "levels", "needed_support": True},
    {"sibling_filter": True}, {"plan": "levels", "pair_twu": True}, {"plan": "prefix"}, {"kernel": "lists"}, {"unit_tuples": 6}, {"unit_tuples": 4, "la_start": "prefix"}, {"unit_tuples": 5, "pair_twu": True},
    {"item_order": "twu_asc", "use_spk": False}, {"item_order": "lexicographic", "use_spk": False, "plan": "levels"},
]


@pytest.mark.parametrize("seed, how", list(enumerate(FLAGS)))
def test_random_baskets(spark, seed, how):
    rng = random.Random(seed)
    items = "abcdefgh"[: rng.randint(4, 7)]
    rows = [(t, i, rng.randint(1, 5) * rng.randint(1, 20)) for t in range(rng.randint(8, 30)) for i in items if rng.random() < 0.5]
    b = Basket(spark.createDataFrame(rows, "tid bigint, item string, u bigint"))
    assert names(mine(b, "0.05", "0.4", **how).settled()) == brute(rows, 0.05, 0.4)


def test_partitions_do_not_matter(spark):
    rng = random.Random(99)
    rows = [(t, i, rng.randint(1, 50)) for t in range(40) for i in "abcdef" if rng.random() < 0.5]
    b = Basket(spark.createDataFrame(rows, "tid bigint, item string, u bigint"))
    before, found = spark.conf.get("spark.sql.shuffle.partitions"), []
    try:
        for n in (1, 7, 50):
            spark.conf.set("spark.sql.shuffle.partitions", n)
            found += [sorted(map(tuple, mine(b, "0.03", "0.3", **how).settled().collect())) for how in ({"plan": "levels"}, {"unit_tuples": 10})]
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    assert all(f == found[0] for f in found) and len(found[0]) > 6


def test_mined_by_segment_equals_each_alone(spark):
    rng = random.Random(5)
    rows = [(t, i, rng.randint(1, 50)) for t in range(30) for i in "abcde" if rng.random() < 0.6]
    df = spark.createDataFrame(rows, "tid bigint, item string, u bigint")
    seg = spark.createDataFrame([(t, "xyz"[t % 3] if t % 3 else None) for t in range(30)], "tid bigint, segment string")
    got = {}
    for r in analysis.segment_mine(df, seg, "0.05", "0.4").collect():
        got.setdefault(r["segment"], set()).add(r["pattern"])
    assert got == {"xyz"[n]: brute([r for r in rows if r[0] % 3 == n], 0.05, 0.4) for n in (1, 2)}


def test_a_level_is_two_shuffles(spark):
    """One by pattern and item for the counts; lists come from places in the transactions, with no further one at the first level."""
    from corrutil.plans import levels

    plans, keep = [], levels.keep
    try:
        levels.keep = lambda df, held: plans.append(df._jdf.queryExecution().executedPlan().toString()) or keep(df, held)
        rows = [(t, i, 5) for t in range(20) for i in "abcd"]
        levels.mine(Basket(spark.createDataFrame(rows, "tid bigint, item string, u bigint")), "0.1", "0.1", plan="levels")
    finally:
        levels.keep = keep
    counted = [p for p in plans if "keys=[pid" in p and "monotonically" in p]
    assert counted and all(p.count("hashpartitioning(pid") <= 2 and "Cartesian" not in p and "Python" not in p for p in counted)
    assert "hashpartitioning(tid" not in counted[0]
