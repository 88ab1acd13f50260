"""More items than one task ranks: none of them promising, or all."""

import pytest

from corrutil.operators import analysis, basket
from corrutil.plans import baselines, prepare
from corrutil.plans.levels import mine
from corrutil.types import Basket

QUERIES = {
    "mine_w1": lambda b, u: mine(b, u, "0.05").settled(),
    "affinity_w1": lambda b, u: baselines.mine_affinity(b, u).settled(),
    "by_chance_w1": lambda b, u: analysis.by_chance(baselines.mine_plain(b, u).settled(), mine(b, u, "0.9").settled()),
    "class_counts_w1": lambda b, u: analysis.class_counts(b, [u, "0.9"], ["0.01", "0.5"]),
    "grid_counts_w1": lambda b, u: analysis.pattern_counts(b, [u, "0.9"], ["0.01", "0.5"]),
    "mine_levels_w1": lambda b, u: mine(b, u, "0.05", plan="levels").settled(),
    "mine_prefix_w1": lambda b, u: mine(b, u, "0.05", plan="prefix").settled(),
    "plain_w1": lambda b, u: baselines.mine_plain(b, u).settled(),
    "tree_growth_w1": lambda b, u: baselines.mine_tree_growth(b, u).settled(),
}


def rows_of(spark) -> Basket:
    """Five transactions of two items each, all items different but one."""
    rows = [(t, f"i{2 * t + j}" if j or t else "i3", 5 + t, 2, 2 * (5 + t)) for t in range(5) for j in range(2)]
    return Basket(spark.createDataFrame(rows, "tid bigint, item string, qty bigint, profit bigint, u bigint"))


@pytest.mark.parametrize("name", QUERIES)
@pytest.mark.parametrize("least", ["0.6", "0.1"])
def test_many_items(spark, monkeypatch, name, least):
    want = sorted(map(tuple, QUERIES[name](rows_of(spark), least).collect()), key=str)
    for module in (basket, prepare):
        monkeypatch.setattr(module, "ONE_SORT", 3)
    assert sorted(map(tuple, QUERIES[name](rows_of(spark), least).collect()), key=str) == want
    # Beyond three fifths of the whole no item is promising.
    assert any(isinstance(x, int) and x for r in want for x in r) == (least == "0.1")
