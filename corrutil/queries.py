"""All queries of the mining library, and for each the SQL that DuckDB answers it with."""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import experiments, streaming
from .functions import cents, correlation_kind, kulc, shown
from .operators import analysis
from .operators import basket as ops
from .plans import baselines
from .plans.levels import mine, mine_variant
from .types import Basket, ratio
from .workloads import VIEW_SQL, VIEWS, table

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def _add(name: str, query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql is not None:
        ORACLE_SQL[name] = sql


def _view(name: str):
    return lambda spark, sf: VIEWS[name](spark, sf)


def powerset(view: str) -> str:
    """Common tables of every itemset that occurs: ``c`` (pattern, k, sup, utility, kulc, items), ``b``, ``o``, ``t``."""
    return f"""WITH RECURSIVE b AS MATERIALIZED ({VIEW_SQL[view]}),
p(tid, items, last, u) AS (SELECT tid, [item], item, u FROM b UNION ALL SELECT p.tid, list_append(p.items, b.item), b.item, p.u + b.u FROM p JOIN b ON p.tid = b.tid AND b.item > p.last),
o AS (SELECT item, count(*) AS n, sum(u) AS u FROM b GROUP BY item), t AS (SELECT sum(u) AS total FROM b),
s AS (SELECT items, array_to_string(items, ',') AS pattern, count(*) AS sup, sum(u) AS utility FROM p GROUP BY items),
i AS (SELECT pattern, sum(CAST(1 AS DOUBLE) / n) AS inv FROM (SELECT pattern, unnest(items) AS item FROM s) x JOIN o USING (item) GROUP BY pattern),
c AS (SELECT s.pattern, CAST(len(items) AS INT) AS k, CAST(sup AS BIGINT) AS sup, CAST(utility AS BIGINT) AS utility, sup * inv / len(items) AS kulc, items FROM s JOIN i USING (pattern))
"""


def levels_sql(view: str, util: str, cor: str) -> str:
    """Qualifying patterns of every length, for views whose subsets are too many to list: ``g`` (x, inv, sup, su) by item ranks ``r``.

    Each step of the recursion extends the rows of the patterns before it; windows over equal patterns keep those whose
    utility and what remains, and whose correlation along the support order, can still reach the thresholds.
    """
    r = ratio(util)
    least = f"* {r.denominator} >= {r.numerator} * (SELECT total FROM t)"
    return f"""WITH RECURSIVE b0 AS MATERIALIZED ({VIEW_SQL[view]}), t AS (SELECT sum(u) AS total FROM b0),
w AS (SELECT *, sum(u) OVER (PARTITION BY tid) AS tu FROM b0),
o AS MATERIALIZED (SELECT item, count(*) AS n, CAST(row_number() OVER (ORDER BY count(*), item) AS INT) AS r FROM w GROUP BY item HAVING CAST(sum(tu) AS HUGEINT) {least}),
b AS MATERIALIZED (SELECT tid, r, n, u, coalesce(sum(u) OVER (PARTITION BY tid ORDER BY r DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS ru FROM b0 JOIN o USING (item)),
p AS (SELECT tid, [r] AS x, r AS last, 1::DOUBLE / n AS inv, u AS iu, n AS sup, sum(u) OVER (PARTITION BY r) AS su FROM b
 UNION ALL
 SELECT tid, x, last, inv, iu, sup, su FROM (
  SELECT *, count(*) OVER y AS sup, sum(iu) OVER y AS su, sum(iu + ru) OVER y AS ub FROM (
   SELECT p.tid, list_append(p.x, b.r) AS x, b.r AS last, p.inv + 1::DOUBLE / b.n AS inv, p.iu + b.u AS iu, b.ru FROM p JOIN b ON p.tid = b.tid AND b.r > p.last)
  WINDOW y AS (PARTITION BY x))
 WHERE CAST(ub AS HUGEINT) {least} AND sup * inv / len(x) >= {cor} - 1e-9),
f AS (SELECT x, any_value(inv) AS inv, any_value(sup) AS sup, any_value(su) AS su FROM p GROUP BY x),
g AS (SELECT * FROM f WHERE CAST(su AS HUGEINT) {least} AND sup * inv / len(x) >= {cor} - 1e-9),
c AS (SELECT array_to_string(list_sort(list(o.item)), ',') AS pattern, CAST(len(g.x) AS INT) AS k, CAST(any_value(sup) AS BIGINT) AS sup, CAST(any_value(su) AS BIGINT) AS utility, any_value(sup * inv / len(x)) AS kulc, list_sort(list(o.item)) AS items
 FROM (SELECT *, unnest(x) AS r FROM g) g JOIN o USING (r) GROUP BY g.x)
"""


def deep_sql(view: str, util: str, cor: str) -> str:
    return levels_sql(view, util, cor) + "SELECT pattern, k, sup, utility, round(kulc + 1e-12, 6) AS kulc FROM c"


def _at_least(util: str, column: str = "utility") -> str:
    r = ratio(util)
    return f"CAST({column} AS HUGEINT) * {r.denominator} >= {r.numerator} * (SELECT total FROM t)"


def mined_sql(view: str, util: str, cor: str) -> str:
    return powerset(view) + f"SELECT pattern, k, sup, utility, round(kulc + 1e-12, 6) AS kulc FROM c WHERE {_at_least(util)} AND kulc >= {cor} - 1e-9"


def _mined(view: str, util: str, cor: str, **how):
    return lambda spark, sf: mine(VIEWS[view](spark, sf), util, cor, **how).settled()


# Definitions
for _v in ("w1", "w3"):
    _b = f"WITH b AS ({VIEW_SQL[_v]})"
    _add(f"item_utility_{_v}", lambda s, d, v=_v: ops.item_utility(VIEWS[v](s, d)), f"{_b} SELECT tid, item, u FROM b")
    _add(f"transaction_utility_{_v}", lambda s, d, v=_v: ops.transaction_utility(VIEWS[v](s, d)), f"{_b} SELECT tid, CAST(sum(u) AS BIGINT) AS tu FROM b GROUP BY tid")
    _add(f"total_utility_{_v}", lambda s, d, v=_v: VIEWS[v](s, d).rows.agg(F.sum("u").alias("total")), f"{_b} SELECT CAST(sum(u) AS BIGINT) AS total FROM b")
    _stats = f"{_b}, w AS (SELECT *, sum(u) OVER (PARTITION BY tid) AS tu FROM b), st AS (SELECT item, count(*) AS sup, CAST(sum(tu) AS BIGINT) AS twu, CAST(sum(u) AS BIGINT) AS u FROM w GROUP BY item), r AS (SELECT *, CAST(row_number() OVER (ORDER BY sup, item) AS INT) AS item_rank FROM st), f AS (SELECT b.tid, b.item, r.item_rank, b.u, CAST(coalesce(sum(b.u) OVER (PARTITION BY b.tid ORDER BY r.item_rank DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS ru FROM b JOIN r USING (item))"
    _add(f"item_support_{_v}", lambda s, d, v=_v: ops.item_stats(VIEWS[v](s, d)).select("item", "sup"), f"{_stats} SELECT item, sup FROM st")
    _add(f"item_twu_{_v}", lambda s, d, v=_v: ops.item_stats(VIEWS[v](s, d)).select("item", F.col("twu").cast("bigint").alias("twu"), F.col("u").cast("bigint").alias("u")), f"{_stats} SELECT item, twu, u FROM st")
    _add(f"item_rank_{_v}", lambda s, d, v=_v: ops.rank_items(ops.item_stats(VIEWS[v](s, d))).select("item", "item_rank"), f"{_stats} SELECT item, item_rank FROM r")
    _add(f"remaining_utility_{_v}", lambda s, d, v=_v: ops.remaining_utility(*_ranked(VIEWS[v](s, d))), f"{_stats} SELECT tid, item, item_rank, u, ru FROM f")
    _add(f"initial_lists_{_v}", lambda s, d, v=_v: ops.initial_lists(*_ranked(VIEWS[v](s, d))), f"{_stats} SELECT item, tid, u AS iu, ru FROM f")
    _add(f"list_totals_{_v}", lambda s, d, v=_v: ops.list_totals(ops.initial_lists(*_ranked(VIEWS[v](s, d)))), f"{_stats} SELECT item, count(*) AS sup, CAST(sum(u) AS BIGINT) AS iu, CAST(sum(ru) AS BIGINT) AS ru FROM f GROUP BY item")
    if _v == "w3":
        _pair = _stats + ", e AS (SELECT a.item AS x, b2.item AS y, a.tid, a.u + b2.u AS iu, b2.ru, a.u + a.ru AS joint, tu.tu FROM f a JOIN f b2 ON a.tid = b2.tid AND b2.item_rank > a.item_rank JOIN (SELECT tid, sum(u) AS tu FROM b GROUP BY tid) tu ON tu.tid = a.tid)"


def _ranked(basket: Basket) -> tuple[Basket, DataFrame]:
    return basket, ops.rank_items(ops.item_stats(basket))


def _pairs(spark: SparkSession, sf: str) -> DataFrame:
    basket, ranks = _ranked(VIEWS["w3"](spark, sf))
    rows = ops.remaining_utility(basket, ranks)
    names = ranks.select("item_rank", "item")
    lists = rows.select(F.array("item_rank").alias("ranks"), F.col("item_rank").alias("last"), "tid", F.col("u").alias("iu"), "ru")
    both = ops.extend_lists(lists, rows.select("tid", "item_rank", "u", "ru"))
    first = both.withColumn("a", F.element_at("ranks", 1)).join(names.select(F.col("item_rank").alias("a"), F.col("item").alias("x")), "a")
    return first.join(names.select(F.col("item_rank").alias("last"), F.col("item").alias("y")), "last").join(ops.transaction_utility(basket), "tid").select("x", "y", "tid", "iu", "ru", "joint", "tu")


def _pair_kulc(spark: SparkSession, sf: str) -> DataFrame:
    sups = ops.item_stats(VIEWS["w3"](spark, sf)).select("item", "sup")
    n = _pairs(spark, sf).groupBy("x", "y").agg(F.count(F.lit(1)).alias("sup"))
    both = n.join(sups.select(F.col("item").alias("x"), F.col("sup").alias("sx")), "x").join(sups.select(F.col("item").alias("y"), F.col("sup").alias("sy")), "y")
    value = kulc("sup", 1 / F.col("sx") + 1 / F.col("sy"), F.lit(2))
    return both.select("x", "y", "sup", shown(value).alias("kulc"), correlation_kind(value).alias("kind"))


_add("pair_lists_w3", lambda s, d: _pairs(s, d).select("x", "y", "tid", "iu", "ru"), _pair + " SELECT x, y, tid, CAST(iu AS BIGINT) AS iu, ru FROM e")
_add("pair_twu_w3", lambda s, d: _pairs(s, d).groupBy("x", "y").agg(F.sum("tu").alias("twu")), _pair + " SELECT x, y, CAST(sum(tu) AS BIGINT) AS twu FROM e GROUP BY x, y")
_add("pair_la_bound_w3", lambda s, d: _pairs(s, d).groupBy("x", "y").agg(F.sum("joint").alias("joint"), F.sum(F.col("iu") + F.col("ru")).alias("ub")), _pair + " SELECT x, y, CAST(sum(joint) AS BIGINT) AS joint, CAST(sum(iu + ru) AS BIGINT) AS ub FROM e GROUP BY x, y")
_kind = "CASE WHEN v > 0.5 + 1e-9 THEN 'positive' WHEN v < 0.5 - 1e-9 THEN 'negative' ELSE 'none' END AS kind"
_add("pair_kulc_w3", _pair_kulc, _pair + f" SELECT x, y, sup, round(v + 1e-12, 6) AS kulc, {_kind} FROM (SELECT x, y, count(*) AS sup, count(*) * (1::DOUBLE / max(sx.sup) + 1::DOUBLE / max(sy.sup)) / 2 AS v FROM e JOIN st sx ON sx.item = x JOIN st sy ON sy.item = y GROUP BY x, y)")

# The correlated miner on every view. SQL lists all subsets where transactions are short, else it goes by levels.
MINED = {
    "mine_w1": ("w1", "0.0001", "0.05", {}), "mine_w2": ("w2", "0.005", "0.1", {}), "mine_w3": ("w3", "0.01", "0.2", {}), "mine_w3_all": ("w3", "0.01", "0", {}),
    "mine_w4": ("w4", "0.07", "0.65", {}), "mine_w5": ("w5", "0.0005", "0.03", {}), "mine_w6": ("w6", "0.001", "0.05", {}), "mine_w7": ("w7", "0.004", "0.2", {}),
    "mine_w8": ("w8", "0.03", "0.8", {}), "mine_w8_low": ("w8", "0.03", "0.7", {}), "mine_w9": ("w9", "0.001", "0.1", {}), "tags_w10": ("w10", "0.8", "0.5", {}), "conv_w11": ("w11", "0.02", "0.85", {}),
    "labels_w12": ("w12", "0.01", "0.1", {}), "bench_w13": ("w13", "0.01", "0.2", {}),
    "mine_levels_w1": ("w1", "0.0001", "0.05", {"plan": "levels"}), "mine_levels_w3": ("w3", "0.01", "0.2", {"plan": "levels"}),
    "mine_prefix_w1": ("w1", "0.0001", "0.05", {"plan": "prefix"}), "mine_prefix_w3": ("w3", "0.01", "0.2", {"plan": "prefix"}), "mine_lists_w3": ("w3", "0.01", "0.2", {"kernel": "lists"}), "mine_lists_w4": ("w4", "0.07", "0.65", {"kernel": "lists"}),
    "mine_hybrid_w2": ("w2", "0.002", "0.15", {"plan": "auto", "unit_tuples": 500}),
    "mine_la_prefix_start_w3": ("w3", "0.01", "0.2", {"la_start": "prefix", "plan": "levels"}), "mine_sibling_filter_w3": ("w3", "0.01", "0.2", {"sibling_filter": True}),
    "mine_needed_support_w3": ("w3", "0.01", "0.2", {"needed_support": True, "plan": "levels"}),
    "mine_twu_order_w3": ("w3", "0.01", "0.2", {"item_order": "twu_asc", "use_spk": False}), "mine_lexicographic_w3": ("w3", "0.01", "0.2", {"item_order": "lexicographic", "use_spk": False}),
    "mine_zero_utility_w3": ("w3", "0", "0.3", {}),
}
DEEP = {"w4", "w8", "w10", "w11", "w13"}
for _name, (_v, _u, _c, _how) in MINED.items():
    _add(_name, _mined(_v, _u, _c, **_how), (deep_sql if _v in DEEP else mined_sql)(_v, _u, _c))
for _variant in ("ubu", "ubu_spk", "ubu_la", "all"):
    _add(f"variant_{_variant}_w3", lambda s, d, n=_variant: mine_variant(VIEWS["w3"](s, d), "0.01", "0.3", n).settled(), mined_sql("w3", "0.01", "0.3"))
    _add(f"variant_{_variant}_w2", lambda s, d, n=_variant: mine_variant(VIEWS["w2"](s, d), "0.005", "0.1", n).settled(), deep_sql("w2", "0.005", "0.1"))


#: Thresholds at which the ablation is measured, from few patterns to many.
EFFORT_W3 = [("0.05", "0.3"), ("0.01", "0.2")]
#: Dense transactions: what cutting by correlation saves.
EFFORT_W13 = [("0.1", "0.3"), ("0.06", "0.2")]


def effort_sql(view: str, pairs: list[tuple[str, str]]) -> str:
    """Nodes visited, joins, pairs cut, patterns and list entries of the four variants; candidates and entries of the projection baseline."""
    parts = []
    for n, (util, cor) in enumerate(pairs):
        r = ratio(util)
        least = f"* {r.denominator} >= {r.numerator} * (SELECT total FROM t)"
        base = f"""w AS (SELECT *, sum(u) OVER (PARTITION BY tid) AS tu FROM b0),
o AS MATERIALIZED (SELECT item, count(*) AS n, CAST(row_number() OVER (ORDER BY count(*), item) AS INT) AS r FROM w GROUP BY item HAVING CAST(sum(tu) AS HUGEINT) {least}),
b AS MATERIALIZED (SELECT tid, r, n, u, tu, coalesce(sum(u) OVER (PARTITION BY tid ORDER BY r DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS ru FROM w JOIN o USING (item))"""
        for name, spk, la in (("ubu", False, False), ("ubu_spk", True, False), ("ubu_la", False, True), ("all", True, True)):
            go = f"alive AND CAST(ub AS HUGEINT) {least}" + (f" AND sup * inv / len(x) >= {cor} - 1e-9" if spk else "")
            alive = f"CAST(joint AS HUGEINT) {least}" if la else "true"
            parts.append(f"""SELECT '{name}' AS method, '{util}' AS min_util, '{cor}' AS min_cor, count(*) FILTER (WHERE alive) AS visited, count(*) FILTER (WHERE len(x) > 1) AS joined, count(*) FILTER (WHERE NOT alive) AS la_cut,
 count(*) FILTER (WHERE alive AND CAST(su AS HUGEINT) {least} AND sup * inv / len(x) >= {cor} - 1e-9) AS patterns, CAST(coalesce(sum(sup) FILTER (WHERE alive), 0) AS BIGINT) AS tuples FROM (
 WITH RECURSIVE {base}, p AS (
  SELECT tid, [r] AS x, r AS last, 1::DOUBLE / n AS inv, u AS iu, ru, n AS sup, sum(u) OVER (PARTITION BY r) AS su, sum(u + ru) OVER (PARTITION BY r) AS ub, true AS alive FROM b
  UNION ALL
  SELECT tid, x, last, inv, iu, ru, sup, su, ub, {alive} AS alive FROM (
   SELECT *, count(*) OVER y AS sup, sum(iu) OVER y AS su, sum(iu + ru) OVER y AS ub, sum(j) OVER y AS joint FROM (
    SELECT p.tid, list_append(p.x, b.r) AS x, b.r AS last, p.inv + 1::DOUBLE / b.n AS inv, p.iu + b.u AS iu, b.ru, p.iu + p.ru AS j FROM p JOIN b ON p.tid = b.tid AND b.r > p.last WHERE {go})
   WINDOW y AS (PARTITION BY x)))
 SELECT x, any_value(inv) AS inv, any_value(sup) AS sup, any_value(su) AS su, any_value(alive) AS alive FROM p GROUP BY x)""")
        parts.append(f"""SELECT 'projection' AS method, '{util}' AS min_util, '{cor}' AS min_cor, count(*) AS visited, 0 AS joined, 0 AS la_cut, count(*) FILTER (WHERE CAST(su AS HUGEINT) {least} AND ok) AS patterns, CAST(coalesce(sum(sup), 0) AS BIGINT) AS tuples FROM (
 WITH RECURSIVE {base}, p AS (
  SELECT tid, [r] AS x, r AS last, 1::DOUBLE / n AS inv, u AS iu, tu, n AS sup, sum(u) OVER (PARTITION BY r) AS su, true AS ok FROM b
  UNION ALL
  SELECT tid, x, last, inv, iu, tu, sup, su, CAST(twu AS HUGEINT) {least} AND sup * inv / len(x) >= {cor} - 1e-9 AS ok FROM (
   SELECT *, count(*) OVER y AS sup, sum(iu) OVER y AS su, sum(tu) OVER y AS twu FROM (
    SELECT p.tid, list_append(p.x, b.r) AS x, b.r AS last, p.inv + 1::DOUBLE / b.n AS inv, p.iu + b.u AS iu, p.tu FROM p JOIN b ON p.tid = b.tid AND b.r > p.last WHERE p.ok)
   WINDOW y AS (PARTITION BY x)))
 SELECT x, any_value(sup) AS sup, any_value(su) AS su, any_value(ok) AS ok FROM p GROUP BY x)""")
    return f"WITH b0 AS MATERIALIZED ({VIEW_SQL[view]}), t AS (SELECT sum(u) AS total FROM b0) " + "\nUNION ALL\n".join(parts)


def _effort(view: str, pairs: list[tuple[str, str]]):
    return lambda spark, sf: experiments.effort(VIEWS[view](spark, sf), pairs)


_add("variant_effort_w3", _effort("w3", EFFORT_W3), effort_sql("w3", EFFORT_W3))
_add("variant_effort_w13", _effort("w13", EFFORT_W13), effort_sql("w13", EFFORT_W13))

# Baselines
_add("plain_w1", lambda s, d: baselines.mine_plain(VIEWS["w1"](s, d), "0.0002").settled(), mined_sql("w1", "0.0002", "0"))
_add("plain_w3", lambda s, d: baselines.mine_plain(VIEWS["w3"](s, d), "0.01").settled(), mined_sql("w3", "0.01", "0"))
_add("plain_levels_w3", lambda s, d: baselines.mine_plain(VIEWS["w3"](s, d), "0.01", plan="levels").settled(), mined_sql("w3", "0.01", "0"))
_add("plain_basic_w3", lambda s, d: baselines.mine_plain(VIEWS["w3"](s, d), "0.01", pair_twu=False, use_la=True).settled(), mined_sql("w3", "0.01", "0"))
_add("plain_projected_w3", lambda s, d: baselines.mine_plain_projected(VIEWS["w3"](s, d), "0.01").settled(), mined_sql("w3", "0.01", "0"))
_add("two_phase_w3", lambda s, d: baselines.mine_two_phase(VIEWS["w3"](s, d), "0.01").settled(), mined_sql("w3", "0.01", "0"))
_add("tree_growth_w3", lambda s, d: baselines.mine_tree_growth(VIEWS["w3"](s, d), "0.01").settled(), mined_sql("w3", "0.01", "0"))
_add("tree_growth_w1", lambda s, d: baselines.mine_tree_growth(VIEWS["w1"](s, d), "0.0002").settled(), mined_sql("w1", "0.0002", "0"))
_add("projection_w3", lambda s, d: baselines.mine_projection(VIEWS["w3"](s, d), "0.01", "0.2").settled(), mined_sql("w3", "0.01", "0.2"))
_add("projection_w4", lambda s, d: baselines.mine_projection(VIEWS["w4"](s, d), "0.07", "0.65").settled(), deep_sql("w4", "0.07", "0.65"))
_add("exhaustive_w3", lambda s, d: baselines.mine_exhaustive(VIEWS["w3"](s, d)), powerset("w3") + "SELECT pattern, k, sup, utility, round(kulc + 1e-12, 6) AS kulc FROM c")
_twu = "tw AS (SELECT items, CAST(sum(tu) AS BIGINT) AS twu FROM p JOIN (SELECT tid, sum(u) AS tu FROM b GROUP BY tid) x USING (tid) GROUP BY items)"
_add("projection_candidates_w3", lambda s, d: baselines.projection_candidates(VIEWS["w3"](s, d), "0.05", "0.2").settled(), powerset("w3").rstrip() + ", " + _twu + f" SELECT pattern, k, sup, twu FROM c JOIN tw USING (items) WHERE {_at_least('0.05', 'twu')} AND kulc >= 0.2 - 1e-9")


def affinity_sql(view: str, util: str) -> str:
    r = ratio(util)
    return f"""WITH RECURSIVE b AS MATERIALIZED ({VIEW_SQL[view]}), t AS (SELECT sum(u) AS total FROM b),
p(tid, items, last, m, f) AS (SELECT tid, [item], item, qty, profit FROM b UNION ALL SELECT p.tid, list_append(p.items, b.item), b.item, least(p.m, b.qty), p.f + b.profit FROM p JOIN b ON p.tid = b.tid AND b.item > p.last)
SELECT array_to_string(items, ',') AS pattern, CAST(len(items) AS INT) AS k, count(*) AS sup, CAST(sum(m) AS BIGINT) AS af, CAST(sum(m * f) AS BIGINT) AS au FROM p GROUP BY items
HAVING CAST(sum(m * f) AS HUGEINT) * {r.denominator} >= {r.numerator} * (SELECT total FROM t)"""


_add("affinity_w3", lambda s, d: baselines.mine_affinity(VIEWS["w3a"](s, d), "0.01").settled(), affinity_sql("w3a", "0.01"))
_add("affinity_w1", lambda s, d: baselines.mine_affinity(VIEWS["w1"](s, d), "0.0001").settled(), affinity_sql("w1", "0.0001"))
_add("fpgrowth_w3", lambda s, d: baselines.frequent_itemsets(VIEWS["w3"](s, d), 0.1), powerset("w3") + "SELECT pattern, k, sup FROM c WHERE sup >= ceil(0.1 * (SELECT count(DISTINCT tid) FROM b))")
_add(
    "rules_w3",
    lambda s, d: baselines.association_rules(VIEWS["w3"](s, d), 0.05, 0.4),
    powerset("w3") + """, f AS (SELECT * FROM c WHERE sup >= ceil(0.05 * (SELECT count(DISTINCT tid) FROM b)))
SELECT a.pattern AS antecedent, z AS consequent, round(f.sup::DOUBLE / a.sup, 6) AS confidence FROM (SELECT *, unnest(items) AS z FROM f WHERE k > 1) f JOIN f a ON a.items = list_filter(f.items, lambda x: x <> f.z) WHERE f.sup::DOUBLE / a.sup >= 0.4""",
)

# Counts over grids of thresholds
GRID_W3 = (["0.01", "0.02", "0.05", "0.1", "0.15", "0.2"], ["0", "0.1", "0.2", "0.3", "0.4", "0.5"])
GRID_W1 = (["0.0001", "0.00015", "0.0002", "0.0003", "0.0005", "0.001"], ["0.05", "0.06", "0.08", "0.1", "0.15", "0.2"])


def grid_sql(view: str, utils: list[str], cors: list[str]) -> str:
    grid = ", ".join(f"('{u}', '{c}', {Fraction(ratio(u)).numerator}, {Fraction(ratio(u)).denominator}, {c})" for u in utils for c in cors)
    return powerset(view).rstrip() + f""", g(min_util, min_cor, num, den, cor) AS (VALUES {grid}),
n AS (SELECT min_util, min_cor, count(c.pattern) AS patterns FROM g LEFT JOIN c ON CAST(c.utility AS HUGEINT) * g.den >= g.num * (SELECT total FROM t) AND c.kulc >= g.cor - 1e-9 GROUP BY min_util, min_cor)
"""


_add("grid_counts_w3", lambda s, d: analysis.pattern_counts(VIEWS["w3"](s, d), *GRID_W3), grid_sql("w3", *GRID_W3) + "SELECT * FROM n")
_add("grid_counts_w1", lambda s, d: analysis.pattern_counts(VIEWS["w1"](s, d), *GRID_W1), grid_sql("w1", *GRID_W1) + "SELECT * FROM n")
_add("grid_monotone_w3", lambda s, d: analysis.count_steps(analysis.pattern_counts(VIEWS["w3"](s, d), *GRID_W3)), grid_sql("w3", *GRID_W3) + "SELECT *, coalesce(patterns <= before, true) AS falls FROM (SELECT *, lag(patterns) OVER (PARTITION BY min_util ORDER BY CAST(min_cor AS DOUBLE)) AS before FROM n)")

# Every class counted on one grid of utility thresholds: high-utility, affinity, and correlated at six thresholds
CLASSES = {
    "w1": (["0.0001", "0.00015", "0.0002", "0.0003", "0.0005", "0.001"], ["0.01", "0.02", "0.05", "0.06", "0.08", "0.1"]),
    "w2a": (["0.001", "0.002", "0.003", "0.005", "0.007", "0.01"], ["0.02", "0.04", "0.06", "0.08", "0.1", "0.12"]),
    "w3a": (["0.01", "0.02", "0.05", "0.1", "0.15", "0.2"], ["0.1", "0.2", "0.25", "0.3", "0.4", "0.5"]),
    "w13": (["0.04", "0.05", "0.06", "0.08", "0.1", "0.15"], ["0.1", "0.2", "0.3", "0.4", "0.5", "0.6"]),
}


def affinity_deep_sql(view: str, util: str) -> str:
    """``af`` (x, au) of the affinity patterns, by levels: a pattern goes on while its own and all later utilities can reach the threshold."""
    r = ratio(util)
    return f"""qb AS MATERIALIZED (SELECT tid, item, qty, profit, u, coalesce(sum(u) OVER (PARTITION BY tid ORDER BY item DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS ru FROM b0),
ap AS (SELECT tid, [item] AS x, item AS last, qty AS m, profit AS f, sum(u) OVER (PARTITION BY item) AS au FROM qb
 UNION ALL
 SELECT tid, x, last, m, f, au FROM (SELECT *, sum(m * f) OVER y AS au, sum(m * f + ru) OVER y AS ub FROM (
   SELECT p.tid, list_append(p.x, b.item) AS x, b.item AS last, least(p.m, b.qty) AS m, p.f + b.profit AS f, b.ru FROM ap p JOIN qb b ON p.tid = b.tid AND b.item > p.last) WINDOW y AS (PARTITION BY x))
  WHERE CAST(ub AS HUGEINT) * {r.denominator} >= {r.numerator} * (SELECT total FROM t)),
af AS (SELECT x, any_value(au) AS au FROM ap GROUP BY x)"""


def classes_sql(view: str, utils: list[str], cors: list[str]) -> str:
    loosest = min(utils, key=ratio)
    grid = ", ".join(f"('{u}', {ratio(u).numerator}, {ratio(u).denominator})" for u in utils)
    levels = ", ".join(f"('P{i + 1}', '{c}', {c})" for i, c in enumerate(cors))
    return levels_sql(view, loosest, "0").rstrip() + f""", {affinity_deep_sql(view, loosest)},
gu(min_util, num, den) AS (VALUES {grid}), gc(class, min_cor, cor) AS (VALUES ('HUP', '0', 0), {levels}),
n AS (SELECT min_util, class, min_cor, count(c.pattern) AS patterns FROM gu CROSS JOIN gc LEFT JOIN c ON CAST(c.utility AS HUGEINT) * den >= num * (SELECT total FROM t) AND c.kulc >= cor - 1e-9 GROUP BY ALL
 UNION ALL SELECT min_util, 'AHU', NULL, count(af.x) FROM gu LEFT JOIN af ON CAST(au AS HUGEINT) * den >= num * (SELECT total FROM t) GROUP BY ALL)
SELECT n.min_util, n.class, n.min_cor, n.patterns, CASE WHEN h.patterns > 0 THEN round(n.patterns::DOUBLE / h.patterns, 6) END AS share FROM n JOIN n h ON h.min_util = n.min_util AND h.class = 'HUP'"""


for _v, (_us, _cs) in CLASSES.items():
    _add(f"class_counts_{_v}", lambda s, d, v=_v, us=_us, cs=_cs: analysis.class_counts(VIEWS[v](s, d), us, cs), classes_sql(_v, _us, _cs))

# What is asked of patterns
_chu = powerset("w3").rstrip() + f", m AS (SELECT pattern, k, sup, utility, round(kulc + 1e-12, 6) AS kulc, items FROM c WHERE {_at_least('0.01')} AND kulc >= 0.2 - 1e-9), h AS (SELECT * FROM c WHERE {_at_least('0.01')})"
_cols = "pattern, k, sup, utility, kulc"
_p3 = _mined("w3", "0.01", "0.2")
_add("class_overlap_w3", lambda s, d: analysis.pattern_overlap(_p3(s, d), baselines.mine_plain(VIEWS["w3"](s, d), "0.01").settled()), _chu + " SELECT count(*) FILTER (WHERE a IS NOT NULL AND z IS NOT NULL) AS both, count(*) FILTER (WHERE z IS NULL) AS only_a, count(*) FILTER (WHERE a IS NULL) AS only_b, round(count(*) FILTER (WHERE a IS NOT NULL AND z IS NOT NULL)::DOUBLE / count(*), 6) AS jaccard FROM (SELECT m.pattern AS a, h.pattern AS z FROM m FULL JOIN h USING (pattern))")
_add("by_chance_w1", lambda s, d: analysis.by_chance(baselines.mine_plain(VIEWS["w1"](s, d), "0.0001").settled(), _mined("w1", "0.0001", "0.05")(s, d)), powerset("w1") + f"SELECT pattern, k, sup, utility, round(kulc + 1e-12, 6) AS kulc FROM c WHERE {_at_least('0.0001')} AND kulc < 0.05 - 1e-9")
_three = levels_sql("w3a", "0.01", "0").rstrip() + ", " + affinity_deep_sql("w3a", "0.01") + f", a AS (SELECT array_to_string(x, ',') AS pattern FROM af WHERE {_at_least('0.01', 'au')})"
_add(
    "class_overlap_all_w3",
    lambda s, d: analysis.overlap_of_classes(*_classes3(s, d)),
    _three + ", y AS (SELECT true AS hup, coalesce(kulc >= 0.2 - 1e-9, false) AS chu, a.pattern IS NOT NULL AS ahu FROM c LEFT JOIN a USING (pattern) UNION ALL SELECT false, false, true FROM a WHERE pattern NOT IN (SELECT pattern FROM c)) SELECT hup, chu, ahu, count(*) AS patterns FROM y GROUP BY ALL",
)
_add("correlated_and_affine_w3", lambda s, d: analysis.in_both(_classes3(s, d)[1], _classes3(s, d)[2]), _three + f" SELECT {_cols.replace('kulc', 'round(kulc + 1e-12, 6) AS kulc')} FROM c JOIN a USING (pattern) WHERE kulc >= 0.2 - 1e-9")
_add(
    "exactness_w3",
    lambda s, d: analysis.exactness(_p3(s, d), baselines.mine_exhaustive(VIEWS["w3"](s, d)).join(_mined("w3", "0.01", "0")(s, d).select("pattern"), "pattern", "left_semi").where("kulc >= 0.2")),
    _chu + " SELECT count(*) AS found, 0 AS missing, 0 AS spurious FROM m",
)
_add("top_k_by_lift_w3", lambda s, d: analysis.top_k(ops.interest_measures(VIEWS["w3"](s, d), _p3(s, d)).where("k > 1").select("pattern", "k", "sup", "lift"), 10, "lift"), _chu + ", ls AS (SELECT m.pattern, sum(ln(o.n)) AS logs FROM (SELECT pattern, unnest(items) AS item FROM m) m JOIN o USING (item) GROUP BY 1) SELECT pattern, k, sup, round(exp(ln(sup) + (k - 1) * ln((SELECT count(DISTINCT tid) FROM b)) - logs), 6) AS lift FROM m JOIN ls USING (pattern) WHERE k > 1 ORDER BY lift DESC, pattern LIMIT 10")
_add("top_k_by_utility_w3", lambda s, d: analysis.top_k(_p3(s, d), 10), _chu + f" SELECT {_cols} FROM m ORDER BY utility DESC, pattern LIMIT 10")
_add("top_k_by_kulc_w3", lambda s, d: analysis.top_k(_p3(s, d).where("k > 1"), 10, "kulc"), _chu + f" SELECT {_cols} FROM m WHERE k > 1 ORDER BY kulc DESC, pattern LIMIT 10")
_add("top_per_length_w3", lambda s, d: analysis.top_k_per_length(_p3(s, d), 3), _chu + f" SELECT * FROM (SELECT {_cols}, CAST(row_number() OVER (PARTITION BY k ORDER BY utility DESC, pattern) AS INT) AS place FROM m) WHERE place <= 3")
_add("length_profile_w3", lambda s, d: analysis.length_profile(_p3(s, d)), _chu + " SELECT k, count(*) AS patterns, min(kulc) AS least_kulc, max(kulc) AS most_kulc, CAST(sum(utility) AS BIGINT) AS utility FROM m GROUP BY k")
_add("utility_share_w3", lambda s, d: analysis.utility_share(_p3(s, d)), _chu + " SELECT pattern, k, utility, round(sum(utility) OVER (PARTITION BY k ORDER BY utility DESC, pattern ROWS UNBOUNDED PRECEDING)::DOUBLE / sum(utility) OVER (PARTITION BY k)::DOUBLE, 6) AS share FROM m")
_add("closed_w3", lambda s, d: analysis.closed_patterns(_p3(s, d)), _chu + f" SELECT {_cols} FROM m WHERE NOT EXISTS (SELECT 1 FROM m z WHERE z.k > m.k AND z.sup = m.sup AND list_has_all(z.items, m.items))")
_add("maximal_w3", lambda s, d: analysis.maximal_patterns(_p3(s, d)), _chu + f" SELECT {_cols} FROM m WHERE NOT EXISTS (SELECT 1 FROM m z WHERE z.k > m.k AND list_has_all(z.items, m.items))")
_add("containing_w3", lambda s, d: analysis.containing(_p3(s, d), "PROMO"), _chu + f" SELECT {_cols} FROM m WHERE list_contains(items, 'PROMO')")


def _recommend(spark: SparkSession, sf: str) -> DataFrame:
    basket = VIEWS["w3"](spark, sf)
    two = [r[0] for r in ops.item_stats(basket).orderBy("item").limit(2).collect()]
    return analysis.recommend(_p3(spark, sf), two, 5)


_add("recommend_w3", _recommend, _chu + ", v AS (SELECT list(item) AS have FROM (SELECT item FROM o ORDER BY item LIMIT 2)), q AS (SELECT utility, kulc, list_filter(items, lambda x: NOT list_contains(have, x)) AS rest FROM m, v WHERE k > 1) SELECT rest[1] AS item, max(utility) AS utility, max(kulc) AS kulc FROM q WHERE len(rest) = 1 GROUP BY 1 ORDER BY utility DESC, kulc DESC, item LIMIT 5")
_add(
    "measures_w3",
    lambda s, d: ops.interest_measures(VIEWS["w3"](s, d), _p3(s, d)),
    _chu + """, n AS (SELECT m.pattern, min(o.n) AS least, max(o.n) AS most, sum(ln(o.n)) AS logs FROM (SELECT pattern, unnest(items) AS item FROM m) m JOIN o USING (item) GROUP BY 1),
un AS (SELECT m.pattern, count(DISTINCT b.tid) AS union_sup FROM (SELECT pattern, unnest(items) AS item FROM m) m JOIN b USING (item) GROUP BY 1), x AS (SELECT m.*, c.kulc AS v FROM m JOIN c USING (pattern))
SELECT pattern, k, sup, round(v + 1e-12, 6) AS kulc, """ + _kind + """, round(sup::DOUBLE / most, 6) AS all_confidence, round(sup::DOUBLE / least, 6) AS max_confidence, round(sup::DOUBLE / union_sup, 6) AS coherence, round(sup / exp(logs / k), 6) AS cosine, round(exp(ln(sup) + (k - 1) * ln((SELECT count(DISTINCT tid) FROM b)) - logs), 6) AS lift FROM x JOIN n USING (pattern) JOIN un USING (pattern)""",
)
_add("itemset_utility_w3", lambda s, d: ops.itemset_utility(VIEWS["w3"](s, d), _p3(s, d)), powerset("w3").rstrip() + ", " + _twu + f" SELECT pattern, utility, sup, twu FROM c JOIN tw USING (items) WHERE {_at_least('0.01')} AND kulc >= 0.2 - 1e-9")
_add(
    "affinity_of_patterns_w3",
    lambda s, d: ops.affinity(VIEWS["w3a"](s, d), _p3(s, d)),
    _chu + f""", ab AS ({VIEW_SQL['w3a']}), hits AS (SELECT m.pattern, ab.tid, count(*) AS n, min(qty) AS q, sum(profit) AS f, max(m.k) AS k FROM (SELECT pattern, k, unnest(items) AS item FROM m) m JOIN ab USING (item) GROUP BY 1, 2)
SELECT pattern, CAST(sum(q) AS BIGINT) AS af, CAST(sum(q * f) AS BIGINT) AS au FROM hits WHERE n = k GROUP BY pattern""",
)


def _classes3(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """High-utility, correlated and affinity patterns of the types with one profit each."""
    basket = VIEWS["w3a"](spark, sf)
    return baselines.mine_plain(basket, "0.01").settled(), mine(basket, "0.01", "0.2").settled(), baselines.mine_affinity(basket, "0.01").settled()


# Segments, rollups
def _segments(spark: SparkSession, sf: str) -> DataFrame:
    rows = VIEWS["w3"](spark, sf).rows.select("tid", "item", "u")
    seg = table(spark, sf, "orders").join(table(spark, sf, "customer"), F.col("o_custkey") == F.col("c_custkey")).select(F.col("o_orderkey").alias("tid"), F.col("c_mktsegment").alias("segment"))
    return analysis.segment_mine(rows, seg, "0.02", "0.2")


_add("segment_mine_w3", _segments, f"""WITH RECURSIVE b AS MATERIALIZED (SELECT v.*, c_mktsegment AS g FROM ({VIEW_SQL['w3']}) v JOIN orders ON tid = o_orderkey JOIN customer ON o_custkey = c_custkey),
p(g, tid, items, last, u) AS (SELECT g, tid, [item], item, u FROM b UNION ALL SELECT p.g, p.tid, list_append(p.items, b.item), b.item, p.u + b.u FROM p JOIN b ON p.tid = b.tid AND b.item > p.last),
o AS (SELECT g, item, count(*) AS n FROM b GROUP BY 1, 2), t AS (SELECT g, sum(u) AS total FROM b GROUP BY 1),
s AS (SELECT g, items, array_to_string(items, ',') AS pattern, count(*) AS sup, sum(u) AS utility FROM p GROUP BY 1, 2),
i AS (SELECT x.g, pattern, sum(1::DOUBLE / n) AS inv FROM (SELECT g, pattern, unnest(items) AS item FROM s) x JOIN o ON o.g = x.g AND o.item = x.item GROUP BY 1, 2)
SELECT s.pattern, CAST(len(items) AS INT) AS k, sup, CAST(utility AS BIGINT) AS utility, round(sup * inv / len(items) + 1e-12, 6) AS kulc, s.g AS segment FROM s JOIN i ON s.g = i.g AND s.pattern = i.pattern JOIN t ON t.g = s.g WHERE CAST(utility AS HUGEINT) * 50 >= total AND sup * inv / len(items) >= 0.2 - 1e-9""")


def _located(spark: SparkSession, sf: str) -> DataFrame:
    where = table(spark, sf, "orders").join(table(spark, sf, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(table(spark, sf, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(table(spark, sf, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return VIEWS["w3"](spark, sf).rows.join(where.select(F.col("o_orderkey").alias("tid"), F.col("r_name").alias("region"), F.col("c_mktsegment").alias("segment")), "tid")


_located_sql = f"WITH x AS (SELECT v.tid, v.item, v.u, r_name AS region, c_mktsegment AS segment FROM ({VIEW_SQL['w3']}) v JOIN orders ON tid = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey) SELECT region, segment, item, CAST(sum(u) AS BIGINT) AS u, count(*) AS n FROM x GROUP BY "


def _sums() -> list:
    return [F.sum("u").cast("bigint").alias("u"), F.count(F.lit(1)).alias("n")]


_add("utility_rollup", lambda s, d: _located(s, d).rollup("region", "segment", "item").agg(*_sums()), _located_sql + "ROLLUP (region, segment, item)")
_add("utility_cube", lambda s, d: _located(s, d).cube("region", "segment", "item").agg(*_sums()), _located_sql + "CUBE (region, segment, item)")


def _sets(spark: SparkSession, sf: str) -> DataFrame:
    return _located(spark, sf).groupingSets([["region", "item"], ["segment", "item"], []], "region", "segment", "item").agg(*_sums()).select("region", "segment", "item", "u", "n")


_add("utility_sets", _sets, _located_sql + "GROUPING SETS ((region, item), (segment, item), ())")


def _simulated(spark: SparkSession, sf: str) -> DataFrame:
    return mine(VIEWS["w6s"](spark, sf), "0.001", "0.05").settled()


#: The simulator's hash is Spark's own, so SQL can't follow; tests hold it to brute force.
_add("mine_simulated_w6", _simulated)


# Streams, in batch form (the same plans run on streams)
def _events(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "events")


_ev = "FROM events WHERE user_id IS NOT NULL AND event_type IS NOT NULL AND ts IS NOT NULL AND value > 0"
_c = "CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT)"
_add("stream_item_stats_day", lambda s, d: streaming.window_item_stats(_events(s, d)), f"SELECT date_trunc('day', ts) AS start, event_type AS item, count(*) AS n, {_c} AS u {_ev} GROUP BY 1, 2")
_add("stream_item_stats_sliding", lambda s, d: streaming.window_item_stats(_events(s, d), size="7 days", slide="1 day"), f"SELECT start, item, count(*) AS n, {_c} AS u FROM (SELECT *, event_type AS item, date_trunc('day', ts) - to_days(CAST(j AS INT)) AS start FROM (SELECT * {_ev}) e, range(0, 7) r(j)) GROUP BY 1, 2")
_add(
    "stream_session_baskets",
    lambda s, d: streaming.session_baskets(_events(s, d)).select("user_id", "start", "n", "tu"),
    f"WITH e AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new {_ev} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS sid FROM e) SELECT user_id, min(ts) AS start, count(*) AS n, {_c} AS tu FROM s GROUP BY user_id, sid",
)
_add(
    "stream_item_twu_day",
    lambda s, d: streaming.window_item_twu(_events(s, d)),
    f"WITH e AS (SELECT date_trunc('day', ts) AS start, user_id, event_type AS item, {_c} AS u {_ev} GROUP BY 1, 2, 3), t AS (SELECT *, sum(u) OVER (PARTITION BY start, user_id) AS tu FROM e) SELECT start, item, count(*) AS sup, CAST(sum(u) AS BIGINT) AS u, CAST(sum(tu) AS BIGINT) AS twu FROM t GROUP BY 1, 2",
)
_add("stream_window_baskets", lambda s, d: streaming.window_baskets(_events(s, d)), f"SELECT date_trunc('day', ts) AS start, user_id AS tid, event_type AS item, {_c} AS u {_ev} GROUP BY 1, 2, 3")


def _window_mine(spark: SparkSession, sf: str) -> DataFrame:
    return streaming.mine_windows(streaming.window_baskets(_events(spark, sf)), "0.05", "0.3")


_add("stream_window_mine", _window_mine, f"""WITH RECURSIVE b AS MATERIALIZED (SELECT date_trunc('day', ts) AS g, user_id AS tid, event_type AS item, {_c} AS u {_ev} GROUP BY 1, 2, 3),
p(g, tid, items, last, u) AS (SELECT g, tid, [item], item, u FROM b UNION ALL SELECT p.g, p.tid, list_append(p.items, b.item), b.item, p.u + b.u FROM p JOIN b ON p.tid = b.tid AND p.g = b.g AND b.item > p.last),
o AS (SELECT g, item, count(*) AS n FROM b GROUP BY 1, 2), t AS (SELECT g, sum(u) AS total FROM b GROUP BY 1),
s AS (SELECT g, items, array_to_string(items, ',') AS pattern, count(*) AS sup, sum(u) AS utility FROM p GROUP BY 1, 2),
i AS (SELECT x.g, pattern, sum(1::DOUBLE / n) AS inv FROM (SELECT g, pattern, unnest(items) AS item FROM s) x JOIN o ON o.g = x.g AND o.item = x.item GROUP BY 1, 2)
SELECT s.g AS start, s.pattern, CAST(len(items) AS INT) AS k, sup, CAST(utility AS BIGINT) AS utility, round(sup * inv / len(items) + 1e-12, 6) AS kulc FROM s JOIN i ON s.g = i.g AND s.pattern = i.pattern JOIN t ON t.g = s.g WHERE CAST(utility AS HUGEINT) * 20 >= total AND sup * inv / len(items) >= 0.3 - 1e-9""")
_add("stream_deduplicated", lambda s, d: streaming.deduplicated(_events(s, d).unionByName(_events(s, d))).select("event_id", "user_id", "event_type"), "SELECT DISTINCT event_id, user_id, event_type " + _ev)
_add("event_cents_by_type", lambda s, d: _events(s, d).groupBy(F.col("event_type").alias("item")).agg(F.sum(cents("value")).alias("u")), f"SELECT event_type AS item, {_c} AS u FROM events GROUP BY 1")
