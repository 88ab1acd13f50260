"""Baskets and the quantities defined on them."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import all_confidence, coherence, correlation_kind, cosine, kulc, lift, max_confidence, shown
from ..scratch import written
from ..types import Basket

#: Sums of utilities; at 100 TB a 64-bit total overflows.
SUM = "decimal(38,0)"
#: Items up to which ranks come from one sorted partition.
ONE_SORT = 1_000_000


def explode_records(tx: DataFrame) -> DataFrame:
    """Nested transactions to rows ``tid, item, qty``."""
    return tx.select("tid", F.explode("record").alias("r")).select("tid", F.col("r.item").alias("item"), F.col("r.qty").alias("qty"))


def build_basket(rows: DataFrame, profit: DataFrame | None = None) -> Basket:
    """From ``tid, item, qty`` and ``item, unit_profit``, or from ``tid, item, u``.

    Rows of one item in one transaction are summed. A row without id or item, with a
    quantity, profit or utility that is missing or not positive, goes to ``rejected``.
    """
    if profit is None:
        reason = F.when(F.col("tid").isNull(), "no transaction").when(F.col("item").isNull(), "no item").when(F.coalesce("u", F.lit(0)) <= 0, "utility not positive")
        marked = rows.withColumn("reason", reason)
        good = marked.where("reason IS NULL").groupBy("tid", "item").agg(F.sum("u").cast("bigint").alias("u"))
        return Basket(good, marked.where("reason IS NOT NULL"))
    reason = (
        F.when(F.col("tid").isNull(), "no transaction").when(F.col("item").isNull(), "no item").when(F.coalesce("qty", F.lit(0)) <= 0, "quantity not positive")
        .when(F.col("unit_profit").isNull(), "no profit").when(F.col("unit_profit") <= 0, "profit not positive")
    )
    marked = rows.join(profit, "item", "left").withColumn("reason", reason)
    good = marked.where("reason IS NULL").groupBy("tid", "item").agg(F.sum("qty").cast("bigint").alias("qty"), F.max("unit_profit").alias("profit"))
    return Basket(good.select("tid", "item", "qty", "profit", (F.col("qty") * F.col("profit")).alias("u")), marked.where("reason IS NOT NULL"))


def item_utility(basket: Basket) -> DataFrame:
    return basket.rows.select("tid", "item", "u")


def transaction_utility(basket: Basket) -> DataFrame:
    return basket.rows.groupBy("tid").agg(F.sum("u").cast("bigint").alias("tu"))


def total_utility(basket: Basket) -> int:
    return int(basket.rows.agg(F.coalesce(F.sum(F.col("u").cast(SUM)), F.lit(0).cast(SUM))).first()[0])


def with_tu(rows: DataFrame) -> DataFrame:
    return rows.withColumn("tu", F.sum("u").over(Window.partitionBy("tid")))


def item_stats(basket: Basket) -> DataFrame:
    """``item, sup, twu, u``: one shuffle by transaction, one (pre-aggregated) by item."""
    return with_tu(basket.rows).groupBy("item").agg(F.count(F.lit(1)).alias("sup"), F.sum(F.col("tu").cast(SUM)).alias("twu"), F.sum(F.col("u").cast(SUM)).alias("u"))


ORDERS = {"support_asc": ["sup", "item"], "twu_asc": ["twu", "item"], "lexicographic": ["item"]}


def rank_items(stats: DataFrame, order: str = "support_asc", most: int | None = None) -> DataFrame:
    """``stats`` and ``item_rank`` from 1. Many items are ranked by a range-partitioned sort; ``most``: a bound of their number, where known."""
    keys = ORDERS[order]
    if (stats.limit(ONE_SORT + 1).count() if most is None else most) <= ONE_SORT:
        return stats.coalesce(1).withColumn("item_rank", F.row_number().over(Window.orderBy(*keys)))
    dealt = stats.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("__at", F.monotonically_increasing_id())
    # Written, as places must not change between the two reads.
    dealt = written(dealt, "ranked")
    part = F.shiftright("__at", 33)
    offsets, seen = [], 0
    for p, n in sorted(tuple(r) for r in dealt.groupBy(part).count().collect()):  # a row for each partition
        offsets.append((p, seen))
        seen += n
    if not offsets:
        # None is left to rank, as where no item of many reaches a threshold.
        return dealt.withColumn("item_rank", F.lit(None).cast("int")).drop("__at")
    start = F.create_map(*(F.lit(x) for pair in offsets for x in pair))
    return dealt.withColumn("item_rank", (start[part] + F.col("__at").bitwiseAND((1 << 33) - 1) + 1).cast("int")).drop("__at")


def remaining_utility(basket: Basket, ranks: DataFrame) -> DataFrame:
    """``tid, item, item_rank, u, ru``: ru sums the utilities of the later items of the transaction."""
    later = Window.partitionBy("tid").orderBy(F.desc("item_rank")).rowsBetween(Window.unboundedPreceding, -1)
    return basket.rows.join(ranks.select("item", "item_rank"), "item").withColumn("ru", F.coalesce(F.sum("u").over(later), F.lit(0))).select("tid", "item", "item_rank", "u", "ru")


def initial_lists(basket: Basket, ranks: DataFrame) -> DataFrame:
    """The list of each item: ``item, tid, iu, ru``."""
    return remaining_utility(basket, ranks).select("item", "tid", F.col("u").alias("iu"), "ru")


def list_totals(lists: DataFrame, key: str = "item") -> DataFrame:
    return lists.groupBy(key).agg(F.count(F.lit(1)).alias("sup"), F.sum("iu").cast("bigint").alias("iu"), F.sum("ru").cast("bigint").alias("ru"))


def extend_lists(lists: DataFrame, rows: DataFrame) -> DataFrame:
    """Lists of patterns with one later item more, from co-occurrence alone.

    lists: ``ranks, last, tid, iu, ru``; rows: ``tid, item_rank, u, ru``. Also ``joint``: the parent's bound in the transaction.
    """
    a, b = lists.alias("a"), rows.alias("b")
    found = a.join(b, (F.col("a.tid") == F.col("b.tid")) & (F.col("b.item_rank") > F.col("a.last")))
    return found.select(F.concat("a.ranks", F.array("b.item_rank")).alias("ranks"), F.col("b.item_rank").alias("last"), F.col("a.tid").alias("tid"), (F.col("a.iu") + F.col("b.u")).alias("iu"), F.col("b.ru").alias("ru"), (F.col("a.iu") + F.col("a.ru")).alias("joint"))


def covering_rows(basket: Basket, patterns: DataFrame) -> DataFrame:
    """``pattern, tid`` with sums over the pattern's items, for transactions that hold all of them.

    patterns: ``pattern`` (items joined by commas). A pattern meets only the transactions of its rarest item; whether
    one holds the rest is tested within its row.
    """
    more = ["qty", "profit"] if {"qty", "profit"} <= set(basket.rows.columns) else []
    tx = basket.rows.groupBy("tid").agg(F.sum("u").alias("tu"), F.collect_list(F.struct("item", "u", *more)).alias("s"))
    sups = basket.rows.groupBy("item").agg(F.count(F.lit(1)).alias("n"))
    named = patterns.select("pattern").distinct().withColumn("items", F.split("pattern", ","))
    rarest = named.select("pattern", "items", F.explode("items").alias("item")).join(sups, "item", "left").groupBy("pattern", "items").agg(F.min(F.struct(F.coalesce("n", F.lit(0)), "item")).alias("r")).select("pattern", "items", F.col("r.item").alias("rarest"))
    met = rarest.join(tx.select("tid", "tu", "s", F.explode("s.item").alias("rarest")), "rarest")
    whole = met.withColumn("h", F.filter("s", lambda e: F.array_contains("items", e["item"]))).where(F.size("h") == F.size("items"))
    total = lambda f: F.aggregate("h", F.lit(0).cast("bigint"), lambda acc, e: acc + e[f])
    extra = [F.array_min("h.qty").alias("min_qty"), total("profit").alias("profits")] if more else []
    return whole.select("pattern", "tid", F.size("items").alias("k"), total("u").alias("u"), "tu", *extra)


def itemset_utility(basket: Basket, patterns: DataFrame) -> DataFrame:
    return covering_rows(basket, patterns).groupBy("pattern").agg(F.sum("u").cast("bigint").alias("utility"), F.count(F.lit(1)).alias("sup"), F.sum("tu").cast("bigint").alias("twu"))


def affinity(basket: Basket, patterns: DataFrame) -> DataFrame:
    """``pattern, af, au``: least quantity in each transaction, summed; times the unit profits."""
    return covering_rows(basket, patterns).groupBy("pattern").agg(F.sum("min_qty").cast("bigint").alias("af"), F.sum(F.col("min_qty") * F.col("profits")).cast("bigint").alias("au"))


def interest_measures(basket: Basket, patterns: DataFrame) -> DataFrame:
    """``pattern, k, sup, kulc, kind`` and the other measures of given patterns."""
    named = patterns.select("pattern").distinct().withColumn("item", F.explode(F.split("pattern", ",")))
    sups = basket.rows.groupBy("item").agg(F.count(F.lit(1)).alias("s"))
    per = named.join(sups, "item").groupBy("pattern").agg(F.count(F.lit(1)).alias("k"), F.min("s").alias("least"), F.max("s").alias("most"), F.sum(1 / F.col("s")).alias("inv"), F.sum(F.log(F.col("s").cast("double"))).alias("logs"))
    united = named.join(basket.rows.select("item", "tid"), "item").select("pattern", "tid").distinct().groupBy("pattern").agg(F.count(F.lit(1)).alias("union_sup"))
    both = itemset_utility(basket, patterns).join(per, "pattern").join(united, "pattern")
    whole = basket.rows.agg(F.countDistinct("tid").alias("whole"))
    both = both.crossJoin(F.broadcast(whole))  # one row
    value = kulc("sup", "inv", "k")
    r = lambda c: F.round(c, 6)
    return both.select("pattern", F.col("k").cast("int").alias("k"), "sup", shown(value).alias("kulc"), correlation_kind(value).alias("kind"), r(all_confidence("sup", "most")).alias("all_confidence"), r(max_confidence("sup", "least")).alias("max_confidence"), r(coherence("sup", "union_sup")).alias("coherence"), r(cosine("sup", "logs", "k")).alias("cosine"), r(lift("sup", "logs", "k", "whole")).alias("lift"))

