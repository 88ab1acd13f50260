"""The correlated miner over many independent baskets at once, told apart by a key.

Totals, thresholds, supports and the support order are those of each key; a level is one join
and one aggregation for all keys, so the number of jobs follows the longest pattern, not the keys.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import EPS, pattern_text, shown
from ..operators.basket import SUM
from ..scratch import delete_tables
from ..scratch import written as scratch
from ..types import ratio
from .prepare import keep


def mine_keyed(rows: DataFrame, key: str, min_util, min_cor) -> DataFrame:
    """``pattern, k, sup, utility, kulc`` and the key, from ``key, tid, item, u``: all patterns of each key's own basket.

    Written; the levels' tables are deleted. No rows: no patterns.
    """
    util, cor = ratio(min_util), float(ratio(min_cor))
    held: list[DataFrame] = []

    def written(df: DataFrame, name: str) -> DataFrame:
        return keep(df, held)

    rows = written(rows.select(F.col(key).alias("g"), "tid", "item", F.col("u").cast(SUM).alias("u")), "keyed")
    limits = rows.groupBy("g").agg(F.sum("u").alias("total")).select("g", F.expr(f"cast((total * {util.numerator} + {util.denominator - 1}) div {util.denominator} as {SUM})").alias("least"))
    with_tu = rows.withColumn("tu", F.sum("u").over(Window.partitionBy("g", "tid")).cast(SUM))
    stats = with_tu.groupBy("g", "item").agg(F.count(F.lit(1)).alias("sup"), F.sum("tu").alias("twu")).join(limits, "g").where("twu >= least")
    items = written(stats.select("g", "item", "sup", "least", F.row_number().over(Window.partitionBy("g").orderBy("sup", "item")).alias("item_rank")), "keyed-items")
    later = Window.partitionBy("g", "tid").orderBy(F.desc("item_rank")).rowsBetween(Window.unboundedPreceding, -1)
    ranked = rows.join(items, ["g", "item"]).select("g", "tid", "item_rank", "u", F.coalesce(F.sum("u").over(later), F.lit(0)).cast(SUM).alias("ru"), (1 / F.col("sup")).alias("inv"), "least")
    ranked = written(ranked, "keyed-rows")
    lists = ranked.select("g", "tid", F.array("item_rank").alias("ranks"), F.col("item_rank").alias("last"), F.col("u").alias("iu"), "ru", F.col("inv").alias("inv_sup"), "least")
    emitted = []
    k = 1
    while True:
        level = lists.groupBy("g", "ranks").agg(F.count(F.lit(1)).alias("sup"), F.sum("iu").alias("iu"), F.sum("ru").alias("ru"), F.first("inv_sup").alias("inv_sup"), F.first("least").alias("least"))
        level = written(level.withColumn("k", F.lit(k)).withColumn("kulc", F.col("sup") * F.col("inv_sup") / k).where(F.col("kulc") >= cor - EPS), "keyed-level")
        emitted.append(level.where("iu >= least").select("g", "ranks", "k", "sup", "iu", "kulc"))
        # Along the support order Kulc never rises, and no extension has more than the utility and what remains.
        grow = level.where("iu + ru >= least").select("g", "ranks")
        if grow.isEmpty():
            break
        a = lists.join(grow, ["g", "ranks"], "left_semi").alias("a")
        joined = a.join(ranked.alias("b"), (F.col("a.g") == F.col("b.g")) & (F.col("a.tid") == F.col("b.tid")) & (F.col("b.item_rank") > F.col("a.last")))
        lists = written(
            joined.select(
                "a.g", "a.tid", F.concat("a.ranks", F.array("b.item_rank")).alias("ranks"), F.col("b.item_rank").alias("last"), (F.col("a.iu") + F.col("b.u")).cast(SUM).alias("iu"), "b.ru",
                (F.col("a.inv_sup") + F.col("b.inv")).alias("inv_sup"), "a.least",
            ),
            "keyed-lists",
        )
        k += 1
    out = emitted[0]
    for more in emitted[1:]:
        out = out.unionByName(more)
    spelled = out.withColumn("item_rank", F.explode("ranks")).join(items.select("g", "item_rank", "item"), ["g", "item_rank"])
    found = spelled.groupBy("g", "ranks", "k", "sup", "iu", "kulc").agg(pattern_text(F.collect_list("item")).alias("pattern")).select("pattern", "k", "sup", F.col("iu").cast("bigint").alias("utility"), shown("kulc").alias("kulc"), F.col("g").alias(key))
    out = scratch(found, "patterns")
    delete_tables(*held)
    return out
