"""What every miner starts from: thresholds, ranked promising items, and transactions as sorted arrays.

The source is read once: its transactions are written, one row each. Statistics, totals and the
ranked transactions come from that table. A transaction's row holds its different items.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators.basket import ONE_SORT, SUM, rank_items
from ..scratch import written
from ..types import Basket, least_utility


def keep(df: DataFrame, held: list[DataFrame]) -> DataFrame:
    """Written to the shared folder: a level's plan never holds those before it."""
    df = written(df, "mined")
    held.append(df)
    return df


@dataclass
class Prepared:
    """tx: ``tid, tu, s``; s: ``item_rank, u, ru, sup`` (and ``qty, profit``) of the promising items by rank.

    total counts all rows, ``ru`` promising items only; ``most`` is the largest support of any item; ``items`` are ``item, item_rank, sup, inv``.
    """

    total: int
    least: int
    most: int
    items: DataFrame
    tx: DataFrame

    @property
    def rows(self) -> DataFrame:
        return self.tx.select("tid", "tu", F.explode("s").alias("e")).select("tid", "tu", "e.*")

    @property
    def entries(self) -> DataFrame:
        """One row for each place: ``tid, tu, at`` (from 1), ``e`` and the whole ``s``."""
        return self.tx.select("tid", "tu", "s", F.posexplode("s").alias("at", "e")).withColumn("at", F.col("at") + 1)


def later(s: str = "s", at: str = "at"):
    """The places behind ``at``."""
    return F.slice(F.col(s), F.col(at) + 1, F.size(s))


def prepare(basket: Basket, min_util, order: str, held: list[DataFrame], extra: tuple[str, ...] = ()) -> Prepared:
    fields = ["item", "u", *extra]
    tx = keep(basket.rows.groupBy("tid").agg(F.sum(F.col("u").cast(SUM)).alias("tu"), F.collect_list(F.struct(*fields)).alias("s")), held)
    flat = tx.select("tid", "tu", F.explode("s").alias("e")).select("tid", "tu", "e.*")
    stats = keep(flat.groupBy("item").agg(F.count(F.lit(1)).alias("sup"), F.sum("tu").cast(SUM).alias("twu"), F.sum(F.col("u").cast(SUM)).cast(SUM).alias("u")), held)
    whole, different, most = stats.coalesce(1).agg(F.coalesce(F.sum("u"), F.lit(0)), F.count(F.lit(1)), F.coalesce(F.max("sup"), F.lit(0))).first()
    total = int(whole)
    least = least_utility(min_util, total)
    items = rank_items(stats.where(F.col("twu") >= F.lit(least).cast(SUM)), order, different).select("item", F.col("item_rank").cast("int").alias("item_rank"), "sup", (1 / F.col("sup")).alias("inv"))
    if different > ONE_SORT:
        items = keep(items, held)
    behind = Window.partitionBy("tid").orderBy(F.desc("item_rank")).rowsBetween(Window.unboundedPreceding, -1)
    places = flat.join(items.select("item", "item_rank", "sup"), "item").withColumn("ru", F.coalesce(F.sum("u").over(behind), F.lit(0)))
    ordered = places.groupBy("tid").agg(F.max("tu").alias("tu"), F.array_sort(F.collect_list(F.struct("item_rank", "u", "ru", "sup", *extra))).alias("s"))
    return Prepared(total, least, int(most), items, keep(ordered, held))


__all__ = ["Prepared", "keep", "later", "prepare"]
