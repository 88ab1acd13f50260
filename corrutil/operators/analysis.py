"""What is asked of mined patterns: grids of counts, classes compared, closed and maximal ones, recommendations, segments."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import EPS
from ..plans.baselines import mine_affinity
from ..plans.keyed import mine_keyed
from ..plans.levels import mine
from ..scratch import written
from ..types import Basket, least_utility, ratio
from .basket import SUM, total_utility


def pattern_counts(basket: Basket, utils: Iterable, cors: Iterable, **how) -> DataFrame:
    """``min_util, min_cor, patterns`` for each pair of thresholds, from one mining run at the loosest ones."""
    utils, cors = list(utils), list(cors)
    spark = basket.rows.sparkSession
    total = total_utility(basket)
    found = mine(basket, min(utils, key=ratio), min(cors, key=ratio), **how).settled(exact=True)
    grid = spark.createDataFrame([(str(u), str(c), least_utility(u, total), float(ratio(c))) for u in utils for c in cors], "min_util string, min_cor string, least bigint, cor double")
    # The grid is a few dozen rows that the caller names.
    pairs = F.broadcast(grid)
    hit = found.join(pairs, (F.col("utility") >= F.col("least")) & (F.col("kulc") >= F.col("cor") - EPS))
    counted = hit.groupBy("min_util", "min_cor").agg(F.count(F.lit(1)).alias("n"))
    return grid.join(counted, ["min_util", "min_cor"], "left").select("min_util", "min_cor", F.coalesce("n", F.lit(0)).alias("patterns"))


def class_counts(basket: Basket, utils: Iterable, cors: Iterable) -> DataFrame:
    """``min_util, class, min_cor, patterns, share``: high-utility (HUP), affinity (AHU) and correlated patterns (P1, P2, ... by threshold).

    Share is that of the high-utility patterns. The basket needs ``qty, profit``. Two mining runs, at the loosest thresholds, give the whole table.
    """
    utils, cors = list(utils), list(cors)
    spark = basket.rows.sparkSession
    total, loosest = total_utility(basket), min(utils, key=ratio)
    plain = mine(basket, loosest, 0, use_spk=False, ratio_cut=False).settled(exact=True).select(F.col("utility").cast(SUM).alias("value"), "kulc")
    affine = mine_affinity(basket, loosest).settled().select(F.col("au").cast(SUM).alias("value"), F.lit(None).cast("double").alias("kulc"))
    classes = [("HUP", "0", 0.0), *((f"P{i + 1}", str(c), float(ratio(c))) for i, c in enumerate(cors)), ("AHU", None, None)]
    grid = spark.createDataFrame([(str(u), least_utility(u, total), *c) for u in utils for c in classes], f"min_util string, least {SUM}, class string, min_cor string, cor double".replace(SUM, "bigint"))
    # The grid is a few dozen rows that the caller names.
    both = plain.unionByName(affine)
    fits = (F.col("value") >= F.col("least")) & F.col("kulc").isNull().eqNullSafe(F.col("cor").isNull()) & (F.col("cor").isNull() | (F.col("kulc") >= F.col("cor") - EPS))
    counted = both.join(F.broadcast(grid), fits).groupBy("min_util", "class").agg(F.count(F.lit(1)).alias("n"))
    counts = grid.join(counted, ["min_util", "class"], "left").select("min_util", "class", "min_cor", F.coalesce("n", F.lit(0)).alias("patterns"))
    hup = counts.where("class = 'HUP'").select("min_util", F.col("patterns").alias("all"))
    return counts.join(hup, "min_util").select("min_util", "class", "min_cor", "patterns", F.round(F.when(F.col("all") > 0, F.col("patterns") / F.col("all")), 6).alias("share"))


def count_steps(counts: DataFrame) -> DataFrame:
    """Each count beside the one at the next lower correlation threshold; ``falls`` is true if it does not rise."""
    w = Window.partitionBy("min_util").orderBy(F.col("min_cor").cast("double"))
    return counts.withColumn("before", F.lag("patterns").over(w)).withColumn("falls", F.coalesce(F.col("patterns") <= F.col("before"), F.lit(True)))


def pattern_overlap(a: DataFrame, b: DataFrame) -> DataFrame:
    """``both, only_a, only_b, jaccard`` of two pattern classes."""
    x, y = a.select("pattern", F.lit(1).alias("in_a")), b.select("pattern", F.lit(1).alias("in_b"))
    n = lambda c: F.coalesce(F.sum(c.cast("bigint")), F.lit(0))
    both = F.col("in_a").isNotNull() & F.col("in_b").isNotNull()
    out = x.join(y, "pattern", "full_outer").agg(n(both).alias("both"), n(F.col("in_b").isNull()).alias("only_a"), n(F.col("in_a").isNull()).alias("only_b"))
    whole = F.col("both") + F.col("only_a") + F.col("only_b")
    return out.withColumn("jaccard", F.round(F.when(whole > 0, F.col("both") / whole).otherwise(0.0), 6))


def overlap_of_classes(plain: DataFrame, correlated: DataFrame, affine: DataFrame) -> DataFrame:
    """``hup, chu, ahu, patterns``: how many patterns are in each combination of the three classes."""
    named = [df.select("pattern", F.lit(n).alias("n")) for n, df in (("hup", plain), ("chu", correlated), ("ahu", affine))]
    every = named[0].unionByName(named[1]).unionByName(named[2])
    flags = every.groupBy("pattern").agg(*(F.bool_or(F.col("n") == c).alias(c) for c in ("hup", "chu", "ahu")))
    return flags.groupBy("hup", "chu", "ahu").agg(F.count(F.lit(1)).alias("patterns"))


def in_both(a: DataFrame, b: DataFrame) -> DataFrame:
    """Patterns of ``a`` that ``b`` has too."""
    return a.join(b.select("pattern"), "pattern", "left_semi")


def exactness(found: DataFrame, expected: DataFrame) -> DataFrame:
    """``found, missing, spurious``: patterns given, expected ones not among them, and those not expected."""
    x, y = found.select("pattern", F.lit(True).alias("x")), expected.select("pattern", F.lit(True).alias("y"))
    n = lambda c: F.coalesce(F.sum(c.cast("bigint")), F.lit(0))
    return x.join(y, "pattern", "full_outer").agg(n(F.col("x").isNotNull()).alias("found"), n(F.col("x").isNull()).alias("missing"), n(F.col("y").isNull()).alias("spurious"))


def by_chance(plain: DataFrame, correlated: DataFrame) -> DataFrame:
    """High-utility patterns that are not correlated."""
    return plain.join(correlated.select("pattern"), "pattern", "left_anti")


def top_k(patterns: DataFrame, n: int, by: str = "utility") -> DataFrame:
    return patterns.orderBy(F.desc(by), "pattern").limit(n)


def top_k_per_length(patterns: DataFrame, n: int, by: str = "utility") -> DataFrame:
    w = Window.partitionBy("k").orderBy(F.desc(by), "pattern")
    return patterns.withColumn("place", F.row_number().over(w)).where(F.col("place") <= n)


def length_profile(patterns: DataFrame) -> DataFrame:
    return patterns.groupBy("k").agg(F.count(F.lit(1)).alias("patterns"), F.min("kulc").alias("least_kulc"), F.max("kulc").alias("most_kulc"), F.sum("utility").cast("bigint").alias("utility"))


def utility_share(patterns: DataFrame) -> DataFrame:
    """Patterns of each length by utility, with the share of the length's utility up to them.

    Running sums are made in ranges of patterns, and each range starts from the sum of those before it, so a length is not one task.
    """
    keys = [F.col("k"), F.desc("utility"), F.col("pattern")]
    dealt = written(patterns.select("pattern", "k", "utility").repartitionByRange(*keys).withColumn("part", F.spark_partition_id()), "ranges")
    own = F.col("utility").cast(SUM)
    sums = dealt.groupBy("k", "part").agg(F.sum(own).alias("s"))
    # One row for each range and length.
    before = Window.partitionBy("k").orderBy("part")
    starts = sums.withColumn("start", F.sum("s").over(before) - F.col("s")).withColumn("whole", F.sum("s").over(Window.partitionBy("k"))).select("k", "part", "start", "whole")
    run = Window.partitionBy("k", "part").orderBy(F.desc("utility"), "pattern").rowsBetween(Window.unboundedPreceding, 0)
    placed = dealt.withColumn("upto", F.sum(own).over(run)).join(starts, ["k", "part"])
    return placed.select("pattern", "k", "utility", F.round((F.col("start") + F.col("upto")).cast("double") / F.col("whole").cast("double"), 6).alias("share"))


def _supersets(patterns: DataFrame, same_support: bool) -> DataFrame:
    """``pattern``: those with a larger one, found over the item of the pattern that the fewest patterns hold, then tested for containment."""
    items = patterns.select("pattern", "k", "sup", F.split("pattern", ",").alias("items"))
    each = items.select("pattern", "k", "sup", "items", F.explode("items").alias("item"))
    often = each.groupBy("item").agg(F.count(F.lit(1)).alias("n"))
    small = each.join(often, "item").groupBy("pattern", "k", "sup", "items").agg(F.min(F.struct("n", "item")).alias("r")).select("pattern", "k", "sup", "items", F.col("r.item").alias("item"))
    large = each.select("item", F.col("k").alias("large_k"), F.col("sup").alias("large_sup"), F.col("items").alias("large_items"))
    match = small["item"] == large["item"]
    if same_support:
        match = match & (F.col("sup") == F.col("large_sup"))
    held = small.join(large, match & (F.col("large_k") > F.col("k")) & (F.size(F.array_except("items", "large_items")) == 0), "left_semi")
    return held.select("pattern")


def closed_patterns(patterns: DataFrame) -> DataFrame:
    """Patterns with no larger one of the same support among them."""
    return patterns.join(_supersets(patterns, True), "pattern", "left_anti")


def maximal_patterns(patterns: DataFrame) -> DataFrame:
    """Patterns with no larger one among them."""
    return patterns.join(_supersets(patterns, False), "pattern", "left_anti")


def containing(patterns: DataFrame, item: str) -> DataFrame:
    return patterns.where(F.array_contains(F.split("pattern", ","), item))


def recommend(patterns: DataFrame, basket_items: list[str], n: int) -> DataFrame:
    """``item, utility, kulc``: the items that would complete patterns of which the basket holds the rest, best utility first."""
    have = F.array(*(F.lit(x) for x in basket_items)) if basket_items else F.array().cast("array<string>")
    missing = F.array_except(F.split("pattern", ","), have)
    near = patterns.where((F.col("k") > 1) & (F.size(missing) == 1)).select(F.element_at(missing, 1).alias("item"), "utility", "kulc")
    return near.groupBy("item").agg(F.max("utility").alias("utility"), F.max("kulc").alias("kulc")).orderBy(F.desc("utility"), F.desc("kulc"), "item").limit(n)


def segment_mine(rows: DataFrame, segments: DataFrame, min_util, min_cor) -> DataFrame:
    """Patterns of each segment by itself, all in one run. rows: ``tid, item, u``; segments: ``tid, segment``.

    Totals, supports and thresholds are a segment's own. Transactions without a segment are left out; no rows, no patterns.
    """
    placed = rows.select("tid", "item", "u").join(segments.where("segment IS NOT NULL").select("tid", "segment"), "tid")
    return mine_keyed(placed, "segment", min_util, min_cor)
