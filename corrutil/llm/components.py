"""Connected components of a graph of links, by shuffles alone.

Large-star and small-star steps in turn: each moves links towards smaller
nodes and keeps components; the links end as stars around each component's least
node. Every round is written to the shared folder. A hot node is aggregated
map-side (its least neighbour), never gathered.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .scratch import discard, written


def _large_star(links: DataFrame) -> DataFrame:
    """Each node links its larger neighbours to the least of its neighbours and itself."""
    both = links.select(F.col("a").alias("n"), F.col("b").alias("m")).unionByName(links.select(F.col("b").alias("n"), F.col("a").alias("m")))
    least = both.groupBy("n").agg(F.least(F.min("m"), F.col("n")).alias("low"))
    return both.join(least, "n").where("m > n").select(F.col("m").alias("a"), F.col("low").alias("b")).where("a <> b").distinct()


def _small_star(links: DataFrame) -> DataFrame:
    """Each node links its smaller neighbours and itself to the least of them."""
    down = links.select(F.greatest("a", "b").alias("n"), F.least("a", "b").alias("m"))
    least = down.groupBy("n").agg(F.min("m").alias("low"))
    return down.join(least, "n").select(F.col("m").alias("a"), F.col("low").alias("b")).where("a <> b").unionByName(least.select(F.col("n").alias("a"), F.col("low").alias("b"))).distinct()


def components(links: DataFrame, *, max_rounds: int = 60) -> DataFrame:
    """``node, root`` of every node of the links ``a, b``; root is the component's least node."""
    now = written(links.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "links")
    before = None
    for _ in range(max_rounds):
        mark = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if mark[0] == 0 or mark == before:
            break
        before = mark
        after = written(_small_star(_large_star(now)), "links")
        discard(now)
        now = after
    else:
        raise RuntimeError("components did not settle")
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("root"))).distinct()
