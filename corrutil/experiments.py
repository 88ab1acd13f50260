"""The reference's experiments as workloads: search effort, run time and memory of each variant over grids of thresholds."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession

from .plans.baselines import mine_projection
from .plans.levels import VARIANTS, mine_variant
from .scratch import delete_tables, written
from .types import Basket, MiningResult

#: What is compared: four variants of the correlated miner, and the projection baseline.
METHODS: dict[str, Callable[..., MiningResult]] = {
    **{name: (lambda basket, util, cor, n=name, **how: mine_variant(basket, util, cor, n, **how)) for name in VARIANTS},
    "projection": lambda basket, util, cor, **how: mine_projection(basket, util, cor),
}


def effort(basket: Basket, pairs: Iterable[tuple[str, str]], methods: Iterable[str] = METHODS) -> DataFrame:
    """``method, min_util, min_cor, visited, joined, la_cut, patterns, tuples``: the work of each method at each pair of thresholds.

    Nodes visited, pairs of lists that met, pairs cut by the joint bound, patterns found, and list entries of the visited.
    """
    spark = basket.rows.sparkSession
    rows, basket = [], Basket(written(basket.rows, "basket"))
    for util, cor in pairs:
        for name in methods:
            r = METHODS[name](basket, util, cor)
            n = r.patterns.count()
            rows.append((name, str(util), str(cor), *(r.total(x) for x in ("visited", "joined", "la_cut")), n, r.total("tuples")))
            r.close()
    delete_tables(basket.rows)
    schema = "method string, min_util string, min_cor string, visited bigint, joined bigint, la_cut bigint, patterns bigint, tuples bigint"
    return spark.createDataFrame(rows, schema)


def _pools(spark: SparkSession) -> list:
    beans = spark.sparkContext._jvm.java.lang.management.ManagementFactory.getMemoryPoolMXBeans()
    return [b for b in beans if str(b.getType()) == "Heap memory"]


def measured(spark: SparkSession, run: Callable[[], MiningResult]) -> dict:
    """Seconds, patterns, effort, the most list entries held at once, and the peak heap of this JVM in MB.

    The heap is that of the driver's JVM, which in local mode is all there is; it is set back by a collection before the run.
    """
    spark.sparkContext._jvm.System.gc()
    for pool in _pools(spark):
        pool.resetPeakUsage()
    began = time.time()
    result = run()
    n = result.patterns.count()
    seconds = time.time() - began
    heap = sum(int(p.getPeakUsage().getUsed()) for p in _pools(spark)) >> 20
    out = {"seconds": round(seconds, 3), "patterns": n, **{x: result.total(x) for x in ("visited", "joined", "la_cut", "tuples")}, "peak_tuples": max([c.get("peak", 0) or 0 for c in result.counters] or [0]), "peak_heap_mb": heap}
    result.close()
    return out


def run_grid(spark: SparkSession, basket: Basket, utils: list[str], cors: list[str], methods: Iterable[str] = METHODS, done: Callable[[dict], None] | None = None) -> list[dict]:
    """Each method at every utility threshold with the middle correlation threshold, and the other way round."""
    pairs = dict.fromkeys([*((u, cors[len(cors) // 2]) for u in utils), *((utils[len(utils) // 2], c) for c in cors)])
    out = []
    for util, cor in pairs:
        for name in methods:
            row = {"method": name, "min_util": util, "min_cor": cor, **measured(spark, lambda: METHODS[name](basket, util, cor))}
            out.append(row)
            if done:
                done(row)
    return out


def compared(rows: list[dict], against: str = "projection") -> list[dict]:
    """Each row with how many times as long, and how many times the entries, the method ``against`` took at its thresholds."""
    base = {(r["min_util"], r["min_cor"]): r for r in rows if r["method"] == against}
    out = []
    for r in rows:
        b = base.get((r["min_util"], r["min_cor"]))
        more = {} if b is None else {"speed_up": round(b["seconds"] / max(r["seconds"], 1e-3), 2), "entries_ratio": round(b["tuples"] / max(r["tuples"], 1), 2), "heap_ratio": round(b["peak_heap_mb"] / max(r["peak_heap_mb"], 1), 2)}
        out.append(r | more)
    return out
