"""Baselines: plain-utility, two-phase, merging projection, affinity, projection, tree growth, exhaustive, frequent patterns."""

from __future__ import annotations

from collections.abc import Iterator
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import EPS, pattern_text, shown
from ..operators.basket import SUM
from ..types import Basket, MiningResult, ratio
from .levels import mine, named
from .prepare import Prepared, keep, later, prepare


def mine_plain(basket: Basket, min_util, *, pair_twu: bool = True, use_la: bool = False, max_k: int | None = None, plan: str = "auto") -> MiningResult:
    """All high-utility patterns by lists in the order of TWU, with the pair filter or without."""
    return mine(basket, min_util, 0, use_spk=False, use_la=use_la, item_order="twu_asc", pair_twu=pair_twu, max_k=max_k, plan=plan)


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for more in frames[1:]:
        out = out.unionByName(more)
    return out


def _seen(level: DataFrame, *more) -> list[int]:
    return [int(x or 0) for x in level.coalesce(1).agg(F.count(F.lit(1)), *more).first()]


def mine_two_phase(basket: Basket, min_util, *, max_k: int | None = None) -> MiningResult:
    """Level-wise candidates by TWU alone, then one verifying pass."""
    held: list[DataFrame] = []
    p = prepare(basket, min_util, "support_asc", held)
    limit = F.lit(p.least).cast(SUM)
    pairs = p.entries.select(F.lit(0).cast("bigint").alias("pid"), F.col("e.item_rank").alias("b"), "tid", "tu", "at")
    before = None
    found, counters, k = [], [], 1
    while True:
        level = pairs.groupBy("pid", "b").agg(F.count(F.lit(1)).alias("sup"), F.sum(F.col("tu").cast(SUM)).alias("twu")).where(F.col("twu") >= limit)
        level = keep(_numbered(level, before), held)
        n = _seen(level)[0]
        counters.append({"k": k, "candidates": n})
        if not n:
            break
        found.append(level.select("ranks"))
        if k == max_k:
            break
        lists = keep(pairs.join(level.select(F.col("parent").alias("pid"), "b", F.col("pid").alias("child")), ["pid", "b"]).select(F.col("child").alias("pid"), "tid", "at"), held)
        step = F.posexplode(later()).alias("step", "e")
        pairs = lists.join(p.tx, "tid").select("pid", "tid", "tu", "at", step).select("pid", F.col("e.item_rank").alias("b"), "tid", "tu", (F.col("at") + F.col("step") + 1).alias("at"))
        before, k = level.select("pid", "ranks"), k + 1
    return MiningResult(_verified(p, found, 0.0), counters, held)


def _numbered(level: DataFrame, before: DataFrame | None, **more) -> DataFrame:
    """The level's (pid, b) as patterns of their own: ``pid, parent, b, ranks``; ``before`` has the parents' ranks."""
    if before is None:
        grown = level.withColumn("path", F.array().cast("array<int>"))
    else:
        grown = level.join(before.withColumnRenamed("ranks", "path"), "pid")
    rest = [c for c in level.columns if c not in ("pid", "b")]
    return grown.select(F.monotonically_increasing_id().alias("pid"), F.col("pid").alias("parent"), "b", F.concat("path", F.array("b")).alias("ranks"), *rest)


def _verified(p: Prepared, found: list[DataFrame], cor: float) -> DataFrame:
    """Utility, support and Kulc of candidate ranks, from the transactions; those that pass.

    A candidate meets the transactions of its rarest item, which is its first, and each is tested in place.
    """
    if not found:
        found = [p.items.select(F.array("item_rank").alias("ranks")).limit(0)]
    ranks = _union(found)
    sets = p.entries.select(F.col("e.item_rank").alias("first"), "s")
    met = ranks.withColumn("first", F.element_at("ranks", 1)).join(sets, "first")
    hit = F.filter("s", lambda e: F.array_contains("ranks", e["item_rank"]))
    whole = met.select("ranks", hit.alias("h")).where(F.size("h") == F.size("ranks"))
    u = F.aggregate("h", F.lit(0).cast("bigint"), lambda acc, e: acc + e["u"])
    inv = F.aggregate("h", F.lit(0.0), lambda acc, e: acc + 1 / e["sup"])
    measured = whole.select("ranks", u.alias("u"), inv.alias("inv")).groupBy("ranks").agg(F.sum(F.col("u").cast(SUM)).alias("iu"), F.count(F.lit(1)).alias("sup"), F.first("inv").alias("inv"))
    scored = measured.withColumn("k", F.size("ranks")).withColumn("kulc", F.col("sup") * F.col("inv") / F.col("k"))
    return named(scored.where((F.col("iu") >= F.lit(p.least).cast(SUM)) & (F.col("kulc") >= cor - EPS)), p.items)


def _projected(basket: Basket, min_util, min_cor, max_k: int | None, held: list[DataFrame]) -> tuple[Prepared, list[DataFrame], list[dict]]:
    """Candidates of the projection baseline, by levels: ``ranks, k, sup, twu``."""
    cor = float(ratio(min_cor))
    p = prepare(basket, min_util, "support_asc", held)
    limit = F.lit(p.least).cast(SUM)
    # The whole suffix of each row is carried along, as this baseline does.
    db = p.entries.select(F.lit(0).cast("bigint").alias("pid"), F.col("e.item_rank").alias("b"), F.col("e.sup").alias("b_sup"), "tu", later().alias("rest"))
    before = None
    found, counters, k = [], [], 1
    while True:
        level = db.groupBy("pid", "b").agg(F.count(F.lit(1)).alias("sup"), F.sum(F.col("tu").cast(SUM)).alias("twu"), F.first("b_sup").alias("b_sup"))
        inv = 1 / F.col("b_sup")
        if before is not None:
            level, inv = level.join(before.select("pid", "inv_sup"), "pid"), F.col("inv_sup") + inv
        level = level.withColumn("inv_sup", inv).withColumn("kulc", F.col("sup") * F.col("inv_sup") / k).withColumn("passes", (F.col("twu") >= limit) & (F.col("kulc") >= cor - EPS))
        level = keep(_numbered(level.drop("b_sup"), before.select("pid", "ranks") if before is not None else None), held)
        visited, n, tuples, wide = _seen(level, F.sum(F.col("passes").cast("int")), F.sum("sup"), F.sum(F.when(F.col("passes"), F.col("sup"))))
        counters.append({"k": k, "visited": visited, "candidates": n, "tuples": tuples, "expanded": n, "peak": wide})
        if not n:
            break
        level = level.where("passes")
        found.append(level.select("ranks", F.lit(k).alias("k"), "sup", "twu"))
        if k == max_k:
            break
        # The projected databases themselves: rows with all that follows.
        kept = keep(db.join(level.select(F.col("parent").alias("pid"), "b", F.col("pid").alias("child")), ["pid", "b"]).select(F.col("child").alias("pid"), "tu", "rest"), held)
        db = kept.select("pid", "tu", "rest", F.posexplode("rest").alias("step", "e")).select("pid", F.col("e.item_rank").alias("b"), F.col("e.sup").alias("b_sup"), "tu", F.slice("rest", F.col("step") + 2, F.size("rest")).alias("rest"))
        before, k = level.select("pid", "ranks", "inv_sup"), k + 1
    return p, found, counters


def mine_projection(basket: Basket, min_util, min_cor, *, max_k: int | None = None) -> MiningResult:
    """Sub-databases of whole suffixes, candidates by TWU and Kulc, utilities in a last pass. The comparator of the correlated miner."""
    held: list[DataFrame] = []
    p, found, counters = _projected(basket, min_util, min_cor, max_k, held)
    return MiningResult(_verified(p, [f.select("ranks") for f in found], float(ratio(min_cor))), counters, held)


def projection_candidates(basket: Basket, min_util, min_cor, *, max_k: int | None = None) -> MiningResult:
    """``pattern, k, sup, twu`` of the candidates that the projection baseline makes, before its last pass."""
    held: list[DataFrame] = []
    p, found, counters = _projected(basket, min_util, min_cor, max_k, held)
    every = _union(found) if found else p.items.select(F.array("item_rank").alias("ranks"), F.lit(1).alias("k"), "sup", F.lit(0).cast(SUM).alias("twu")).limit(0)
    spelled = every.select("*", F.explode("ranks").alias("item_rank")).join(p.items.select("item_rank", "item"), "item_rank")
    texts = spelled.groupBy("ranks", "k", "sup", "twu").agg(pattern_text(F.collect_list("item")).alias("pattern"))
    return MiningResult(texts.select("pattern", F.col("k").cast("int").alias("k"), "sup", F.col("twu").cast("bigint").alias("twu")), counters, held)


def mine_plain_projected(basket: Basket, min_util, *, max_k: int | None = None) -> MiningResult:
    """Projection with merged equal suffixes, local utilities (which items stay) and subtree utilities (which are followed)."""
    held: list[DataFrame] = []
    p = prepare(basket, min_util, "twu_asc", held)
    limit = F.lit(p.least).cast(SUM)
    s_type = "array<struct<item_rank:int,u:bigint>>"
    db = p.tx.select(F.array().cast("array<int>").alias("ranks"), F.lit(0).cast("bigint").alias("iu"), F.lit(1).cast("bigint").alias("n"), F.transform("s", lambda e: F.struct(e["item_rank"].alias("item_rank"), e["u"].alias("u"))).cast(s_type).alias("s"))
    found, counters, k = [], [], 0
    while True:
        # Equal suffixes of one pattern become one row: utilities are summed place by place (places -2 and -1: the pattern's own, and the rows).
        shape = F.transform("s", lambda e: e["item_rank"])
        cell = lambda at, v: F.struct(at.cast("int").alias("at"), v.cast("bigint").alias("v"))
        cells = F.concat(F.array(cell(F.lit(-2), F.col("iu")), cell(F.lit(-1), F.col("n"))), F.transform("s", lambda e, i: cell(i, e["u"])))
        sums = db.select("ranks", shape.alias("shape"), F.explode(cells).alias("c")).groupBy("ranks", "shape", F.col("c.at").alias("at")).agg(F.sum("c.v").alias("v"))
        added = sums.groupBy("ranks", "shape").agg(F.array_sort(F.collect_list(F.struct("at", "v"))).alias("vs"))
        zipped = F.zip_with("shape", F.slice("vs", 3, F.size("vs")), lambda r, c: F.struct(r.alias("item_rank"), c["v"].alias("u")))
        merged = keep(added.select("ranks", F.element_at("vs", 1)["v"].alias("iu"), F.element_at("vs", 2)["v"].alias("n"), zipped.cast(s_type).alias("s")), held)
        rest = F.aggregate("s", F.lit(0).cast("bigint"), lambda acc, e: acc + e["u"])
        local = merged.select("ranks", "iu", rest.alias("rest"), F.explode("s").alias("e")).groupBy("ranks", F.col("e.item_rank").alias("b")).agg(F.sum((F.col("iu") + F.col("rest")).cast(SUM)).alias("local"))
        stay = local.where(F.col("local") >= limit).groupBy("ranks").agg(F.collect_set("b").alias("stay"))
        thin = merged.join(stay, "ranks").select("ranks", "iu", "n", F.filter("s", lambda e: F.array_contains("stay", e["item_rank"])).alias("s"))
        behind = F.slice("s", F.col("at") + 2, F.size("s"))
        after = F.aggregate(behind, F.lit(0).cast("bigint"), lambda acc, e: acc + e["u"])
        steps = keep(thin.select("ranks", "iu", "n", "s", F.posexplode("s").alias("at", "b")).select(F.concat("ranks", F.array("b.item_rank")).alias("ranks"), (F.col("iu") + F.col("b.u")).alias("iu"), "n", after.alias("ru"), behind.cast(s_type).alias("s")), held)
        k += 1
        level = keep(steps.groupBy("ranks").agg(F.sum("n").alias("sup"), F.sum(F.col("iu").cast(SUM)).alias("iu"), F.sum((F.col("iu") + F.col("ru")).cast(SUM)).alias("subtree")), held)
        n, go, rows = _seen(level, F.sum((F.col("subtree") >= limit).cast("int")), F.sum("sup"))
        counters.append({"k": k, "visited": n, "expanded": go, "tuples": rows})
        found.append(level.where(F.col("iu") >= limit).select("ranks", F.lit(k).alias("k"), "sup", "iu"))
        if not go or k == max_k:
            break
        db = steps.join(level.where(F.col("subtree") >= limit).select("ranks"), "ranks").select("ranks", "iu", "n", "s")
    out = _union(found)
    inv = out.select("ranks", F.explode("ranks").alias("item_rank")).join(p.items.select("item_rank", "inv"), "item_rank").groupBy("ranks").agg(F.sum("inv").alias("inv_sup"))
    return MiningResult(named(out.join(inv, "ranks").withColumn("kulc", F.col("sup") * F.col("inv_sup") / F.col("k")), p.items), counters, held)


def mine_affinity(basket: Basket, min_util, *, max_k: int | None = None) -> MiningResult:
    """Patterns whose affinity utility (least quantity times the sum of profits) reaches the threshold.

    patterns: ``pattern, k, sup, af, au``. Bound: what a pattern has, and of each later item of the
    transaction its profit times the lesser of its quantity and the pattern's.
    """
    held: list[DataFrame] = []
    p = prepare(basket, min_util, "support_asc", held, ("qty", "profit"))
    limit = F.lit(p.least).cast(SUM)

    def bounded(pairs: DataFrame) -> DataFrame:
        """``bound`` of each entry, from the places behind it."""
        more = F.aggregate(later(), F.lit(0).cast("bigint"), lambda acc, e: acc + e["profit"] * F.least(e["qty"], F.col("m")))
        return pairs.withColumn("bound", F.col("m") * F.col("p") + more).drop("s")

    pairs = bounded(p.entries.select(F.lit(0).cast("bigint").alias("pid"), F.col("e.item_rank").alias("b"), "tid", "at", F.col("e.qty").alias("m"), F.col("e.profit").alias("p"), "s"))
    before = None
    found, counters, k = [], [], 1
    while True:
        level = pairs.groupBy("pid", "b").agg(F.count(F.lit(1)).alias("sup"), F.sum(F.col("m").cast(SUM)).alias("af"), F.sum((F.col("m") * F.col("p")).cast(SUM)).alias("au"), F.sum(F.col("bound").cast(SUM)).alias("bound")).where(F.col("bound") >= limit)
        level = keep(_numbered(level, before), held)
        n, tuples = _seen(level, F.sum("sup"))
        counters.append({"k": k, "visited": n, "expanded": n, "tuples": tuples})
        found.append(level.where(F.col("au") >= limit).select("ranks", F.lit(k).alias("k"), "sup", "af", "au"))
        if not n or k == max_k:
            break
        lists = keep(pairs.join(level.select(F.col("parent").alias("pid"), "b", F.col("pid").alias("child")), ["pid", "b"]).select(F.col("child").alias("pid"), "tid", "at", "m", "p"), held)
        step = F.posexplode(later()).alias("step", "e")
        grown = lists.join(p.tx.select("tid", "s"), "tid").select("pid", "tid", "at", "m", "p", "s", step)
        pairs = bounded(grown.select("pid", F.col("e.item_rank").alias("b"), "tid", (F.col("at") + F.col("step") + 1).alias("at"), F.least("m", "e.qty").alias("m"), (F.col("p") + F.col("e.profit")).alias("p"), "s"))
        before, k = level.select("pid", "ranks"), k + 1
    out = _union(found)
    spelled = out.select("*", F.explode("ranks").alias("item_rank")).join(p.items.select("item_rank", "item"), "item_rank")
    return MiningResult(spelled.groupBy("ranks", "k", "sup", "af", "au").agg(pattern_text(F.collect_list("item")).alias("pattern")).select("pattern", F.col("k").cast("int").alias("k"), "sup", F.col("af").cast("bigint").alias("af"), F.col("au").cast("bigint").alias("au")), counters, held)


def mine_exhaustive(basket: Basket, *, max_items: int = 16) -> DataFrame:
    """``pattern, k, sup, utility, kulc`` of every itemset that occurs: subsets of each transaction, no pruning."""
    whole = basket.rows.groupBy("tid").agg(F.array_sort(F.collect_list(F.struct("item", "u"))).alias("s"))
    longest = whole.agg(F.max(F.size("s"))).first()[0] or 0
    if longest > max_items:
        raise ValueError(f"a transaction has {longest} items; all subsets are made of {max_items} at most")
    start = F.array(F.struct(F.array().cast("array<string>").alias("items"), F.lit(0).cast("bigint").alias("u")))
    subsets = F.aggregate("s", start, lambda acc, e: F.concat(acc, F.transform(acc, lambda x: F.struct(F.concat(x["items"], F.array(e["item"])).alias("items"), (x["u"] + e["u"]).alias("u")))))
    every = whole.select(F.explode(subsets).alias("x")).where("size(x.items) > 0").groupBy(F.col("x.items").alias("items")).agg(F.count(F.lit(1)).alias("sup"), F.sum("x.u").cast("bigint").alias("utility"))
    one = basket.rows.groupBy("item").agg((1 / F.count(F.lit(1))).alias("inv"))
    inv = every.select("items", F.explode("items").alias("item")).join(one, "item").groupBy("items").agg(F.sum("inv").alias("inv"))
    return every.join(inv, "items").select(F.array_join("items", ",").alias("pattern"), F.size("items").alias("k"), "sup", "utility", shown(F.col("sup") * F.col("inv") / F.size("items")).alias("kulc"))


class _Node:
    __slots__ = ("item", "up", "count", "utility", "below")

    def __init__(self, item: int, up: "_Node | None") -> None:
        self.item, self.up, self.count, self.utility, self.below = item, up, 0, 0, {}


def _tree(paths: Iterator[tuple[list[int], int, int]]) -> dict[int, list[_Node]]:
    """A prefix tree of paths (items, rows, utility); for each item the nodes that hold it. Equal beginnings share nodes."""
    root, nodes = _Node(0, None), {}
    for items, count, utility in paths:
        at = root
        for x in items:
            node = at.below.get(x)
            if node is None:
                node = at.below[x] = _Node(x, at)
                nodes.setdefault(x, []).append(node)
            at = node
            at.count += count
            at.utility += utility
    return nodes


def _tree_candidates(head: tuple[int, ...], paths: list[tuple[list[int], int, int]], least: int, max_k: int | None, out: list) -> None:
    """Candidates that extend ``head``: an item stays if the paths that hold it have enough utility together."""
    whole: dict[int, int] = {}
    for items, _, utility in paths:
        for x in items:
            whole[x] = whole.get(x, 0) + utility
    kept = {x for x, t in whole.items() if t >= least}
    if not kept:
        return
    nodes = _tree(([x for x in items if x in kept], n, u) for items, n, u in paths)
    for x, held in nodes.items():
        out.append((x, *head))
        if max_k is not None and len(head) + 1 >= max_k:
            continue
        below = []
        for node in held:
            items, at = [], node.up
            while at is not None and at.up is not None:
                items.append(at.item)
                at = at.up
            if items:
                below.append((items[::-1], node.count, node.utility))
        if below:
            _tree_candidates((x, *head), below, least, max_k, out)


def _grow(least: int, max_k: int | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, paths, out = None, [], []

        def flush() -> Iterator[pa.RecordBatch]:
            if now is not None:
                _tree_candidates(now, paths, least, max_k, out)
            while out:
                part = out[:50_000]
                del out[:50_000]
                yield pa.RecordBatch.from_arrays([pa.array([list(x) for x in part], pa.list_(pa.int32()))], ["ranks"])

        for b in batches:
            for head, path, n, u in zip(*(b.column(c).to_pylist() for c in ("head", "path", "n", "u")), strict=True):
                head = tuple(head)
                if head != now:
                    yield from flush()
                    now, paths = head, []
                paths.append((path, n, int(u)))
        yield from flush()

    return run


def mine_tree_growth(basket: Basket, min_util, *, max_k: int | None = None, unit_paths: int = 50_000) -> MiningResult:
    """Tree-based growth: candidates from conditional prefix trees, then one verifying pass.

    A unit is a suffix of items with the paths that lead to it; equal paths are one row before they leave the JVM, and
    in a task they share the nodes of a prefix tree. A path's utility is that of its items and the unit's last item. Units
    of over ``unit_paths`` different paths are divided by the item before, until each fits a task.
    """
    held: list[DataFrame] = []
    p = prepare(basket, min_util, "twu_asc", held)
    limit = F.lit(p.least).cast(SUM)
    upto = F.aggregate(F.slice("s", 1, F.col("at")), F.lit(0).cast(SUM), lambda acc, e: (acc + e["u"]).cast(SUM))
    before = F.transform(F.slice("s", 1, F.col("at") - 1), lambda e: e["item_rank"])
    rows = p.entries.select(F.array("e.item_rank").alias("head"), before.alias("path"), F.lit(1).cast("bigint").alias("n"), upto.alias("u"))
    found, counters, k = [], [], 1
    while True:
        merged = keep(rows.groupBy("head", "path").agg(F.sum("n").alias("n"), F.sum("u").cast(SUM).alias("u")), held)
        heads = keep(merged.groupBy("head").agg(F.sum("u").alias("u"), F.count(F.lit(1)).alias("paths")).where(F.col("u") >= limit), held)
        n, large = _seen(heads, F.sum((F.col("paths") > unit_paths).cast("int")))
        counters.append({"k": k, "candidates": n})
        found.append(heads.select(F.col("head").alias("ranks")))
        if max_k is not None and k >= max_k:
            break
        small = merged.join(heads.where(F.col("paths") <= unit_paths).select("head"), "head").where(F.size("path") > 0)
        parts = int(basket.rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        grown = small.repartition(parts, "head").sortWithinPartitions("head").select("head", "path", "n", "u").mapInArrow(_grow(p.least, max_k), "ranks array<int>")
        found.append(keep(grown, held))
        counters.append({"k": -1, "candidates": found[-1].count()})
        if not large:
            break
        wide = merged.join(heads.where(F.col("paths") > unit_paths).select("head"), "head")
        rows = wide.select("head", "path", "n", "u", F.posexplode("path").alias("at", "x")).select(F.concat(F.array("x"), "head").alias("head"), F.slice("path", F.lit(1), F.col("at")).alias("path"), "n", "u")
        k += 1
    ordered = [f.select(F.array_sort("ranks").alias("ranks")) for f in found]
    return MiningResult(_verified(p, ordered, 0.0), counters, held)


def _fp(basket: Basket, min_sup: float, min_conf: float = 0.5):
    from pyspark.ml.fpm import FPGrowth

    tx = basket.rows.groupBy("tid").agg(F.collect_set("item").alias("items"))
    return FPGrowth(itemsCol="items", minSupport=min_sup, minConfidence=min_conf).fit(tx)


def frequent_itemsets(basket: Basket, min_sup: float) -> DataFrame:
    return _fp(basket, min_sup).freqItemsets.select(pattern_text("items").alias("pattern"), F.size("items").alias("k"), F.col("freq").alias("sup"))


def association_rules(basket: Basket, min_sup: float, min_conf: float) -> DataFrame:
    rules = _fp(basket, min_sup, min_conf).associationRules
    return rules.select(pattern_text("antecedent").alias("antecedent"), pattern_text("consequent").alias("consequent"), F.round("confidence", 6).alias("confidence"))


__all__ = [n for n in dir() if n.startswith("mine")] + ["projection_candidates", "frequent_itemsets", "association_rules"]
