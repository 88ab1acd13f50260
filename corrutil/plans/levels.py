"""The correlated miner.

Patterns grow one later item at a time along the support order. A level is one aggregation over
list entries and what follows them in their transactions, which gives every child's support, utility,
remaining utility and joint bound at once, and one pass that makes the lists of the children to be
expanded. Lists hold a place in a transaction, so the first two levels need no join at all.

Patterns that fit a task become units of ``prefix``, searched depth first; only those too
large for one go on level by level, so a frequent item is split by its second item, then its third.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import EPS, pattern_text, shown
from ..operators.basket import SUM
from ..types import Basket, MiningResult, ratio
from .prefix import EFFORT, Rules, search_units
from .prepare import Prepared, keep, later, prepare

#: Transactions of a pattern up to which one task searches everything below it.
UNIT_TUPLES = 200_000


def _most_sup(k: int, cor: float):
    """Largest support of a later item: a child's Kulc is at most sup * (inv_sup + 1 / b_sup) / (k + 1)."""
    need = F.lit((cor - EPS) * (k + 1)) / F.col("sup") - F.col("inv_sup")
    return F.when(need <= 0, F.lit((1 << 63) - 1)).otherwise(F.floor((1 + 1e-9) / need) + 1)


def mine(
    basket: Basket,
    min_util,
    min_cor,
    *,
    use_spk: bool = True,
    use_ubu: bool = True,
    use_la: bool = True,
    la_start: str = "extension",
    item_order: str = "support_asc",
    max_k: int | None = None,
    plan: str = "auto",
    ratio_cut: bool = True,
    needed_support: bool = False,
    sibling_filter: bool = False,
    pair_twu: bool = False,
    kernel: str = "tuples",
    unit_tuples: int = UNIT_TUPLES,
) -> MiningResult:
    """All patterns of utility at least ``min_util`` of the total and Kulc at least ``min_cor``.

    use_spk: expand only patterns that reach min_cor (sound along the support order only).
    use_ubu: expand only patterns whose utility and remaining utility reach the threshold.
    use_la: drop pairs whose joint bound misses it. la_start: that bound starts from the
    extended pattern ("extension") or from its prefix ("prefix").
    ratio_cut: bound the supports of later items by min_cor (off where use_spk is).
    needed_support: drop children below the support that min_cor asks of their items (needs use_spk).
    sibling_filter: extend only by items that survived beside the pattern (for counters).
    pair_twu: extend by items only that share enough utility with the last one (plan "levels") or
    with the first (units).
    plan: "levels"; "prefix" (depth first from single items, whatever their size); or "auto": units of up to
    ``unit_tuples`` transactions depth first, larger ones level by level. kernel: units are searched by
    "tuples" (blocks of patterns at once) or "lists" (pairs of lists, ended early).
    """
    cor = float(ratio(min_cor))
    if use_spk and item_order != "support_asc":
        raise ValueError("cutting by correlation needs the support order")
    if la_start not in ("extension", "prefix"):
        raise ValueError("la_start is 'extension' or 'prefix'")
    if plan not in ("levels", "prefix", "auto"):
        raise ValueError("plan is 'levels', 'prefix' or 'auto'")
    if kernel not in ("tuples", "lists"):
        raise ValueError("kernel is 'tuples' or 'lists'")
    if not use_ubu and max_k is None:
        raise ValueError("without the utility bound a largest length is needed")
    if ratio(min_util) == 0 and cor == 0 and max_k is None:
        raise ValueError("with both thresholds at zero every itemset qualifies: a largest length is needed")
    if sibling_filter:
        plan = "levels"
    cuts = use_spk and item_order == "support_asc" and cor > 0
    rules = Rules(0, cor, use_spk, use_ubu, use_la, la_start, ratio_cut and cuts and not sibling_filter, pair_twu, max_k)
    held: list[DataFrame] = []
    p = prepare(basket, min_util, item_order, held)
    rules = Rules(p.least, *list(vars(rules).values())[1:])
    run = _Run(p, rules, held, needed_support and cuts, sibling_filter)
    top = {"levels": 0, "auto": unit_tuples, "prefix": None}[plan]
    # Patterns and the effort of the units come from one pass, and are written once.
    kept: list[DataFrame] = []
    every = keep(named(run.levels(top, kernel), p.items, digits=None, effort=True), kept)
    exact = every.where("pattern IS NOT NULL").drop(*EFFORT, "part")
    return MiningResult(exact.withColumn("kulc", shown("kulc")), lambda: run.counted(every), held, exact, kept)


class _Run:
    def __init__(self, p: Prepared, rules: Rules, held: list[DataFrame], needed: bool, siblings: bool) -> None:
        self.p, self.rules, self.held, self.needed, self.siblings = p, rules, held, needed, siblings
        self.limit = F.lit(rules.least).cast(SUM)
        self.effort: dict[int, dict] = {}
        self.searches = 0

    def keep(self, df: DataFrame) -> DataFrame:
        return keep(df, self.held)

    def count(self, k: int, **more: int) -> None:
        mine = self.effort.setdefault(k, dict.fromkeys(EFFORT, 0))
        for name, n in more.items():
            mine[name] = max(mine[name], n) if name == "peak" else mine[name] + n

    def counted(self, every: DataFrame) -> list[dict]:
        sums = every.where("pattern IS NULL").groupBy("k").agg(*(F.max(e).alias(e) if e == "peak" else F.sum(e).alias(e) for e in EFFORT)).collect()  # a row for each length
        for row in sums:
            self.count(row["k"], **{e: row[e] or 0 for e in EFFORT})
        return [{"k": k, **self.effort[k]} for k in sorted(self.effort)]

    def judged(self, level: DataFrame, k: int) -> DataFrame:
        """The level with ``expand`` and ``emit``."""
        r = self.rules
        enough = F.col("iu") + F.col("ru") >= self.limit if r.use_ubu else F.lit(True)
        correlated = F.col("kulc") >= r.cor - EPS
        go = F.col("alive") & enough & (correlated if r.use_spk else F.lit(True)) & F.lit(r.max_k is None or k < r.max_k)
        return level.withColumns({"enough": enough, "expand": go, "emit": F.col("alive") & (F.col("iu") >= self.limit) & correlated})

    def tally(self, level: DataFrame, k: int, joined: bool) -> tuple[int, int]:
        """Counters of a judged level; how many patterns grow, and the list entries they have."""
        spk = self.rules.use_spk
        n = lambda c: F.coalesce(F.sum(c.cast("bigint")), F.lit(0))
        alive, enough, low = F.col("alive"), F.col("enough"), F.col("kulc") < self.rules.cor - EPS
        entries = lambda c: F.coalesce(F.sum(F.when(c, F.col("sup"))), F.lit(0))
        seen = level.coalesce(1).agg(F.count(F.lit(1)), n(alive), n(F.col("emit")), n(F.col("expand")), n(alive & ~enough), n(alive & enough & low) if spk else F.lit(0), entries(alive), entries(F.col("expand"))).first()
        made, visited, emitted, grow, ubu, cut, tuples, live = (int(x or 0) for x in seen)
        self.count(k, joined=made if joined else 0, la_cut=made - visited, visited=visited, emitted=emitted, expanded=grow, ubu_cut=ubu, spk_cut=cut, tuples=tuples, peak=live)
        return grow, live

    def levels(self, top: int | None, kernel: str) -> DataFrame:
        """All patterns ``ranks, k, sup, iu, kulc``; patterns of up to ``top`` transactions (None: all) become units."""
        p, r = self.p, self.rules
        emitted = []
        places = p.entries
        if top is None or 0 < p.most <= top:
            return self.units(places, F.lit(True), kernel)
        if top:
            # Single items that fit a task are judged there.
            emitted.append(self.units(places, F.col("e.sup") <= top, kernel))
            places = places.where(F.col("e.sup") > top)
        first = places.groupBy(F.col("e.item_rank").alias("b")).agg(F.count(F.lit(1)).alias("sup"), F.sum(F.col("e.u").cast(SUM)).alias("iu"), F.sum(F.col("e.ru").cast(SUM)).alias("ru"))
        level = first.select(F.col("b").cast("bigint").alias("pid"), F.lit(-1).cast("bigint").alias("parent"), "b", F.array("b").alias("ranks"), "sup", "iu", "ru", (1 / F.col("sup")).alias("inv_sup"), F.lit(1.0).alias("kulc"), F.lit(p.total).cast(SUM).alias("above"), F.lit(True).alias("alive"))
        level = self.keep(self.judged(level, 1))
        k, lists, before = 1, None, None
        grow, live = self.tally(level, 1, False)
        while True:
            emitted.append(level.where("emit").select("ranks", F.lit(k).alias("k"), "sup", "iu", "kulc", *(F.lit(None).cast("bigint").alias(e) for e in [*EFFORT, "part"])))
            if not grow:
                break
            frontier = level.where("expand").withColumn("most_sup", _most_sup(k, r.cor) if r.ratio else F.lit((1 << 63) - 1))
            if k == 1:
                entries = places.join(frontier.select("pid", "b", "most_sup"), F.col("e.item_rank") == F.col("b")).select("pid", "tid", "tu", "at", F.col("e.u").alias("iu"), F.col("e.ru").alias("ru"), "most_sup", "s")
            else:
                entries = lists.join(p.tx.select("tid", "tu", "s"), "tid")
            if k > 1 and top:
                # What fits a task now ends there; the rest goes on by levels.
                small = self.keep(entries.where(F.col("sup") <= top).select("pid", "iu", "tu", later().alias("s")))
                named_units = small.join(frontier.select("pid", "ranks", "inv_sup", "above"), "pid").drop("pid")
                fit = frontier.where(F.col("sup") <= top).coalesce(1).agg(F.count(F.lit(1)), F.coalesce(F.sum("sup"), F.lit(0))).first()
                if fit[0]:
                    emitted.append(self.searched(named_units, int(fit[1]), False, kernel))
                if fit[0] == grow:
                    break
                entries, frontier = entries.where(F.col("sup") > top), frontier.where(F.col("sup") > top)
            after = F.explode(F.filter(F.transform(later(), lambda e, i: F.struct((i + 1).alias("step"), e["item_rank"].alias("b"), e["u"].alias("u"), e["ru"].alias("ru"), e["sup"].alias("b_sup"))), lambda e: e["b_sup"] <= F.col("most_sup")))
            pairs = entries.select("pid", "tid", "tu", "at", (F.col("iu") + F.col("ru")).alias("joint"), "iu", after.alias("e")).select("pid", "tid", "tu", (F.col("at") + F.col("e.step")).alias("at"), "joint", (F.col("iu") + F.col("e.u")).alias("iu"), F.col("e.ru").alias("ru"), F.col("e.b").alias("b"), F.col("e.b_sup").alias("b_sup"))
            if r.pair_twu:
                if k == 1:
                    enough_pairs = self.keep(pairs.groupBy(F.col("pid").alias("x"), "b").agg(F.sum(F.col("tu").cast(SUM)).alias("t")).where(F.col("t") >= self.limit).select("x", "b"))
                last = frontier.select("pid", F.col("b").cast("bigint").alias("x"))
                pairs = pairs.join(last, "pid").join(enough_pairs, ["x", "b"], "left_semi").drop("x")
            if before is not None:
                # X_ab is extended by c only if the pair (X_a, c) survived.
                pairs = pairs.join(frontier.select("pid", F.col("parent").alias("up")), "pid").join(before, ["up", "b"], "left_semi").drop("up")
            children = pairs.groupBy("pid", "b").agg(F.count(F.lit(1)).alias("sup"), F.sum(F.col("iu").cast(SUM)).alias("iu"), F.sum(F.col("ru").cast(SUM)).alias("ru"), F.sum(F.col("joint").cast(SUM)).alias("joint"), F.first("b_sup").alias("b_sup"))
            up = frontier.select("pid", F.col("ranks").alias("path"), F.col("inv_sup").alias("p_inv"), (F.col("iu") + F.col("ru")).alias("own"), F.col("above").alias("p_above"))
            bound = F.col("joint") if r.la_start == "extension" else F.col("p_above") - F.col("own") + F.col("joint")
            inv = F.col("p_inv") + 1 / F.col("b_sup")
            kulc = F.col("sup") * inv / (k + 1)
            scored = children.join(up, "pid").select(
                F.monotonically_increasing_id().alias("pid"), F.col("pid").alias("parent"), "b", F.concat("path", F.array("b")).alias("ranks"), "sup", "iu", "ru", inv.alias("inv_sup"), kulc.alias("kulc"), F.col("own").alias("above"),
                ((bound >= self.limit) if r.use_la else F.lit(True)).alias("alive"),
            )
            if self.needed:
                scored = scored.where(F.col("sup") >= F.floor(F.lit((r.cor - EPS) * (k + 1)) / F.col("inv_sup") * (1 - 1e-9)))
            level = self.keep(self.judged(scored, k + 1))
            grow, live = self.tally(level, k + 1, True)
            if self.siblings:
                before = level.where("alive").select(F.col("parent").alias("up"), "b")
            k += 1
            if grow:
                chosen = level.where("expand").withColumn("most_sup", _most_sup(k, r.cor) if r.ratio else F.lit((1 << 63) - 1))
                chosen = chosen.select(F.col("parent").alias("pid"), "b", F.col("pid").alias("child"), "most_sup", "sup")
                lists = self.keep(pairs.join(chosen, ["pid", "b"]).select(F.col("child").alias("pid"), "tid", "at", "iu", "ru", "most_sup", "sup"))
        return _union(emitted)

    def units(self, places: DataFrame, which, kernel: str) -> DataFrame:
        rows = places.where(which).select(F.array("e.item_rank").alias("ranks"), (1 / F.col("e.sup")).alias("inv_sup"), F.lit(self.p.total).cast(SUM).alias("above"), F.col("e.u").alias("iu"), "tu", later().alias("s"))
        return self.searched(rows, self.entries_of(places, which), True, kernel)

    def entries_of(self, places: DataFrame, which) -> int:
        """About how many rows the units have: the supports of their items, from the item table."""
        items = self.p.items.select(F.struct("sup").alias("e"), "sup").where(which)
        return int(items.coalesce(1).agg(F.coalesce(F.sum("sup"), F.lit(0))).first()[0])

    def searched(self, rows: DataFrame, tuples: int, judge: bool, kernel: str) -> DataFrame:
        self.searches += 1
        found = search_units(rows, tuples, self.rules, judge, kernel)
        # Effort rows of two tasks may be equal: the task tells them apart.
        return found.withColumn("part", F.when(F.col("ranks").isNull(), F.spark_partition_id().cast("bigint") + (self.searches << 32)))


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for more in frames[1:]:
        out = out.unionByName(more)
    return out


def named(found: DataFrame, items: DataFrame, digits: int | None = 6, effort: bool = False) -> DataFrame:
    """``pattern, k, sup, utility, kulc`` from ranks; with ``effort`` its columns too, and rows without ranks stay."""
    value = F.col("kulc") if digits is None else shown("kulc", digits).alias("kulc")
    more = [*EFFORT, "part"] if effort else []
    each = found.select("ranks", "k", "sup", "iu", "kulc", *more, (F.explode_outer if effort else F.explode)("ranks").alias("item_rank"))
    spelled = each.join(items.select("item_rank", "item"), "item_rank", "left" if effort else "inner")
    grouped = spelled.groupBy("ranks", "k", "sup", "iu", "kulc", *more).agg(F.when(F.col("ranks").isNotNull(), pattern_text(F.collect_list("item"))).alias("pattern"))
    return grouped.select("pattern", F.col("k").cast("int").alias("k"), "sup", F.col("iu").cast("bigint").alias("utility"), value, *more)


VARIANTS = {
    "ubu": {"use_spk": False, "use_la": False, "ratio_cut": False},
    "ubu_spk": {"use_la": False, "ratio_cut": False},
    "ubu_la": {"use_spk": False, "ratio_cut": False},
    "all": {"ratio_cut": False},
}


def mine_variant(basket: Basket, min_util, min_cor, name: str, **more) -> MiningResult:
    return mine(basket, min_util, min_cor, **(VARIANTS[name] | more))


__all__ = ["VARIANTS", "mine", "mine_variant", "named"]
