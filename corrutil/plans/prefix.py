"""Depth-first search of units: a pattern's transactions and what may follow it, in one task.

A unit's rows are the transactions of its pattern with their later items as arrays, so a batch
of rows is one flat array with offsets. A step extends a block of patterns at once: every list entry
meets the later places of its own transaction, and equal (pattern, item) pairs are
brought together by one sort. Only pairs that occur are ever built. Blocks wait on a stack, so what
is held grows with the depth, not with the number of patterns.

``dfs`` is the same search over lists of single patterns: two lists are matched by transaction
number, and the joint bound ends the match early.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from decimal import Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import EPS

#: List entries of the units that a task searches at once, and entries that one step may make of a block of patterns.
BUCKET_TUPLES, BLOCK = 100_000, 2_000_000
EFFORT = ["visited", "joined", "la_cut", "ubu_cut", "spk_cut", "emitted", "expanded", "tuples", "peak"]
_OUT = "ranks array<int>, k int, sup bigint, iu decimal(38,0), kulc double, " + ", ".join(f"{c} bigint" for c in EFFORT)


@dataclass(frozen=True)
class Rules:
    """What ends a branch. ``ratio`` bounds the support of later items, ``la_start`` is where the joint bound starts."""

    least: int
    cor: float
    use_spk: bool = True
    use_ubu: bool = True
    use_la: bool = True
    la_start: str = "extension"
    ratio: bool = False
    pair_twu: bool = False
    max_k: int | None = None


def construct_pair(prefix, left, right, least: int, use_la: bool, start: int | None = None):
    """The list of two siblings' union, or None once its bound is below ``least``.

    Lists are (tids, iu, ru), prefix may be None; ``start``: the bound before misses are taken off (own bound if None).
    """
    at = np.searchsorted(right[0], left[0])
    at[at == len(right[0])] = 0
    match = right[0][at] == left[0] if len(right[0]) else np.zeros(len(left[0]), bool)
    if use_la:
        bound = int((left[1] + left[2]).sum()) if start is None else start
        if bound - int((left[1] + left[2])[~match].sum()) < least:
            return None
    tids, at = left[0][match], at[match]
    own = left[1][match] + right[1][at]
    if prefix is not None:
        own = own - prefix[1][np.searchsorted(prefix[0], tids)]
    return tids, own, right[2][at]


def dfs(base: tuple[int, ...], prefix, siblings, supports: dict[int, int], inv_sup: float, least: int, cor: float, use_spk: bool, use_ubu: bool, use_la: bool, max_k: int | None, effort: dict, start: int | None = None) -> list[tuple]:
    """Patterns below ``base``; siblings: its extensions as (rank, list), by rank.

    ``start``: the bound of ``base`` itself; with it, joint bounds start from a pattern's prefix.
    """
    out = []
    stack = [(base, prefix, siblings, inv_sup, start)]
    while stack:
        head, parent, ext, inv, first = stack.pop()
        for i, (rank, own) in enumerate(ext):
            sup = len(own[0])
            if not sup:
                continue
            k, inv_x = len(head) + 1, inv + 1 / supports[rank]
            value, iu, ru = sup * inv_x / k, int(own[1].sum()), int(own[2].sum())
            effort["visited"] += 1
            correlated = value >= cor - EPS
            if iu >= least and correlated:
                out.append(((*head, rank), k, sup, iu, value))
            if max_k is not None and k >= max_k or use_ubu and iu + ru < least or use_spk and not correlated:
                continue
            below = []
            for r, other in ext[i + 1 :]:
                effort["joined"] += 1
                made = construct_pair(parent, own, other, least, use_la, first)
                if made is None:
                    effort["la_cut"] += 1
                elif len(made[0]):
                    below.append((r, made))
            if below:
                stack.append(((*head, rank), own, below, inv_x, None if first is None else iu + ru))
    return out


@dataclass
class Units:
    """Rows of some units in one flat form; rows are sorted by unit.

    paths: (units, k) ranks; inv, above: each unit's sum of 1 / support and its prefix's bound; unit, iu, tu: of each row;
    edge: where a row's later places begin; rank, u, sup: of each place.
    """

    paths: np.ndarray
    inv: np.ndarray
    above: np.ndarray
    unit: np.ndarray
    iu: np.ndarray
    tu: np.ndarray
    edge: np.ndarray
    rank: np.ndarray
    u: np.ndarray
    sup: np.ndarray


def _sums(values: np.ndarray, heads: np.ndarray) -> np.ndarray:
    return np.add.reduceat(values, heads) if len(heads) else np.zeros(0, np.int64)


def _count(effort: dict, k: int, **more: int) -> None:
    mine = effort.setdefault(k, dict.fromkeys(EFFORT, 0))
    for name, n in more.items():
        mine[name] = max(mine[name], n) if name == "peak" else mine[name] + int(n)


def _thin_pairs(x: Units, least: int) -> Units:
    """Without the places whose item and unit have common transactions of less than ``least`` together."""
    row = np.repeat(np.arange(len(x.unit)), np.diff(x.edge))
    names, code = np.unique(x.rank, return_inverse=True)
    key = x.unit[row] * np.int64(max(1, len(names))) + code
    order = np.argsort(key, kind="stable")
    heads = np.flatnonzero(np.r_[True, key[order][1:] != key[order][:-1]]) if len(key) else np.zeros(0, np.int64)
    enough = _sums(x.tu[row][order], heads) >= least
    stay = np.zeros(len(key), bool)
    stay[order] = np.repeat(enough, np.diff(np.r_[heads, len(key)]))
    edge = np.r_[0, np.cumsum(np.bincount(row[stay], minlength=len(x.unit)))]
    return Units(x.paths, x.inv, x.above, x.unit, x.iu, x.tu, edge, x.rank[stay], x.u[stay], x.sup[stay])


def search(x: Units, rules: Rules, judge: bool, effort: dict) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """``paths, sup, iu, kulc`` of the patterns below the units, and of the units themselves with ``judge``."""
    if not len(x.unit):
        return
    if rules.pair_twu:
        x = _thin_pairs(x, rules.least)
    r, k = rules, x.paths.shape[1]
    ends = x.edge[1:]
    summed = np.r_[0, np.cumsum(x.u)]
    owner = np.repeat(np.arange(len(x.unit)), np.diff(x.edge))
    ru = summed[ends[owner]] - summed[1:]
    names, code = np.unique(x.rank, return_inverse=True)
    sup_of = np.zeros(len(names), np.int64)
    sup_of[code] = x.sup
    heads = np.flatnonzero(np.r_[True, x.unit[1:] != x.unit[:-1]])
    sup, iu, rest = np.diff(np.r_[heads, len(x.unit)]), _sums(x.iu, heads), _sums(summed[ends] - summed[x.edge[:-1]], heads)
    grow = np.ones(len(heads), bool)
    if judge:
        kulc = sup * x.inv / k
        correlated, enough = kulc >= r.cor - EPS, iu + rest >= r.least
        emit = (iu >= r.least) & correlated
        grow = (enough if r.use_ubu else grow) & (correlated if r.use_spk else grow)
        if r.max_k is not None and k >= r.max_k:
            grow[:] = False
        _count(effort, k, visited=len(sup), ubu_cut=(~enough).sum() if r.use_ubu else 0, spk_cut=((enough if r.use_ubu else True) & ~correlated).sum() if r.use_spk else 0, emitted=emit.sum(), expanded=grow.sum(), tuples=len(x.unit), peak=len(x.unit))
        if emit.any():
            yield x.paths[emit], sup[emit], iu[emit], kulc[emit]
    kept = np.repeat(grow, sup)
    number = np.cumsum(grow) - 1
    pat, row = np.repeat(number, sup)[kept], np.flatnonzero(kept)
    stack = [(k, x.paths[grow], x.inv[grow], sup[grow], iu[grow] + rest[grow], x.above[grow], pat, row, x.edge[row], x.iu[row])]
    live = len(row)
    while stack:
        k, paths, inv, own_sup, own, above, pat, row, start, have = stack.pop()
        live -= len(pat)
        size = ends[row] - start
        made = int(size.sum())
        if not made:
            continue
        if made > BLOCK and len(paths) > 1:
            per = _sums(size, np.searchsorted(pat, np.arange(len(paths))))
            part = (np.cumsum(per) - per) // BLOCK
            for p in np.unique(part)[::-1].tolist():
                a, b = np.searchsorted(part, [p, p + 1])
                i, j = np.searchsorted(pat, [a, b])
                if b - a < len(paths):
                    stack.append((k, paths[a:b], inv[a:b], own_sup[a:b], own[a:b], above[a:b], pat[i:j] - a, row[i:j], start[i:j], have[i:j]))
                    live += j - i
            if len(np.unique(part)) > 1:
                continue
        rep = np.repeat(np.arange(len(pat)), size)
        at = np.arange(made) - np.repeat(np.cumsum(size) - size - start, size)
        if r.ratio:
            need = (r.cor - EPS) * (k + 1) / own_sup - inv
            with np.errstate(divide="ignore"):
                most = np.where(need <= 0, np.inf, np.floor((1 + 1e-9) / need) + 1)
            fit = x.sup[at] <= most[pat[rep]]
            rep, at = rep[fit], at[fit]
            if not len(at):
                continue
        key = pat[rep].astype(np.int64) * len(names) + code[at]
        order = np.argsort(key, kind="stable")
        rep, at, key = rep[order], at[order], key[order]
        heads = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
        sup, parent, item = np.diff(np.r_[heads, len(key)]), key[heads] // len(names), key[heads] % len(names)
        got = have[rep] + x.u[at]
        iu, rest = _sums(got, heads), _sums(ru[at], heads)
        joint = _sums((have + summed[ends[row]] - summed[start])[rep], heads)
        bound = joint if r.la_start == "extension" else above[parent] - own[parent] + joint
        alive = bound >= r.least if r.use_la else np.ones(len(heads), bool)
        inv_x = inv[parent] + 1 / sup_of[item]
        kulc = sup * inv_x / (k + 1)
        correlated, enough = kulc >= r.cor - EPS, iu + rest >= r.least
        emit = alive & (iu >= r.least) & correlated
        grow = alive & (enough if r.use_ubu else True) & (correlated if r.use_spk else True)
        if r.max_k is not None and k + 1 >= r.max_k:
            grow[:] = False
        new = np.column_stack([paths[parent], names[item]])
        _count(effort, k + 1, joined=len(heads), la_cut=(~alive).sum(), visited=alive.sum(), ubu_cut=(alive & ~enough).sum() if r.use_ubu else 0, spk_cut=(alive & (enough if r.use_ubu else True) & ~correlated).sum() if r.use_spk else 0, emitted=emit.sum(), expanded=grow.sum(), tuples=sup[alive].sum(), peak=live + len(key))
        if emit.any():
            yield new[emit], sup[emit], iu[emit], kulc[emit]
        if grow.any():
            kept = np.repeat(grow, sup)
            number = np.cumsum(grow) - 1
            stack.append((k + 1, new[grow], inv_x[grow], sup[grow], iu[grow] + rest[grow], own[parent[grow]], np.repeat(number, sup)[kept], row[rep[kept]], at[kept] + 1, got[kept]))
            live += int(kept.sum())


def _units(table: pa.Table) -> Units:
    """The rows of a bucket; equal ``ranks`` are one unit."""
    def of(name: str) -> pa.Array:
        column = table.column(name).combine_chunks()
        return column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column

    base, s = of("ranks"), of("s")
    depth = len(base[0])
    paths = base.flatten().to_numpy().reshape(-1, depth)
    order = np.lexsort(paths.T[::-1])
    sorted_paths = paths[order]
    first = np.r_[True, (sorted_paths[1:] != sorted_paths[:-1]).any(axis=1)]
    unit = np.cumsum(first) - 1
    flat, at = s.flatten(), s.offsets.to_numpy().astype(np.int64)
    size, begin = np.diff(at)[order], (at - at[0])[:-1][order]
    edge = np.r_[0, np.cumsum(size)]
    take = np.arange(edge[-1]) + np.repeat(begin - edge[:-1], size)
    place = {f: flat.field(f).to_numpy(zero_copy_only=False)[take] for f in ("item_rank", "u", "sup")}
    column = lambda f: of(f).to_numpy(zero_copy_only=False)[order]
    head = np.flatnonzero(first)
    return Units(sorted_paths[head], column("inv_sup")[head], column("above")[head], unit, column("iu"), column("tu"), edge, place["item_rank"], place["u"], place["sup"])


def _by_lists(x: Units, rules: Rules, judge: bool, effort: dict) -> Iterator[tuple]:
    """``search`` by lists of single patterns (``dfs``)."""
    r = rules
    for n, path in enumerate(x.paths):
        rows = np.flatnonzero(x.unit == n)
        part = Units(x.paths[n : n + 1], x.inv[n : n + 1], x.above[n : n + 1], np.zeros(len(rows), np.int64), x.iu[rows], x.tu[rows], *_places(x, rows))
        if judge:
            yield from search(part, Rules(r.least, r.cor, r.use_spk, r.use_ubu, r.use_la, max_k=len(path)), True, effort)
            if not _may_grow(part, rules):
                continue
        row = np.repeat(np.arange(len(rows)), np.diff(part.edge))
        summed = np.r_[0, np.cumsum(part.u)]
        ru = summed[part.edge[1:][row]] - summed[1:]
        supports, siblings = {}, []
        for item in np.unique(part.rank).tolist():
            at = np.flatnonzero(part.rank == item)
            supports[item] = int(part.sup[at[0]])
            siblings.append((item, (row[at], part.iu[row[at]] + part.u[at], ru[at])))
        mine = {"visited": 0, "joined": len(siblings), "la_cut": 0}
        prefix = (np.arange(len(rows)), part.iu, None)
        start = None if r.la_start == "extension" else int(part.iu.sum() + part.u.sum())
        found = dfs(tuple(path.tolist()), prefix, siblings, supports, float(x.inv[n]), r.least, r.cor, r.use_spk, r.use_ubu, r.use_la, r.max_k, mine, start)
        _count(effort, len(path) + 1, **mine, emitted=len(found))
        for ranks, _, sup, iu, value in found:
            yield np.array([ranks]), np.array([sup]), np.array([iu]), np.array([value])


def _places(x: Units, rows: np.ndarray) -> tuple[np.ndarray, ...]:
    size = np.diff(x.edge)[rows]
    edge = np.r_[0, np.cumsum(size)]
    take = np.arange(edge[-1]) + np.repeat(x.edge[:-1][rows] - edge[:-1], size)
    return edge, x.rank[take], x.u[take], x.sup[take]


def _may_grow(x: Units, r: Rules) -> bool:
    k = x.paths.shape[1]
    return not (r.max_k is not None and k >= r.max_k or r.use_ubu and int(x.iu.sum() + x.u.sum()) < r.least or r.use_spk and len(x.unit) * float(x.inv[0]) / k < r.cor - EPS)


def _batches(found: Iterator[tuple], size: int = 20_000) -> Iterator[pa.RecordBatch]:
    names = ["ranks", "k", "sup", "iu", "kulc", *EFFORT]

    def batch(paths, sup, iu, kulc) -> pa.RecordBatch:
        n, k = paths.shape
        lists = pa.ListArray.from_arrays(pa.array(np.arange(0, (n + 1) * k, k, dtype=np.int32)), pa.array(paths.astype(np.int32).ravel()))
        exact = pa.array([Decimal(int(v)) for v in iu], pa.decimal128(38, 0))
        return pa.RecordBatch.from_arrays([lists, pa.array(np.full(n, k, np.int32)), pa.array(sup.astype(np.int64)), exact, pa.array(kulc.astype(np.float64)), *(pa.nulls(n, pa.int64()) for _ in EFFORT)], names)

    for paths, sup, iu, kulc in found:
        for a in range(0, len(paths), size):
            yield batch(paths[a : a + size], sup[a : a + size], iu[a : a + size], kulc[a : a + size])


def _searcher(rules: Rules, judge: bool, kernel: str) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        effort: dict[int, dict] = {}
        held: list[pa.RecordBatch] = []
        now = None

        def solve() -> Iterator[pa.RecordBatch]:
            x = _units(pa.Table.from_batches(held))
            yield from _batches((search if kernel == "tuples" else _by_lists)(x, rules, judge, effort))

        for b in batches:
            if not b.num_rows:
                continue
            buckets = b.column("bucket").to_numpy()
            cuts = [0, *(np.flatnonzero(buckets[1:] != buckets[:-1]) + 1).tolist(), b.num_rows]
            for i, j in zip(cuts[:-1], cuts[1:], strict=True):
                if held and buckets[i] != now:
                    yield from solve()
                    held = []
                now = buckets[i]
                held.append(b.slice(i, j - i))
        if held:
            yield from solve()
        if effort:
            n = len(effort)
            yield pa.RecordBatch.from_arrays(
                [pa.nulls(n, pa.list_(pa.int32())), pa.array(list(effort), pa.int32()), pa.nulls(n, pa.int64()), pa.nulls(n, pa.decimal128(38, 0)), pa.nulls(n, pa.float64()), *(pa.array([c[e] for c in effort.values()], pa.int64()) for e in EFFORT)],
                ["ranks", "k", "sup", "iu", "kulc", *EFFORT],
            )

    return run


def search_units(units: DataFrame, tuples: int, rules: Rules, judge: bool, kernel: str = "tuples") -> DataFrame:
    """Patterns ``ranks, k, sup, iu, kulc``, and rows without ranks that hold the effort at length k.

    units: ``ranks, inv_sup, above, iu, tu, s``, a row for each transaction of a unit; ``tuples``: about how many there
    are. One shuffle by unit; units are dealt to buckets of about ``BUCKET_TUPLES`` rows, a bucket is searched at once.
    """
    parts = int(units.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    buckets = max(parts, tuples // BUCKET_TUPLES)
    places = F.transform("s", lambda e: F.struct(e["item_rank"].alias("item_rank"), e["u"].alias("u"), e["sup"].alias("sup")))
    dealt = units.select(F.pmod(F.xxhash64("ranks"), F.lit(buckets)).alias("bucket"), "ranks", "inv_sup", F.least("above", F.lit(1 << 62)).cast("bigint").alias("above"), "iu", F.least("tu", F.lit(1 << 62)).cast("bigint").alias("tu"), places.alias("s"))
    # The number of partitions is stated: few large units must not be brought into one task.
    return dealt.repartition(parts, "bucket").sortWithinPartitions("bucket").mapInArrow(_searcher(rules, judge, kernel), _OUT)


__all__ = ["EFFORT", "Rules", "Units", "construct_pair", "dfs", "search", "search_units"]
