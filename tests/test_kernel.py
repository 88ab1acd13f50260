"""The depth-first kernels on many random baskets, over all switches, against plain Python."""

import itertools
import random

import numpy as np
import pytest

from corrutil.plans import prefix
from corrutil.plans.prefix import Rules, Units, search
from corrutil.types import least_utility


def subsets(rows):
    by, sup = {}, {}
    for t, i, u in rows:
        by.setdefault(t, {})[i] = u
        sup[i] = sup.get(i, 0) + 1
    seen = {}
    for x in by.values():
        for k in range(1, len(x) + 1):
            for c in itertools.combinations(sorted(x), k):
                n, u = seen.get(c, (0, 0))
                seen[c] = n + 1, u + sum(x[i] for i in c)
    return {c: (n, u, n * sum(1 / sup[i] for i in c) / len(c)) for c, (n, u) in seen.items()}, sup


def units(rows, rank, sup) -> Units:
    """Every item as a unit: the transactions that hold it, and their later items."""
    by = {}
    for t, i, u in rows:
        by.setdefault(t, []).append((rank[i], u, sup[i]))
    paths, unit, iu, tu, edge, places = [], [], [], [], [0], []
    for i in sorted(rank, key=rank.get):
        for t in sorted(by):
            own = {r: u for r, u, _ in by[t]}
            if rank[i] in own:
                later = sorted(x for x in by[t] if x[0] > rank[i])
                unit.append(len(paths))
                iu.append(own[rank[i]])
                tu.append(sum(own.values()))
                places += later
                edge.append(len(places))
        paths.append([rank[i]])
    column = lambda k: np.array([p[k] for p in places], np.int64)
    inv = np.array([1 / sup[i] for i in sorted(rank, key=rank.get)])
    total = sum(u for *_, u in rows)
    a = lambda x: np.array(x, np.int64)
    return Units(a(paths), inv, np.full(len(paths), total, np.int64), a(unit), a(iu), a(tu), a(edge), column(0), column(1), column(2))


@pytest.mark.parametrize("block", [2_000_000, 40])
def test_both_kernels_on_random_baskets(block, monkeypatch):
    monkeypatch.setattr(prefix, "BLOCK", block)
    for seed in range(500):
        rng = random.Random(seed)
        items = "abcdefg"[: rng.randint(2, 7)]
        rows = [(t, i, rng.randint(1, 5) * rng.randint(1, 20)) for t in range(rng.randint(2, 25)) for i in items if rng.random() < 0.55]
        if not rows:
            continue
        every, sup = subsets(rows)
        util, cor = rng.choice(["0.02", "0.05", "0.1", "0.2"]), rng.choice([0.0, 0.3, 0.5, 0.7])
        least = least_utility(util, sum(u for *_, u in rows))
        want = {c: x for c, x in every.items() if x[1] >= least and x[2] >= cor - 1e-9}
        rank = {i: k + 1 for k, i in enumerate(sorted(sup, key=lambda i: (sup[i], i)))}
        back = {r: i for i, r in rank.items()}
        x = units(rows, rank, sup)
        spk, la, start, pairs, deepest = rng.random() < 0.6, rng.random() < 0.6, rng.choice(["extension", "prefix"]), rng.random() < 0.4, rng.choice([None, None, 2, 3])
        for kernel in (search, prefix._by_lists):
            rules = Rules(least, cor, spk, True, la, start, spk and cor > 0 and rng.random() < 0.6, pairs and kernel is search, deepest)
            effort, got = {}, {}
            for paths, n, iu, kulc in kernel(x, rules, True, effort):
                for p, a, b, c in zip(paths.tolist(), n.tolist(), iu.tolist(), kulc.tolist(), strict=True):
                    key = tuple(sorted(back[r] for r in p))
                    assert key not in got
                    got[key] = (a, b, round(c, 9))
            assert got == {c: (n, u, round(v, 9)) for c, (n, u, v) in want.items() if deepest is None or len(c) <= deepest}, (seed, kernel.__name__, rules)
            assert sum(c["emitted"] for c in effort.values()) == len(got)


def test_a_pattern_on_the_edge_of_the_ratio_cut_stays():
    """At large supports the margin of the threshold is many transactions wide: the cut must leave them."""
    n = 3_000_000
    x = Units(np.array([[1]]), np.array([1 / n]), np.array([10 * n]), np.zeros(n, np.int64), np.ones(n, np.int64), np.full(n, 2), np.arange(n + 1), np.full(n, 2), np.ones(n, np.int64), np.full(n, 2 * n))
    for ratio in (False, True):
        found = [tuple(p) for paths, *_ in search(x, Rules(1, 0.75 + 5e-10, ratio=ratio), True, {}) for p in paths.tolist()]
        assert found == [(1,), (1, 2)]
