"""Column functions: interest measures, pattern text, money, simulators."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Patterns whose exact measure equals a threshold must pass it in binary floating point too.
EPS = 1e-9


#: Added before rounding, so that an exact half goes up whatever the order of its sums left in the last bits.
TIE = 1e-12


def _col(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def kulc(sup: Column | str, inv_sup: Column | str, k: Column | str) -> Column:
    """Mean conditional probability of the pattern given each item; ``inv_sup`` is the sum of 1 / item support."""
    return _col(sup) * _col(inv_sup) / _col(k)


def shown(value: Column | str, digits: int = 6) -> Column:
    """A measure rounded for output."""
    return F.round(_col(value) + TIE, digits)


def correlation_kind(value: Column | str, eps: float = EPS) -> Column:
    """positive, none or negative, around the null-invariant neutral point 0.5."""
    v = _col(value)
    return F.when(v > 0.5 + eps, "positive").when(v < 0.5 - eps, "negative").otherwise("none")


def all_confidence(sup: Column | str, max_item_sup: Column | str) -> Column:
    return _col(sup) / _col(max_item_sup)


def max_confidence(sup: Column | str, min_item_sup: Column | str) -> Column:
    return _col(sup) / _col(min_item_sup)


def coherence(sup: Column | str, union_sup: Column | str) -> Column:
    """Transactions with all items over transactions with any."""
    return _col(sup) / _col(union_sup)


def cosine(sup: Column | str, log_item_sup: Column | str, k: Column | str) -> Column:
    """Support over the geometric mean of the item supports; ``log_item_sup`` is the sum of their logarithms."""
    return _col(sup) / F.exp(_col(log_item_sup) / _col(k))


def lift(sup: Column | str, log_item_sup: Column | str, k: Column | str, transactions: Column | str) -> Column:
    """Support over what independent items would have."""
    return F.exp(F.log(_col(sup).cast("double")) + (_col(k) - 1) * F.log(_col(transactions).cast("double")) - _col(log_item_sup))


def confidence(sup: Column | str, antecedent_sup: Column | str) -> Column:
    return _col(sup) / _col(antecedent_sup)


def pattern_text(items: Column | str) -> Column:
    """Canonical text: items sorted as text, joined by commas."""
    return F.array_join(F.array_sort(_col(items)), ",")


def cents(amount: Column | str) -> Column:
    return F.round(_col(amount) * 100).cast("bigint")


def _unit(seed: int, *key: Column) -> Column:
    """A number in (0, 1) fixed by seed and key."""
    return (F.pmod(F.xxhash64(F.lit(seed), *key), F.lit(1 << 30)) + 0.5) / float(1 << 30)


def simulate_quantity(*key: Column | str, seed: int = 1, most: int = 5) -> Column:
    """Uniform on 1..most, for data without quantities."""
    return F.floor(_unit(seed, *map(_col, key)) * most).cast("bigint") + 1


def simulate_profit(*key: Column | str, seed: int = 2, scale: float = 100.0, spread: float = 1.0) -> Column:
    """Log-normal positive integers, for data without profits."""
    cols = [*map(_col, key)]
    normal = F.sqrt(-2 * F.log(_unit(seed, *cols))) * F.cos(2 * 3.141592653589793 * _unit(seed + 7919, *cols))
    return F.greatest(F.lit(1), F.round(F.exp(normal * spread) * scale)).cast("bigint")
