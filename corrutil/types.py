"""Schemas, thresholds and results."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from decimal import Decimal
from fractions import Fraction

from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .scratch import delete_tables, written

BASKET = T.StructType([T.StructField("tid", T.LongType()), T.StructField("item", T.StringType()), T.StructField("u", T.LongType())])
RECORD = T.ArrayType(T.StructType([T.StructField("item", T.StringType()), T.StructField("qty", T.LongType())]))
TRANSACTION = T.StructType([T.StructField("tid", T.LongType()), T.StructField("user", T.StringType()), T.StructField("ts", T.TimestampType()), T.StructField("record", RECORD)])
PROFIT = T.StructType([T.StructField("item", T.StringType()), T.StructField("unit_profit", T.LongType())])


def ratio(value: str | float | Decimal | Fraction) -> Fraction:
    """A threshold between 0 and 1 as written: 0.1 is one tenth, not its nearest binary number."""
    r = value if isinstance(value, Fraction) else Fraction(Decimal(str(value)))
    if not 0 <= r <= 1:
        raise ValueError(f"a threshold lies between 0 and 1, not at {value}")
    return r


def least_utility(min_util: str | float | Decimal | Fraction, total: int) -> int:
    """The smallest integer utility that is at least ``min_util`` of the total."""
    r = ratio(min_util) * total
    return -(-r.numerator // r.denominator)


@dataclass
class Basket:
    """Validated long-form transactions.

    rows: ``tid, item, u`` (and ``qty, profit`` where known), one row for each item of a transaction.
    rejected: rows that were not valid, with a ``reason``.
    """

    rows: DataFrame
    rejected: DataFrame | None = None


class MiningResult:
    """patterns: ``pattern, k, sup, utility, kulc``; counters: a dict for each level; exact: kulc not rounded.

    held: scratch tables of the run; kept: those that the patterns themselves are read from, if they are written.
    """

    def __init__(self, patterns: DataFrame, counters: list[dict] | Callable[[], list[dict]], held: list[DataFrame], exact: DataFrame | None = None, kept: list[DataFrame] | None = None) -> None:
        self.patterns, self.held, self.exact, self.kept = patterns, held, exact, kept or []
        self._counters = counters

    @property
    def counters(self) -> list[dict]:
        if callable(self._counters):
            self._counters = self._counters()
        return self._counters

    def total(self, name: str) -> int:
        return sum(c.get(name, 0) or 0 for c in self.counters)

    def close(self) -> None:
        """Deletes all scratch tables; the patterns must have been read or written before."""
        delete_tables(*self.held, *self.kept)
        self.held.clear()
        self.kept.clear()

    def settled(self, exact: bool = False) -> DataFrame:
        """The patterns, written; of the run's scratch tables only theirs is left."""
        out = self.exact if exact and self.exact is not None else self.patterns
        if not self.kept:
            out = written(out, "patterns")
        delete_tables(*self.held)
        self.held.clear()
        return out
