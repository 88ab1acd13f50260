"""Readers of transactions and profits, and writers of patterns."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..types import PROFIT, TRANSACTION


def read_transactions(spark: SparkSession, path: str, form: str = "parquet") -> DataFrame:
    """Nested transactions (``tid, user, ts, record``) from Parquet or JSON lines; nothing is inferred."""
    return spark.read.schema(TRANSACTION).format(form).load(path)


def read_profits(spark: SparkSession, path: str, form: str = "parquet") -> DataFrame:
    reader = spark.read.schema(PROFIT)
    return reader.option("header", True).csv(path) if form == "csv" else reader.format(form).load(path)


def read_csv_rows(spark: SparkSession, path: str) -> DataFrame:
    """``tid, item, qty`` from CSV with a head line."""
    return spark.read.schema("tid bigint, item string, qty bigint").option("header", True).csv(path)


def _parsed(lines: DataFrame) -> DataFrame:
    """Lines with their two lists, and with ``reason`` where they are not well formed."""
    parts = F.split(F.trim("value"), r"\s*:\s*")
    cut = lines.withColumn("names", F.split(F.element_at(parts, 1), r"\s+")).withColumn("values", F.when(F.size(parts) == 3, F.transform(F.split(F.try_element_at(parts, F.lit(3)), r"\s+"), lambda v: v.try_cast("bigint"))))
    reason = (
        F.when(F.col("value").isNull() | F.col("values").isNull(), "not three parts").when(F.size("names") != F.size("values"), "lists of different length")
        .when(F.exists("values", lambda v: v.isNull()), "not a number").when(F.exists("names", lambda n: n == ""), "no item")
    )
    return cut.withColumn("reason", reason)


def utility_lines(lines: DataFrame) -> DataFrame:
    """``tid, item, u`` from lines "items : total : utilities" (column ``value``) with a line number ``tid``.

    Lines that are not well formed are left out whole; ``rejected_lines`` gives them.
    """
    good = _parsed(lines).where("reason IS NULL")
    return good.select("tid", F.explode(F.arrays_zip("names", "values")).alias("e")).select("tid", F.col("e.names").alias("item"), F.col("e.values").alias("u"))


def rejected_lines(lines: DataFrame) -> DataFrame:
    """``tid, value, reason`` of the lines that ``utility_lines`` leaves out."""
    return _parsed(lines).where("reason IS NOT NULL").select("tid", "value", "reason")


def read_utility_text(spark: SparkSession, path: str) -> DataFrame:
    """Benchmark files in the form "items : total : utilities"; a transaction's number comes from its file and place."""
    return utility_lines(read_lines(spark, path))


def read_lines(spark: SparkSession, path: str) -> DataFrame:
    """``tid, value``: the lines of text files, numbered."""
    return spark.read.text(path).withColumn("tid", F.monotonically_increasing_id())


class _Lines(DataSourceReader):
    def __init__(self, paths: list[str]) -> None:
        self.paths = paths

    def partitions(self) -> list[InputPartition]:
        return [InputPartition((i, p)) for i, p in enumerate(self.paths)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        number, path = partition.value
        with open(path, encoding="utf-8") as f:
            for i, line in enumerate(f):
                parts = [x.split() for x in line.strip().split(":")]
                if len(parts) == 3 and len(parts[0]) == len(parts[2]):
                    for item, u in zip(parts[0], parts[2], strict=True):
                        if u.lstrip("-").isdigit():
                            yield ((number << 40) + i, item, int(u))


class UtilityTextSource(DataSource):
    """``spark.read.format("utility_text")`` for the same files where every executor sees them, one task a file."""

    @classmethod
    def name(cls) -> str:
        return "utility_text"

    def schema(self) -> str:
        return "tid bigint, item string, u bigint"

    def reader(self, schema) -> DataSourceReader:
        import glob

        return _Lines(sorted(glob.glob(self.options["path"])))


def write_patterns(patterns: DataFrame, path: str, *, run: str, form: str = "parquet") -> None:
    """Patterns of a named run, in folders by run and length."""
    patterns.withColumn("run", F.lit(run)).write.mode("append").partitionBy("run", "k").format(form).save(path)


def register(patterns: DataFrame, view: str = "patterns") -> None:
    patterns.createOrReplaceTempView(view)


def price_as_of(rows: DataFrame, prices: DataFrame) -> DataFrame:
    """``rows`` (``tid, item, ts, ...``) with the latest ``unit_profit`` of each item at or before ``ts``.

    prices: ``item, valid_from, unit_profit``. Rows and prices of an item are sorted together once; no pair is built.
    """
    marks = rows.withColumn("__p", F.lit(None).cast("bigint")).withColumn("__k", F.lit(1))
    steps = prices.select("item", F.col("valid_from").alias("ts"), F.col("unit_profit").alias("__p")).withColumn("__k", F.lit(0))
    both = marks.unionByName(steps, allowMissingColumns=True)
    held = F.expr("last_value(__p) IGNORE NULLS OVER (PARTITION BY item ORDER BY ts, __k ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)")
    return both.withColumn("unit_profit", held).where("__k = 1").drop("__p", "__k")


def within_windows(rows: DataFrame, windows: DataFrame, *, bucket_seconds: int = 86400) -> DataFrame:
    """Rows (``ts``) with every window (``name, start, stop``) that holds them: an equality join on time buckets, then the exact test."""
    bucket = lambda c: F.floor(F.unix_timestamp(c) / bucket_seconds)
    spread = windows.withColumn("__b", F.explode(F.sequence(bucket("start"), bucket("stop"))))
    return rows.withColumn("__b", bucket("ts")).join(spread, "__b").where((F.col("ts") >= F.col("start")) & (F.col("ts") < F.col("stop"))).drop("__b")
