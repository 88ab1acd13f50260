"""Transaction views over the given tables: baskets of ``tid, item, u`` (and ``qty, profit``)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from .functions import cents
from .types import Basket

#: The worked example's transactions (item and quantity) and profits.
EXAMPLE = {1: "a3 b1 e2", 2: "a2 b3 c1 d1", 3: "a1 d3 e2", 4: "a1 b5 c2 d1 e1", 5: "a2 b3 e3"}
EXAMPLE_PROFITS = {"a": 3, "b": 1, "c": 7, "d": 2, "e": 10}
WORDS = "[a-zà-ÿ]+"
TAGS = "<([a-zA-Z][a-zA-Z0-9]*)"
TOP_WORDS = 40


_SCHEMAS: dict[str, StructType] = {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table. Its schema is read from its files once, not by a job for each plan."""
    path = f"{sf_dir}/{name}.parquet"
    if path not in _SCHEMAS:
        _SCHEMAS[path] = spark.read.parquet(path).schema
    return spark.read.schema(_SCHEMAS[path]).parquet(path)


def paper_example(spark: SparkSession) -> Basket:
    rows = [(t, x[0], int(x[1:])) for t, r in EXAMPLE.items() for x in r.split()]
    from .operators.basket import build_basket

    return build_basket(spark.createDataFrame(rows, "tid bigint, item string, qty bigint"), spark.createDataFrame(list(EXAMPLE_PROFITS.items()), "item string, unit_profit bigint"))


def _lines(spark: SparkSession, sf_dir: str, item: str) -> Basket:
    part = table(spark, sf_dir, "part").select("p_partkey", F.col(item).cast("string").alias("item"), cents("p_retailprice").alias("price"))
    lines = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("tid"), "l_partkey", F.col("l_quantity").cast("bigint").alias("qty"))
    # By transaction alone, so that what a miner groups by transaction needs no second shuffle.
    joined = lines.join(part, lines["l_partkey"] == part["p_partkey"]).repartition("tid")
    return Basket(joined.groupBy("tid", "item").agg(F.sum("qty").alias("qty"), F.sum(F.col("qty") * F.col("price")).alias("u")))


def w1_order_part(spark: SparkSession, sf_dir: str) -> Basket:
    b = _lines(spark, sf_dir, "p_partkey")
    return Basket(b.rows.withColumn("profit", (F.col("u") / F.col("qty")).cast("bigint")))


def w2_order_brand(spark: SparkSession, sf_dir: str) -> Basket:
    return _lines(spark, sf_dir, "p_brand")


def w3_order_type(spark: SparkSession, sf_dir: str) -> Basket:
    return _lines(spark, sf_dir, "p_type")


def w3_affinity(spark: SparkSession, sf_dir: str) -> Basket:
    return _one_profit(w3_order_type(spark, sf_dir), spark, sf_dir, "p_type")


def _one_profit(basket: Basket, spark: SparkSession, sf_dir: str, column: str) -> Basket:
    """The basket's quantities with one profit for each item: the least size of its parts and the length of its name."""
    from .operators.basket import build_basket

    profit = table(spark, sf_dir, "part").groupBy(F.col(column).alias("item")).agg((F.min("p_size") + F.length(column)).cast("bigint").alias("unit_profit"))
    return build_basket(basket.rows.select("tid", "item", "qty"), profit)


def w2_affinity(spark: SparkSession, sf_dir: str) -> Basket:
    return _one_profit(w2_order_brand(spark, sf_dir), spark, sf_dir, "p_brand")


def w4_affinity(spark: SparkSession, sf_dir: str) -> Basket:
    return _one_profit(w4_cust_brand(spark, sf_dir), spark, sf_dir, "p_brand")


def w4_cust_brand(spark: SparkSession, sf_dir: str) -> Basket:
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("tid"), "o_custkey")
    rows = w2_order_brand(spark, sf_dir).rows.join(orders, "tid")
    return Basket(rows.groupBy(F.col("o_custkey").alias("tid"), "item").agg(F.sum("qty").alias("qty"), F.sum("u").alias("u")))


def w5_order_supp(spark: SparkSession, sf_dir: str) -> Basket:
    lines = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("tid"), F.col("l_suppkey").cast("string").alias("item"), cents("l_extendedprice").alias("u"))
    return Basket(lines.groupBy("tid", "item").agg(F.sum("u").alias("u")))


def w6_order_name(spark: SparkSession, sf_dir: str) -> Basket:
    return _lines(spark, sf_dir, "p_name")


def w6_simulated(spark: SparkSession, sf_dir: str) -> Basket:
    """W6 as bare itemsets, with simulated quantities and profits, as for data that carries neither."""
    from .functions import simulate_profit, simulate_quantity
    from .operators.basket import build_basket

    bare = w6_order_name(spark, sf_dir).rows.select("tid", "item")
    return build_basket(bare.withColumn("qty", simulate_quantity("tid", "item")), bare.select("item").distinct().withColumn("unit_profit", simulate_profit("item")))


def w7_user_day_event(spark: SparkSession, sf_dir: str) -> Basket:
    events = table(spark, sf_dir, "events").select(F.concat_ws(":", F.col("user_id").cast("string"), F.date_format("ts", "yyyy-MM-dd")).alias("tid"), F.col("event_type").alias("item"), cents("value").alias("u"))
    return Basket(events.groupBy("tid", "item").agg(F.sum("u").alias("u")))


def _top_words(source: DataFrame, key: str) -> Basket:
    words = source.select(F.col(key).alias("tid"), F.explode(F.regexp_extract_all(F.lower("text"), F.lit(WORDS), F.lit(0))).alias("item")).groupBy("tid", "item").agg(F.count(F.lit(1)).alias("qty"))
    top = words.groupBy("item").agg(F.count(F.lit(1)).alias("df")).orderBy(F.desc("df"), "item").limit(TOP_WORDS).select("item")
    return Basket(words.join(F.broadcast(top), "item").select("tid", "item", "qty", F.length("item").cast("bigint").alias("profit"), (F.col("qty") * F.length("item")).alias("u")))


def w8_doc_word(spark: SparkSession, sf_dir: str) -> Basket:
    return _top_words(table(spark, sf_dir, "documents"), "doc_id")


def w9_emb_dim(spark: SparkSession, sf_dir: str) -> Basket:
    values = F.transform("embedding", lambda x, i: F.struct(-F.abs(x.cast("double")), i + 1))
    top = F.slice(F.array_sort(values), 1, 8)
    rows = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("tid"), F.explode(top).alias("e")).select("tid", F.col("e.col2").cast("string").alias("item"), F.round(-F.col("e.col1") * 100).cast("bigint").alias("u"))
    return Basket(rows.where("u > 0").groupBy("tid", "item").agg(F.sum("u").alias("u")))


def _weight(item: Column) -> Column:
    return F.ascii(item) % 7 + F.length(item)


def w10_page_tag(spark: SparkSession, sf_dir: str) -> Basket:
    tags = table(spark, sf_dir, "pages").select(F.col("page_id").alias("tid"), F.explode(F.regexp_extract_all("html", F.lit(TAGS), F.lit(1))).alias("tag")).groupBy("tid", F.lower("tag").alias("item")).agg(F.count(F.lit(1)).alias("qty"))
    return Basket(tags.select("tid", "item", (F.col("qty") * _weight(F.col("item"))).cast("bigint").alias("u")))


def w11_conv_word(spark: SparkSession, sf_dir: str) -> Basket:
    return _top_words(table(spark, sf_dir, "conversations"), "conv_id")


def w12_doc_label(spark: SparkSession, sf_dir: str) -> Basket:
    both = table(spark, sf_dir, "documents").select("doc_id", "lang", "source", "n_chars").join(table(spark, sf_dir, "labels"), "doc_id")
    names = F.array(*(F.concat(F.lit(f"{c}="), F.col(c).cast("string")) for c in ("lang", "source", "quality", "toxic")))
    return Basket(both.select(F.col("doc_id").alias("tid"), F.explode(names).alias("item"), F.col("n_chars").alias("u")).where("item IS NOT NULL").groupBy("tid", "item").agg(F.sum("u").alias("u")))


def w13_bench_word(spark: SparkSession, sf_dir: str) -> Basket:
    return _top_words(table(spark, sf_dir, "benchmark"), "item_id")


VIEWS = {"w1": w1_order_part, "w2": w2_order_brand, "w3": w3_order_type, "w4": w4_cust_brand, "w5": w5_order_supp, "w6": w6_order_name, "w7": w7_user_day_event, "w8": w8_doc_word, "w9": w9_emb_dim, "w10": w10_page_tag, "w11": w11_conv_word, "w12": w12_doc_label, "w13": w13_bench_word, "w2a": w2_affinity, "w3a": w3_affinity, "w4a": w4_affinity, "w6s": w6_simulated}

_LINES = """SELECT l_orderkey AS tid, CAST({0} AS VARCHAR) AS item, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty,
  CAST(sum(CAST(l_quantity AS BIGINT) * CAST(round(p_retailprice * 100) AS BIGINT)) AS BIGINT) AS u
  FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1, 2"""
_WORDS = """SELECT tid, item, qty, CAST(length(item) AS BIGINT) AS profit, CAST(qty * length(item) AS BIGINT) AS u FROM
  (SELECT {0} AS tid, item, count(*) AS qty FROM (SELECT {0}, unnest(regexp_extract_all(lower(text), '[a-zà-ÿ]+')) AS item FROM {1}) GROUP BY ALL) x
  WHERE item IN (SELECT item FROM (SELECT {0}, unnest(regexp_extract_all(lower(text), '[a-zà-ÿ]+')) AS item FROM {1}) GROUP BY item ORDER BY count(DISTINCT {0}) DESC, item LIMIT 40)"""

#: The same views in DuckDB's SQL.
VIEW_SQL = {
    "w1": "SELECT *, u // qty AS profit FROM (" + _LINES.format("p_partkey") + ")",
    "w2": _LINES.format("p_brand"),
    "w3": _LINES.format("p_type"),
    "w4": "SELECT o_custkey AS tid, item, CAST(sum(u) AS BIGINT) AS u FROM (" + _LINES.format("p_brand") + ") v JOIN orders ON v.tid = o_orderkey GROUP BY 1, 2",
    "w5": "SELECT l_orderkey AS tid, CAST(l_suppkey AS VARCHAR) AS item, CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT) AS u FROM lineitem GROUP BY 1, 2",
    "w6": _LINES.format("p_name"),
    "w7": "SELECT user_id || ':' || strftime(ts, '%Y-%m-%d') AS tid, event_type AS item, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS u FROM events GROUP BY 1, 2",
    "w8": _WORDS.format("doc_id", "documents"),
    "w9": """SELECT tid, item, u FROM (SELECT vec_id AS tid, CAST(d AS VARCHAR) AS item, CAST(round(abs(CAST(embedding[d] AS DOUBLE)) * 100) AS BIGINT) AS u,
  row_number() OVER (PARTITION BY vec_id ORDER BY abs(embedding[d]) DESC, d) AS k FROM embeddings, range(1, 65) r(d)) WHERE k <= 8 AND u > 0""",
    "w10": """SELECT tid, item, CAST(count(*) * (ascii(item) % 7 + length(item)) AS BIGINT) AS u FROM
  (SELECT page_id AS tid, lower(unnest(regexp_extract_all(html, '<([a-zA-Z][a-zA-Z0-9]*)', 1))) AS item FROM pages) GROUP BY 1, 2""",
    "w11": _WORDS.format("conv_id", "conversations"),
    "w12": """SELECT doc_id AS tid, unnest(['lang=' || lang, 'source=' || source, 'quality=' || quality, 'toxic=' || toxic]) AS item, n_chars AS u FROM documents JOIN labels USING (doc_id)""",
    "w13": _WORDS.format("item_id", "benchmark"),
}
_CUSTOMERS = "SELECT o_custkey AS tid, item, CAST(sum(qty) AS BIGINT) AS qty FROM ({0}) v JOIN orders ON v.tid = o_orderkey GROUP BY 1, 2"
for _name, _rows, _item in (("w2a", _LINES.format("p_brand"), "p_brand"), ("w3a", _LINES.format("p_type"), "p_type"), ("w4a", _CUSTOMERS.format(_LINES.format("p_brand")), "p_brand")):
    VIEW_SQL[_name] = f"SELECT tid, item, qty, profit, qty * profit AS u FROM ({_rows}) v JOIN (SELECT {_item}, CAST(min(p_size) + length({_item}) AS BIGINT) AS profit FROM part GROUP BY {_item}) ON item = {_item}"
