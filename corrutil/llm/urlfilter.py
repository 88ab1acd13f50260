"""URL filters by a sort-merge range join over canonical keys, in DataFrame functions alone.

A rule (host, path) fits a url whose host is the rule's or a subdomain of it and
whose path starts with the rule's path; the longest fitting rule wins. Hosts are
written with their labels reversed, so that a rule is a prefix, and so an interval,
of the keys ``reversed ancestor host + path``. A url has one key for each ancestor
of its host that some rule names. Rules and keys are sorted together; the sweep
carries the stack of rules that were open at the last rule passed (a rule's stack is
the list of the rules that are prefixes of it, built once from the rules), and a
key takes the deepest rule of that stack that still covers it. That is complete:
every rule between the innermost covering rule and the key in sort order has the
former as prefix, so it is on the stack of the last rule passed.

A popular host (all of ``com``) is dealt over as many sweeps as its keys ask for, ``sweep_keys`` in each,
and each gets the rules of that host again, so no task holds all keys of one host.

Edge cases: a null url, or one without ``://``, has an empty host and path and gets
the default verdict; repeated rows stay as often as they are; of equal rules with
different verdicts ``block`` wins; an empty table gives an empty table. Columns of
the input other than ``id_col`` and ``url_col`` are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Set between the reversed host and the path of a key; sorts before any character of a host.
MARK = "\x00"


def host_and_path(url: Column) -> tuple[Column, Column]:
    known = F.coalesce(F.locate("://", url) > 0, F.lit(False))
    rest = F.expr("substring({0}, locate('://', {0}) + 3)".format("__url"))
    host = F.when(known, F.translate(F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1), UPPER, LOWER)).otherwise("")
    path = F.when(known, F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1)).otherwise("")
    return host, path


def reversed_host(host: Column) -> Column:
    return F.array_join(F.reverse(F.split(host, r"\.", -1)), ".")


def ancestors(host: Column) -> Column:
    """The reversed forms of a host and of all hosts above it, e.g. com, com.example."""
    labels = F.reverse(F.split(host, r"\.", -1))
    return F.when(host == "", F.array().cast("array<string>")).otherwise(
        F.transform(F.sequence(F.lit(1), F.size(labels)), lambda n: F.array_join(F.slice(labels, 1, n), "."))
    )


def stacks(rules: DataFrame) -> DataFrame:
    """``anc, path, stack``: each rule with the rules of its host that are prefixes of its path, outermost first."""
    rules = (
        rules.select(F.translate(F.coalesce("host", F.lit("")), UPPER, LOWER).alias("host"), F.coalesce("path", F.lit("")).alias("path"), "verdict")
        .where(F.col("host") != "")
        .groupBy("host", "path")
        .agg(F.max("verdict").alias("verdict"))
        .select(reversed_host(F.col("host")).alias("anc"), "host", "path", "verdict")
    )
    heads = rules.select("anc", "path", F.explode(F.transform(F.sequence(F.lit(0), F.length("path")), lambda n: F.substring("path", F.lit(1), n))).alias("head"))
    outer = rules.select("anc", F.col("path").alias("head"), "verdict", F.concat("host", "path").alias("rule"))
    return (
        heads.join(outer, ["anc", "head"])
        .groupBy("anc", "path")
        .agg(F.array_sort(F.collect_list(F.struct(F.length("head").alias("depth"), F.col("head").alias("head"), "rule", "verdict"))).alias("stack"))
    )


def judge_urls(pages: DataFrame, rules: DataFrame, *, id_col: str = "page_id", url_col: str = "url", default: str = "allow", sweep_keys: int = 250_000) -> DataFrame:
    """``id_col, host, path, rule, verdict`` of each row; rules: ``host, path, verdict``."""
    host, path = host_and_path(F.col("__url"))
    urls = pages.select(F.col(id_col).alias("__id"), F.col(url_col).alias("__url")).select("__id", host.alias("host"), path.alias("path"))
    rule_stacks = stacks(rules)
    named = rule_stacks.select("anc").distinct()

    keys = urls.withColumn("__anc", ancestors(F.col("host"))).withColumn("__n", F.size("__anc"))
    exploded = keys.select("__id", "host", "path", "__n", F.explode_outer("__anc").alias("anc"))
    # Counted before anything is shuffled; one row for each host that has rules and keys.
    sized = exploded.select("anc").join(named, "anc", "left_semi").groupBy("anc").agg(F.ceil(F.count(F.lit(1)) / sweep_keys).cast("int").alias("salts"))
    points = exploded.select("anc", F.concat("anc", F.lit(MARK), "path").alias("key"), F.lit(1).alias("kind"), "__id", "host", "path", "__n", F.lit(None).cast(rule_stacks.schema["stack"].dataType).alias("stack"))
    opened = rule_stacks.join(sized, "anc").select("anc", F.explode(F.sequence(F.lit(0), F.col("salts") - 1)).alias("salt"), F.concat("anc", F.lit(MARK), "path").alias("key"), F.lit(0).alias("kind"), F.lit(None).cast(urls.schema["__id"].dataType).alias("__id"), F.lit(None).cast("string").alias("host"), F.lit(None).cast("string").alias("path"), F.lit(None).cast("int").alias("__n"), "stack")
    # Keys under hosts that no rule names need no sweep.
    salt = F.pmod(F.xxhash64("__id", "path"), F.col("salts")).cast("int")
    swept = points.join(sized, "anc").withColumn("salt", salt).drop("salts").unionByName(opened)
    idle = points.join(named, "anc", "left_anti").select("__id", "host", "path", "__n", F.lit(None).cast("struct<len:int,rule:string,verdict:string>").alias("hit"))

    sweep = "last_value(stack) IGNORE NULLS OVER (PARTITION BY anc, salt ORDER BY key, kind ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)"
    hit = F.expr("element_at(filter(open, r -> startswith(path, r.head)), -1)")
    judged = (
        swept.withColumn("open", F.expr(sweep))
        .where("kind = 1")
        .withColumn("hit", F.when(F.size(F.expr("filter(open, r -> startswith(path, r.head))")) > 0, hit))
        .select("__id", "host", "path", "__n", F.when(F.col("hit").isNotNull(), F.struct(F.length("hit.rule").alias("len"), F.col("hit.rule").alias("rule"), F.col("hit.verdict").alias("verdict"))).alias("hit"))
    )
    return (
        judged.unionByName(idle)
        .groupBy("__id", "host", "path")
        .agg(F.max("hit").alias("hit"), (F.count(F.lit(1)) / F.max(F.greatest("__n", F.lit(1)))).cast("int").alias("times"))
        .withColumn("__copy", F.explode(F.expr("sequence(1, times)")))
        .select(F.col("__id").alias(id_col), "host", "path", F.col("hit.rule").alias("rule"), F.coalesce("hit.verdict", F.lit(default)).alias("verdict"))
    )


#: The rules of the query, as (host, path, verdict).
RULES = [
    ("com", "/", "allow"),
    ("example.com", "/en/", "block"),
    ("www.example.com", "/en/", "allow"),
    ("net", "/es/", "block"),
    ("net", "/fr/", "block"),
]


def op9_url_filter(spark, sf_dir: str) -> DataFrame:
    rules = spark.sql("SELECT * FROM VALUES " + ", ".join(str(r) for r in RULES) + " AS r(host, path, verdict)")
    return judge_urls(spark.read.parquet(f"{sf_dir}/pages.parquet"), rules)


OP9_SQL = r"""
WITH r(host, path, verdict) AS (VALUES ('com','/','allow'), ('example.com','/en/','block'), ('www.example.com','/en/','allow'), ('net','/es/','block'), ('net','/fr/','block')),
u AS (SELECT page_id, row_number() OVER () AS n, CASE WHEN contains(url, '://') THEN substr(url, strpos(url, '://') + 3) END AS rest FROM pages),
p AS (SELECT page_id, n,
        coalesce(translate(regexp_extract(rest, '^([^/?#]*)', 1, 's'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '') AS host,
        coalesce(regexp_extract(rest, '^[^/?#]*([^?#]*)', 1, 's'), '') AS path FROM u),
j AS (SELECT p.page_id, p.n, p.host, p.path, r.host || r.path AS rule, r.verdict,
        row_number() OVER (PARTITION BY p.n ORDER BY length(r.host || r.path) DESC NULLS LAST) AS k
      FROM p LEFT JOIN r ON (p.host = r.host OR ends_with(p.host, '.' || r.host)) AND starts_with(p.path, r.path))
SELECT page_id, host, path, rule, coalesce(verdict, 'allow') AS verdict FROM j WHERE k = 1
"""
