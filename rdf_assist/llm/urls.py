"""URL filters by host and path prefix: a sort-merge range join in DataFrame operations.

Canonical keys hold the host's labels in reverse and then the path, so the urls that a rule fits at
one host level are an interval of keys: those that start with the rule's key. Rules and urls are
sorted together; the sweep carries the stack of nested rules opened last, and a url takes the
innermost rule of that stack which still holds it. Any rule that holds a url is the last opened
rule or encloses it, so the carried stack never misses one.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
MARK = "\u0001"


def host_path(url: Column) -> tuple[Column, Column]:
    """(host, path); both empty if the url is null or has no '://'."""
    found = F.coalesce(F.instr(url, "://"), F.lit(0))
    rest = F.when(found > 0, F.substring(url, found + 3, F.length(url))).otherwise("")
    host = F.translate(F.regexp_extract(rest, "^[^/?#]*", 0), UPPER, LOWER)
    return host, F.regexp_extract(rest, "^[^/?#]*([^?#]*)", 1)


def _key(labels: Column, path: Column) -> Column:
    return F.concat(F.array_join(labels, "."), F.lit(MARK), path)


def opened(rules: DataFrame) -> DataFrame:
    """(key, stack) of each rule: itself and the rules of the same host whose path is a prefix, shortest first.

    Enclosing rules come from an equi-join on each prefix of the path, not from pairs of a host's rules.
    Of rules with the same host and path, one that blocks wins.
    """
    own = rules.select(F.translate("host", UPPER, LOWER).alias("host"), F.coalesce("path", F.lit("")).alias("path"), "verdict").where("host is not null and verdict is not null")
    own = own.groupBy("host", "path").agg(F.max("verdict").alias("verdict"))
    keyed = own.withColumn("key", _key(F.reverse(F.split("host", r"\.")), F.col("path")))
    outer = keyed.select("host", F.col("path").alias("prefix"), F.struct(F.length("key").alias("size"), "key", F.length("host").alias("host_size"), F.concat("host", "path").alias("rule"), "verdict").alias("item"))
    inner = keyed.select("host", "key", F.explode(F.transform(F.sequence(F.lit(0), F.length("path")), lambda n: F.substring(F.col("path"), F.lit(1), n))).alias("prefix"))
    return inner.join(outer, ["host", "prefix"]).groupBy("key").agg(F.sort_array(F.collect_list("item")).alias("stack"))


def judge(pages: DataFrame, rules: DataFrame, default: str = "allow", salts: int | None = None) -> DataFrame:
    """page_id, host, path, rule and verdict of every page; rule is null where `default` decides.

    A rule fits its host and every subdomain if the path starts with the rule's path; the longest
    (host and path together, then host) wins. Urls are dealt over salts in equal shares, and each salt
    sweeps all rules: rows of one host, however many, spread evenly. Null urls have empty host and path.
    Repeated rows each keep their row; an empty rule list leaves all to the default.
    """
    spark = pages.sparkSession
    salts = salts or 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    levels = rules.agg(F.max(F.size(F.split("host", r"\.")))).first()[0] or 1
    host, path = host_path(F.col("url").cast("string"))
    urls = pages.select("page_id", host.alias("host"), path.alias("path"), F.monotonically_increasing_id().alias("uid"))
    labels = F.reverse(F.split("host", r"\."))
    level = F.explode(F.sequence(F.lit(1), F.least(F.lit(levels), F.size(labels)))).alias("n")
    asked = urls.select("*", level).select("page_id", "host", "path", "uid", F.pmod("uid", F.lit(salts)).cast("int").alias("salt"), _key(F.slice(labels, F.lit(1), F.col("n")), F.col("path")).alias("key"), F.lit(1).alias("kind"))
    starts = opened(rules).select("key", "stack", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"), F.lit(0).alias("kind"))
    swept = asked.unionByName(starts, allowMissingColumns=True)
    order = Window.partitionBy("salt").orderBy("key", "kind").rowsBetween(Window.unboundedPreceding, 0)
    carried = swept.withColumn("stack", F.last("stack", ignorenulls=True).over(order)).where("kind = 1")
    holds = F.element_at(F.expr("filter(stack, s -> startswith(key, s.key))"), -1)
    hit = carried.select("page_id", "host", "path", "uid", "salt", F.when(F.size(F.expr("filter(stack, s -> startswith(key, s.key))")) > 0, holds).alias("hit"))
    best = hit.groupBy("salt", "uid").agg(
        F.first("page_id").alias("page_id"), F.first("host").alias("host"), F.first("path").alias("path"),
        F.max(F.when(F.col("hit").isNotNull(), F.struct(F.length("hit.rule").alias("a"), F.col("hit.host_size").alias("b"), F.col("hit.rule").alias("rule"), F.col("hit.verdict").alias("verdict")))).alias("best"),
    )
    return best.select("page_id", "host", "path", F.col("best.rule").alias("rule"), F.coalesce("best.verdict", F.lit(default)).alias("verdict"))


def rule_frame(spark, rules: list[tuple[str, str, str]]) -> DataFrame:
    """rules as (verdict, host, path)."""
    return spark.createDataFrame(rules, "verdict string, host string, path string")
