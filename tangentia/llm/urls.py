"""Url rules by a sort-merge range join (native).

A host with its labels reversed, each closed by a dot, is a canonical key: every rule's host and all its
subdomains are one interval of keys, and such intervals nest or are disjoint. Urls and rules are sorted
together by key and swept; the running state is the stack of rules whose intervals are open at the last
rule passed, from which those that the url has left are dropped. Path prefixes are then compared on what
is left of the stack, and the longest rule wins.

The sweep is dealt out by (range of rule keys, salt): each range starts at a rule and that rule's row
carries its whole stack, so ranges are independent; urls are salted, and a range's rules (at most
``RULES_PER_RANGE``, plus their stacks) go to each salt. So neither a hot host nor many rules meet in one task.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

RULES_PER_RANGE = 10_000
INLINE_RULES = 1_000
UPPER, LOW = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
RULE_TYPE = "host string, path string, verdict string"


def url_parts(urls: DataFrame, url_col: str) -> DataFrame:
    """Adds host (between the first :// and / ? # or the end, A-Z lower-cased) and path (then up to ? # or the end). Without ://, both are empty."""
    at = F.instr(url_col, "://")
    rest = F.when(at > 0, F.substring(F.col(url_col), at + 3, F.length(url_col))).otherwise("")
    urls = urls.withColumn("__rest", rest).withColumn("__raw", F.regexp_extract("__rest", r"^[^/?#]*", 0))
    path = F.regexp_extract(F.substring(F.col("__rest"), F.length("__raw") + 1, F.length("__rest")), r"^[^?#]*", 0)
    return urls.withColumns({"host": F.translate("__raw", UPPER, LOW), "path": path}).drop("__rest", "__raw")


def host_key(host: Column) -> Column:
    return F.concat(F.array_join(F.reverse(F.split(host, r"\.", -1)), "."), F.lit("."))


def inline_rules(spark: SparkSession, rules: Sequence[tuple[str, str, str]]) -> DataFrame:
    """A few rules as a table of literals, so that no Python worker starts for them; many are sent as a table."""
    if not 0 < len(rules) <= INLINE_RULES:
        return spark.createDataFrame(list(rules), RULE_TYPE)
    rows = F.array(*[F.struct(*[F.lit(v).cast("string").alias(n) for n, v in zip(("host", "path", "verdict"), r, strict=True)]) for r in rules])
    return spark.range(1).select(F.inline(rows))


def rule_stacks(rules: DataFrame) -> DataFrame:
    """One row for each rule host: key, and ``stack``, the rules of this host and of every host above it.

    Hosts above are found by an equi-join on the key's own prefixes, of which there are as many as labels.
    """
    hosts = (
        rules.withColumn("key", host_key("host"))
        .groupBy("key")
        .agg(F.sort_array(F.collect_set(F.struct("key", "path", "verdict", F.concat("host", "path").alias("rule")))).alias("own"))
    )
    labels = F.split(F.col("key"), r"\.", -1)
    prefixes = F.transform(F.sequence(F.lit(1), F.size(labels) - 1), lambda k: F.concat(F.array_join(F.slice(labels, 1, k), "."), F.lit(".")))
    above = hosts.select("key", F.explode(prefixes).alias("up"))
    return (
        above.join(hosts.select(F.col("key").alias("up"), "own"), "up")
        .groupBy("key")
        .agg(F.flatten(F.sort_array(F.collect_list("own"))).alias("stack"))
    )


def judge_urls(
    pages: DataFrame,
    rules: DataFrame | Sequence[tuple[str, str, str]],
    id_col: str = "page_id",
    url_col: str = "url",
    default: str = "allow",
    salts: int | None = None,
) -> DataFrame:
    """(id, host, path, rule, verdict) for every row of ``pages``.

    rules: (host, path prefix, verdict) rows or tuples. A rule fits its host and all subdomains where the
    url's path starts with the rule's; of those that fit, the one with the most characters in host and path
    wins, then ``block`` before ``allow``. Without one, rule is null and the verdict ``default``.
    Of hosts, urls' and rules', A-Z are lower-cased. Null or ``://``-less urls have an empty host and path and fit no rule; repeated rows are judged each;
    other columns of ``pages`` are ignored, whatever their names; an empty table gives an empty result.
    """
    spark = pages.sparkSession
    if not isinstance(rules, DataFrame):
        rules = inline_rules(spark, rules)
    rules = rules.select(F.translate("host", UPPER, LOW).alias("host"), F.coalesce("path", F.lit("")).alias("path"), "verdict").where("host is not null")
    stacks = rule_stacks(rules)
    n_hosts = stacks.count()
    cuts: list[str] = []
    if n_hosts > RULES_PER_RANGE:
        # an evenly spaced subset of the rule keys: one of each RULES_PER_RANGE reaches the driver
        step = Window.orderBy("key")
        cuts = [r[0] for r in stacks.select("key", F.row_number().over(step).alias("n")).where((F.col("n") % RULES_PER_RANGE) == 0).orderBy("key").collect()]
    salts = salts or 8 * max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    bounds = F.array(*[F.lit(c) for c in cuts]) if cuts else F.array().cast("array<string>")
    range_of = lambda key: F.size(F.filter(bounds, lambda c: c <= key))

    urls = pages.select(F.col(id_col).alias("__id"), F.coalesce(F.col(url_col).cast("string"), F.lit("")).alias("__u"))
    urls = url_parts(urls, "__u").select("__id", "host", "path", F.pmod(F.xxhash64("__id", "__u"), F.lit(salts)).cast("int").alias("salt"))
    urls = urls.withColumn("key", host_key(F.col("host"))).withColumn("part", range_of(F.col("key")))
    empty_stack = F.lit(None).cast(stacks.schema["stack"].dataType)
    left = urls.select("part", "salt", "key", F.lit(1).alias("kind"), "__id", "host", "path", empty_stack.alias("stack"))
    right = stacks.select(
        range_of(F.col("key")).alias("part"),
        F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"),
        "key",
        F.lit(0).alias("kind"),
        F.lit(None).cast(urls.schema["__id"].dataType).alias("__id"),
        F.lit(None).cast("string").alias("host"),
        F.lit(None).cast("string").alias("path"),
        "stack",
    )
    sweep = Window.partitionBy("part", "salt").orderBy("key", "kind").rowsBetween(Window.unboundedPreceding, 0)
    swept = left.unionByName(right).withColumn("open", F.last("stack", ignorenulls=True).over(sweep)).where("kind = 1")
    fits = F.filter("open", lambda r: F.startswith(F.col("key"), r["key"]) & F.startswith(F.col("path"), r["path"]))
    best = F.element_at(
        F.sort_array(F.transform(fits, lambda r: F.struct(F.length(r["rule"]).alias("n"), r["verdict"].alias("verdict"), r["rule"].alias("rule"))), asc=False), 1
    )
    swept = swept.withColumn("best", F.when(F.size(F.coalesce(fits, F.array().cast(stacks.schema["stack"].dataType))) > 0, best))
    return swept.select(
        F.col("__id").alias(id_col), "host", "path", F.col("best.rule").alias("rule"), F.coalesce("best.verdict", F.lit(default)).alias("verdict")
    )
