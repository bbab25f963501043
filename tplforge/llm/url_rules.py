"""URL rules by a sort-merge range join, in DataFrame operations only.

A rule (host, path) fits its host and all subdomains where the path starts with
the rule's. With the labels of hosts reversed (`com.example.www.`), all hosts
under a rule's host share a prefix, and strings that share a prefix are one
interval of the sorted order. Such intervals are nested or disjoint, so a sorted
sweep over interval starts, keys and interval ends has a stack of open intervals
at every key. A start event carries the stack after its push, an end event the
stack after its pop, and the running `last` over the sorted events is the stack
a key meets. Rules differ in two strings, so there are two sweeps: paths first;
each path prefix that is open at a path then sweeps the hosts of its own rules.

Distinct keys are dealt to many small buckets by hash and the events of the rules
are copied to every bucket (a bucket is what one window sorts): a hot host or a
repeated url puts no extra rows in one task.

Null urls and urls without `://` have an empty host and path and fit no rule.
Rows are kept as they are, repeated ones too; of rules that repeat, block wins.
An empty rule table leaves every url to the default verdict.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: (host, path, verdict) of the contract
RULES = (
    ("com", "/", "allow"),
    ("example.com", "/en/", "block"),
    ("www.example.com", "/en/", "allow"),
    ("net", "/es/", "block"),
    ("net", "/fr/", "block"),
)
#: sorts behind every string with the prefix before it
_LAST = "\U0010ffff"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def rule_table(spark: SparkSession, rules=RULES) -> DataFrame:
    """Rules as a table made of literals."""
    if not rules:
        return spark.sql("SELECT '' AS host, '' AS path, '' AS verdict WHERE false")
    made = F.array(*(F.struct(*(F.lit(x).alias(n) for x, n in zip(r, ("host", "path", "verdict"), strict=True))) for r in rules))
    return spark.range(1).select(F.inline(made))


def host_of(url: Column) -> Column:
    rest = F.substring(url, F.instr(url, "://") + 3, F.length(url))
    host = F.translate(F.regexp_extract(rest, r"^[^/?#]*", 0), _UPPER, _LOWER)
    return F.coalesce(F.when(F.instr(url, "://") > 0, host), F.lit(""))


def path_of(url: Column) -> Column:
    rest = F.substring(url, F.instr(url, "://") + 3, F.length(url))
    return F.coalesce(F.when(F.instr(url, "://") > 0, F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)), F.lit(""))


def reversed_host(host: Column) -> Column:
    return F.concat(F.array_join(F.reverse(F.split(host, r"\.")), "."), F.lit("."))


def stack_events(prefixes: DataFrame) -> DataFrame:
    """prefixes(prefix), distinct -> events(key, kind, stack): the open intervals after each start and end."""
    own = prefixes.select("prefix", F.explode(F.expr("transform(sequence(0, length(prefix)), i -> left(prefix, i))")).alias("part"))
    nested = own.join(prefixes.select(F.col("prefix").alias("part")), "part")
    stacks = nested.groupBy("prefix").agg(F.expr("transform(array_sort(collect_set(struct(length(part) AS n, part))), x -> x.part)").alias("stack"))
    starts = stacks.select(F.col("prefix").alias("key"), F.lit(0).alias("kind"), "stack")
    ends = stacks.select(F.concat("prefix", F.lit(_LAST)).alias("key"), F.lit(2).alias("kind"), F.expr("slice(stack, 1, size(stack) - 1)").alias("stack"))
    return starts.unionByName(ends)


def sweep(keys: DataFrame, prefixes: DataFrame, buckets: int) -> DataFrame:
    """keys(key), distinct -> (key, stack): all prefixes of each key, shortest first."""
    n = F.lit(buckets)
    points = keys.select(F.pmod(F.xxhash64("key"), n).alias("bucket"), "key", F.lit(1).alias("kind"), F.lit(None).cast("array<string>").alias("stack"))
    events = stack_events(prefixes).select(F.explode(F.sequence(F.lit(0).cast("long"), n.cast("long") - 1)).alias("bucket"), "key", "kind", "stack")
    # at equal keys: pops, then pushes from the outside in, then the key itself
    order = W.partitionBy("bucket").orderBy("key", F.when(F.col("kind") == 2, -1).otherwise(F.col("kind"))).rowsBetween(W.unboundedPreceding, 0)
    swept = points.unionByName(events).withColumn("stack", F.last("stack", ignorenulls=True).over(order))
    return swept.filter("kind = 1").select("key", F.coalesce("stack", F.array().cast("array<string>")).alias("stack"))


def judge_urls(pages: DataFrame, rules: DataFrame, id_col: str = "page_id", url_col: str = "url", default: str = "allow", buckets: int | None = None) -> DataFrame:
    """id, host, path, rule (host and path of the longest fitting rule, or null) and verdict of every row."""
    buckets = buckets or 4 * int(pages.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    urls = pages.select(F.col(id_col).alias("page_id"), host_of(F.col(url_col)).alias("host"), path_of(F.col(url_col)).alias("path"))
    # the prefix of a rule among the rules of its path: a fixed-length name of the path, then the reversed host
    named = (
        rules.groupBy(F.translate("host", _UPPER, _LOWER).alias("r_host"), F.col("path").alias("r_path"))
        .agg(F.max("verdict").alias("r_verdict"))
        .withColumn("prefix", F.concat(F.md5("r_path"), reversed_host(F.col("r_host"))))
    )
    by_path = sweep(urls.select(F.col("path").alias("key")).distinct(), named.select(F.col("r_path").alias("prefix")).distinct(), buckets)
    open_paths = by_path.select(F.col("key").alias("path"), F.explode("stack").alias("r_path"))
    pairs = urls.select("host", "path").distinct().join(open_paths, "path").withColumn("key", F.concat(F.md5("r_path"), reversed_host(F.col("host"))))
    by_host = sweep(pairs.select("key").distinct(), named.select("prefix").distinct(), buckets).filter("size(stack) > 0").select("key", F.element_at("stack", -1).alias("prefix"))
    fits = pairs.join(by_host, "key").join(named, ["prefix", "r_path"])
    longest = fits.groupBy("host", "path").agg(
        F.max_by(F.struct("r_host", "r_path", "r_verdict"), F.struct(F.length("r_host") + F.length("r_path"), F.length("r_host"))).alias("best")
    )
    return urls.join(longest, ["host", "path"], "left").select(
        "page_id", "host", "path", F.concat("best.r_host", "best.r_path").alias("rule"), F.coalesce("best.r_verdict", F.lit(default)).alias("verdict")
    )


ORACLE = """
WITH u AS (
  SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) END AS rest FROM pages
), s AS (
  SELECT page_id, coalesce(translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '') AS host,
         coalesce(regexp_extract(rest, '^[^/?#]*([^?#]*)', 1), '') AS path FROM u
), r(h, p, v) AS (VALUES ('com', '/', 'allow'), ('example.com', '/en/', 'block'), ('www.example.com', '/en/', 'allow'), ('net', '/es/', 'block'), ('net', '/fr/', 'block')),
best AS (
  SELECT s.page_id, max_by(h || p, length(h || p)) AS rule, max_by(v, length(h || p)) AS verdict
  FROM s JOIN r ON starts_with(s.path, r.p) AND (s.host = r.h OR ends_with(s.host, '.' || r.h)) GROUP BY 1
)
SELECT s.page_id, s.host, s.path, best.rule, coalesce(best.verdict, 'allow') AS verdict FROM s LEFT JOIN best USING (page_id)
"""
