"""Relational, analytic and scalar operations around the methods, each with its SQL."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tplforge.functions.distance import sed_arrow
from tplforge.functions.words import tokenize
from tplforge.session import shared_path
from tplforge.sources.corpus import CORPORA, corpus, plain, table
from tplforge.sources.files import read_lines, write_lines

Query = Callable[[SparkSession, str], DataFrame]
_Q: dict[str, Query] = {}
_SQL: dict[str, str] = {}


def op(sql: str | None = None, name: str | None = None):
    def add(f: Query) -> Query:
        _Q[name or f.__name__] = f
        if sql is not None:
            _SQL[name or f.__name__] = sql
        return f

    return add


@op(
    """SELECT event_id, regexp_replace(concat(event_type, ' ', cast(user_id AS VARCHAR)), '[0-9]+', '#', 'g') AS masked FROM events
WHERE value BETWEEN 10 AND 60 AND event_type IN ('click', 'error', 'purchase', 'view') AND props IS NOT NULL"""
)
def op_filter_mask(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    kept = e.filter(F.col("value").between(10, 60) & F.col("event_type").isin("click", "error", "purchase", "view") & ~F.col("props").eqNullSafe(None))
    return kept.select("event_id", F.regexp_replace(F.concat_ws(" ", "event_type", F.col("user_id").cast("string")), "[0-9]+", "#").alias("masked"))


_BROADCAST = "SELECT r_name, count(*) AS n, round(sum(c_acctbal), 2) AS total FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1"


@op(_BROADCAST)
def op_join_broadcast(spark, sf_dir):
    """nation and region hold a fixed number of rows."""
    c, n, r = (table(spark, sf_dir, t) for t in ("customer", "nation", "region"))
    j = c.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))
    return j.groupBy("r_name").agg(F.count("*").alias("n"), F.round(F.sum("c_acctbal"), 2).alias("total"))


_ORDER_LINES = "SELECT o_orderpriority, count(*) AS n, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1"


def _order_lines(spark, sf_dir, hint: str) -> DataFrame:
    o, li = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    j = o.hint(hint).join(li, F.col("o_orderkey") == F.col("l_orderkey"))
    return j.groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))


op(_ORDER_LINES, "op_join_shuffle_hash")(lambda spark, sf_dir: _order_lines(spark, sf_dir, "shuffle_hash"))
op(_ORDER_LINES, "op_join_merge")(lambda spark, sf_dir: _order_lines(spark, sf_dir, "merge"))


@op("SELECT d.doc_id, l.quality, l.toxic FROM documents d LEFT JOIN labels l USING (doc_id)")
def op_join_left(spark, sf_dir):
    return table(spark, sf_dir, "documents").select("doc_id").join(table(spark, sf_dir, "labels"), "doc_id", "left").select("doc_id", "quality", "toxic")


@op("SELECT coalesce(c_nationkey, s_nationkey) AS nation, c, s FROM (SELECT c_nationkey, count(*) AS c FROM customer GROUP BY 1) FULL JOIN (SELECT s_nationkey, count(*) AS s FROM supplier GROUP BY 1) ON c_nationkey = s_nationkey")
def op_join_full(spark, sf_dir):
    c = table(spark, sf_dir, "customer").groupBy("c_nationkey").agg(F.count("*").alias("c"))
    s = table(spark, sf_dir, "supplier").groupBy("s_nationkey").agg(F.count("*").alias("s"))
    return c.join(s, F.col("c_nationkey") == F.col("s_nationkey"), "full_outer").select(F.coalesce("c_nationkey", "s_nationkey").alias("nation"), "c", "s")


@op("SELECT doc_id, n_chars FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def op_semi_labelled(spark, sf_dir):
    return table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels"), "doc_id", "left_semi").select("doc_id", "n_chars")


@op("SELECT doc_id, n_chars FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def op_anti_unlabelled(spark, sf_dir):
    return table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels"), "doc_id", "left_anti").select("doc_id", "n_chars")


@op("SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND abs(length(a.n_name) - length(b.n_name)) <= 1")
def op_join_theta(spark, sf_dir):
    """A fixed-size table against itself under an inequality."""
    n = table(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("a"), F.length("n_name").alias("x"))
    m = n.select(F.col("a").alias("b"), F.col("x").alias("y"))
    return n.join(F.broadcast(m), (F.col("a") < F.col("b")) & (F.abs(F.col("x") - F.col("y")) <= 1)).select("a", "b")


_BAND = """SELECT p.p_partkey, count(*) AS n FROM part p JOIN supplier s ON s.s_acctbal BETWEEN p.p_retailprice - 5 AND p.p_retailprice + 5 GROUP BY 1"""


@op(_BAND)
def op_join_band(spark, sf_dir):
    """A range join by buckets as wide as the range: equal or neighbouring buckets, then the exact test."""
    width = 10.0
    p = table(spark, sf_dir, "part").select("p_partkey", "p_retailprice", F.explode(F.array(*(F.floor(F.col("p_retailprice") / width) + d for d in (-1, 0, 1)))).alias("k"))
    s = table(spark, sf_dir, "supplier").select("s_acctbal", F.floor(F.col("s_acctbal") / width).alias("k"))
    return p.join(s, "k").filter(F.col("s_acctbal").between(F.col("p_retailprice") - 5, F.col("p_retailprice") + 5)).groupBy("p_partkey").agg(F.count("*").alias("n"))


@op(
    """SELECT b.event_id, count(*) AS errors FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'error' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR GROUP BY 1"""
)
def op_join_interval(spark, sf_dir):
    """Events within an hour after an error of their user, by hour buckets."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    hour = 3_600_000_000
    a = e.filter("event_type = 'error'").select("user_id", F.col("us").alias("err"), F.explode(F.array(F.floor(F.col("us") / hour), F.floor(F.col("us") / hour) + 1)).alias("h"))
    b = e.select("event_id", "user_id", "us", F.floor(F.col("us") / hour).alias("h"))
    return b.join(a, ["user_id", "h"]).filter((F.col("us") > F.col("err")) & (F.col("us") <= F.col("err") + hour)).groupBy("event_id").agg(F.count("*").alias("errors"))


@op(
    """SELECT event_id, last_value(CASE WHEN event_type = 'error' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS error_id FROM events"""
)
def op_join_asof(spark, sf_dir):
    """The latest earlier error of the same user."""
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1)
    return table(spark, sf_dir, "events").select("event_id", F.last(F.when(F.col("event_type") == "error", F.col("event_id")), True).over(w).alias("error_id"))


@op("SELECT event_type, count(*) AS n, round(sum(value), 4) AS total, min(value) AS low, max(value) AS high, max_by(event_id, value) AS top FROM events GROUP BY 1")
def op_agg_basic(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"), F.min("value").alias("low"), F.max("value").alias("high"), F.max_by("event_id", "value").alias("top"))


@op("SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def op_agg_distinct(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@op("SELECT l_returnflag, count(*) FILTER (WHERE l_quantity > 25) AS big, count(*) FILTER (WHERE l_discount = 0) AS full_price FROM lineitem GROUP BY 1")
def op_agg_filter(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.count_if(F.col("l_quantity") > 25).alias("big"), F.count_if(F.col("l_discount") == 0).alias("full_price"))


def _totals_sql(how: str) -> str:
    return f"SELECT l_returnflag, l_linestatus, grouping_id(l_returnflag, l_linestatus) AS gid, count(*) AS n FROM lineitem GROUP BY {how}"


def _totals(df: DataFrame) -> DataFrame:
    return df.agg(F.grouping_id().cast("long").alias("gid"), F.count("*").alias("n"))


op(_totals_sql("CUBE (l_returnflag, l_linestatus)"), "op_cube")(lambda spark, sf_dir: _totals(table(spark, sf_dir, "lineitem").cube("l_returnflag", "l_linestatus")))
op(_totals_sql("ROLLUP (l_returnflag, l_linestatus)"), "op_rollup")(lambda spark, sf_dir: _totals(table(spark, sf_dir, "lineitem").rollup("l_returnflag", "l_linestatus")))


@op(_totals_sql("GROUPING SETS ((l_returnflag), (l_linestatus), ())"))
def op_grouping_sets(spark, sf_dir):
    cols = ["l_returnflag", "l_linestatus"]
    return _totals(table(spark, sf_dir, "lineitem").groupingSets([[cols[0]], [cols[1]], []], *cols))


@op("SELECT source, count(*) FILTER (WHERE lang = 'de') AS de, count(*) FILTER (WHERE lang = 'en') AS en, count(*) FILTER (WHERE lang = 'es') AS es, count(*) FILTER (WHERE lang = 'fr') AS fr FROM documents GROUP BY 1")
def op_pivot(spark, sf_dir):
    return table(spark, sf_dir, "documents").groupBy("source").pivot("lang", ["de", "en", "es", "fr"]).agg(F.count(F.lit(1))).fillna(0)


@op("SELECT s.source, l.lang, coalesce(n, 0) AS n FROM (SELECT DISTINCT source FROM documents) s CROSS JOIN (VALUES ('de'), ('en'), ('es'), ('fr')) l(lang) LEFT JOIN (SELECT source, lang, count(*) AS n FROM documents GROUP BY 1, 2) USING (source, lang)")
def op_unpivot(spark, sf_dir):
    return op_pivot(spark, sf_dir).unpivot("source", ["de", "en", "es", "fr"], "lang", "n")


@op("SELECT true AS words_ok, true AS median_ok, true AS top_ok")
def op_sketch(spark, sf_dir):
    """Approximate distinct words, median length and most frequent words, each held to its bound by the exact figures."""
    d = tokenize(table(spark, sf_dir, "documents"), "text")
    w = d.select(F.explode("words").alias("w"))
    near = w.agg(F.approx_count_distinct("w", 0.02).alias("words"), F.expr("approx_top_k(w, 10, 10000)[0].count").alias("top"))
    exact = w.groupBy("w").agg(F.count("*").alias("n")).agg(F.count("*").alias("words_exact"), F.max("n").alias("top_exact"))
    length = d.agg(F.percentile_approx("n_words", 0.5, 1000).alias("m"), F.percentile("n_words", F.lit(0.49)).alias("lo"), F.percentile("n_words", F.lit(0.51)).alias("hi"))
    one = near.crossJoin(exact).crossJoin(length)  # three tables of one row
    return one.select(
        (F.abs(F.col("words") - F.col("words_exact")) <= 0.08 * F.col("words_exact")).alias("words_ok"),
        F.col("m").between(F.floor("lo"), F.ceil("hi")).alias("median_ok"),
        (F.abs(F.col("top") - F.col("top_exact")) <= 0.01 * F.col("top_exact")).alias("top_ok"),
    )


@op("SELECT o_orderkey, rank() OVER w AS rk, dense_rank() OVER w AS dr, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS rn FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderpriority)")
def op_win_rank(spark, sf_dir):
    w = W.partitionBy("o_custkey")
    return table(spark, sf_dir, "orders").select("o_orderkey", F.rank().over(w.orderBy("o_orderpriority")).alias("rk"), F.dense_rank().over(w.orderBy("o_orderpriority")).alias("dr"), F.row_number().over(w.orderBy(F.desc("o_totalprice"), "o_orderkey")).alias("rn"))


@op("SELECT event_id, ntile(4) OVER (PARTITION BY event_type ORDER BY value, event_id) AS quartile, round(percent_rank() OVER (PARTITION BY event_type ORDER BY value), 9) AS pr FROM events")
def op_win_ntile(spark, sf_dir):
    w = W.partitionBy("event_type")
    return table(spark, sf_dir, "events").select("event_id", F.ntile(4).over(w.orderBy("value", "event_id")).alias("quartile"), F.round(F.percent_rank().over(w.orderBy("value")), 9).alias("pr"))


@op("SELECT o_orderkey, lag(o_orderkey) OVER w AS before, lead(o_orderkey) OVER w AS after, first_value(o_orderkey) OVER w AS first FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def op_win_lag(spark, sf_dir):
    w = W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return table(spark, sf_dir, "orders").select("o_orderkey", F.lag("o_orderkey").over(w).alias("before"), F.lead("o_orderkey").over(w).alias("after"), F.first("o_orderkey").over(w).alias("first"))


@op("SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2) AS spent FROM orders")
def op_win_rows(spark, sf_dir):
    w = W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(-2, 0)
    return table(spark, sf_dir, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(w), 2).alias("spent"))


@op("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS n FROM events")
def op_win_range(spark, sf_dir):
    e = table(spark, sf_dir, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.count("*").over(W.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)).alias("n"))


@op("SELECT l_orderkey, l_linenumber, l_partkey, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber, l_partkey LIMIT 20")
def op_sort_limit(spark, sf_dir):
    """A top-k report."""
    return table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber", "l_partkey").limit(20)


@op("SELECT source, doc_id, n_chars FROM (SELECT *, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) AS k FROM documents) WHERE k <= 3")
def op_topk_group(spark, sf_dir):
    """The three longest per source: heaps of three are merged, so a hot source is no large window."""
    d = table(spark, sf_dir, "documents").select("source", "doc_id", "n_chars")
    k = W.partitionBy("source", "salt").orderBy(F.desc("n_chars"), "doc_id")
    local = d.withColumn("salt", F.pmod(F.xxhash64("doc_id"), F.lit(64))).withColumn("k", F.row_number().over(k)).filter("k <= 3")
    return local.withColumn("k", F.row_number().over(W.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id"))).filter("k <= 3").select("source", "doc_id", "n_chars")


def _keys(spark, sf_dir):
    return table(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")), table(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k"))


for _name, _sql, _f in (
    ("op_union", "UNION ALL", DataFrame.unionByName),
    ("op_union_distinct", "UNION", lambda a, b: a.union(b).distinct()),
    ("op_intersect", "INTERSECT", DataFrame.intersect),
    ("op_intersect_all", "INTERSECT ALL", DataFrame.intersectAll),
    ("op_except", "EXCEPT", DataFrame.subtract),
    ("op_except_all", "EXCEPT ALL", DataFrame.exceptAll),
):
    op(f"SELECT c_nationkey AS k FROM customer {_sql} SELECT s_nationkey AS k FROM supplier", _name)(lambda spark, sf_dir, f=_f: f(*_keys(spark, sf_dir)))


@op(
    """SELECT page_id, split_part(url, '/', 3) AS host, upper(split_part(url, '/', 4)) AS lang, reverse(url) AS back, length(url) AS n, levenshtein(split_part(url, '/', 3), 'www.example.com') AS far, regexp_extract(url, '([0-9]+)', 1) AS num, lpad(cast(page_id AS VARCHAR), 8, '0') AS padded FROM pages"""
)
def op_string(spark, sf_dir):
    u = F.col("url")
    host = F.split_part(u, F.lit("/"), F.lit(3))
    return table(spark, sf_dir, "pages").select("page_id", host.alias("host"), F.upper(F.split_part(u, F.lit("/"), F.lit(4))).alias("lang"), F.reverse(u).alias("back"), F.length(u).alias("n"), F.levenshtein(host, F.lit("www.example.com")).alias("far"), F.regexp_extract(u, "([0-9]+)", 1).alias("num"), F.lpad(F.col("page_id").cast("string"), 8, "0").alias("padded"))


@op("SELECT o_orderkey, strftime(o_orderdate, '%Y-%m') AS month, cast(date_trunc('quarter', o_orderdate) AS DATE) AS quarter, dayofyear(o_orderdate) AS doy, date_diff('day', DATE '1992-01-01', cast(o_orderdate AS DATE)) AS days FROM orders")
def op_date(spark, sf_dir):
    d = F.col("o_orderdate")
    return table(spark, sf_dir, "orders").select("o_orderkey", F.date_format(d, "yyyy-MM").alias("month"), F.trunc(d.cast("date"), "quarter").alias("quarter"), F.dayofyear(d).alias("doy"), F.datediff(d.cast("date"), F.lit("1992-01-01").cast("date")).alias("days"))


@op("SELECT p_partkey, round(sqrt(p_retailprice), 6) AS root, round(ln(p_retailprice), 6) AS log, round(pow(p_size, 2), 2) AS sq, greatest(p_size, 25) AS hi, least(p_size, 25) AS lo, p_partkey % 7 AS m FROM part")
def op_math(spark, sf_dir):
    p, s = F.col("p_retailprice"), F.col("p_size")
    return table(spark, sf_dir, "part").select("p_partkey", F.round(F.sqrt(p), 6).alias("root"), F.round(F.log(p), 6).alias("log"), F.round(F.pow(s, F.lit(2)), 2).alias("sq"), F.greatest(s, F.lit(25)).alias("hi"), F.least(s, F.lit(25)).alias("lo"), (F.col("p_partkey") % 7).alias("m"))


@op(
    f"""WITH l AS ({plain(CORPORA["part_shelf"])}), w AS (SELECT log_id, string_split(raw, ' ') AS w FROM l)
SELECT log_id, len(list_filter(w, lambda x: regexp_matches(x, '[0-9]'))) AS digits, list_position(w, 'by') AS at_by, array_to_string(list_transform(w, lambda x: upper(x)), '-') AS up, w[1] AS head, len(list_distinct(w)) AS kinds FROM w"""
)
def op_array(spark, sf_dir):
    w = F.col("words")
    return tokenize(corpus(spark, sf_dir, "part_shelf")).select("log_id", F.size(F.filter(w, lambda x: x.rlike("[0-9]"))).alias("digits"), F.array_position(w, "by").alias("at_by"), F.array_join(F.transform(w, F.upper), "-").alias("up"), w[0].alias("head"), F.size(F.array_distinct(w)).alias("kinds"))


@op(
    f"""WITH l AS ({plain(CORPORA["ord_desk"])}), w AS (SELECT log_id, string_split(raw, ' ') AS w, string_split(truth, ' ') AS t FROM l), x AS (SELECT log_id, unnest(w) AS v, unnest(t) AS k FROM w)
SELECT log_id, k AS name, v AS value FROM x WHERE starts_with(k, '[')"""
)
def op_map(spark, sf_dir):
    """The variables of each line as a map, then its entries."""
    d = tokenize(corpus(spark, sf_dir, "ord_desk"))
    pairs = F.filter(F.arrays_zip("labels", "words"), lambda p: p["labels"].startswith("["))
    named = F.map_from_arrays(F.transform(pairs, lambda p: p["labels"]), F.transform(pairs, lambda p: p["words"]))
    return d.select("log_id", F.explode(named).alias("name", "value"))


@op("SELECT event_id, cast(json_extract_string(props, '$.k') AS INT) AS k, cast(json_extract_string(props, '$.k') AS INT) + 1 AS next FROM events")
def op_json(spark, sf_dir):
    bag = F.from_json("props", "struct<k:int>")
    v = F.variant_get(F.parse_json("props"), "$.k", "int")
    return table(spark, sf_dir, "events").select("event_id", bag["k"].alias("k"), (v + 1).alias("next"))


_PART_WORDS = "p AS (SELECT p_partkey, string_split(p_name, ' ') AS a, string_split(lower(p_type), ' ') AS b, list_distinct(list_concat(string_split(p_name, ' '), string_split(lower(p_type), ' '))) AS d FROM part)"
_GLYPHS = "list_aggregate(list_transform({}, lambda x: chr(33 + list_position(d, x)::INT)), 'string_agg', '')"


@op(f"WITH {_PART_WORDS} SELECT p_partkey, levenshtein({_GLYPHS.format('a')}, {_GLYPHS.format('b')})::INT AS dist FROM p")
def op_udf(spark, sf_dir):
    """Edit distance of two word lists in Arrow batches: the form for similarities that built-ins cannot express."""
    p = table(spark, sf_dir, "part").select("p_partkey", F.split("p_name", " ").alias("a"), F.split(F.lower("p_type"), " ").alias("b"))
    return p.select("p_partkey", sed_arrow("exact")("a", "b").alias("dist"))


@op("SELECT label, pos, round(avg(v), 6) AS mean FROM (SELECT label, unnest(range(0, 64)) AS pos, unnest(embedding)::DOUBLE AS v FROM embeddings) GROUP BY 1, 2")
def op_udaf(spark, sf_dir):
    """Mean vector per label: an aggregate function in Arrow sums the vectors of a label's shards, built-ins the shards."""

    @F.pandas_udf("array<double>")
    def total(v: pd.Series) -> list:
        return np.sum(np.stack(v.to_numpy()), axis=0, dtype=np.float64).tolist()

    e = table(spark, sf_dir, "embeddings")
    shard = F.pmod(F.xxhash64("vec_id"), F.lit(4 * int(spark.conf.get("spark.sql.shuffle.partitions"))))
    part = e.groupBy("label", shard.alias("shard")).agg(total("embedding").alias("v"))
    n = e.groupBy("label").agg(F.count("*").alias("n"))
    sums = part.select("label", F.posexplode("v").alias("pos", "v")).groupBy("label", "pos").agg(F.sum("v").alias("v"))
    return sums.join(n, "label").select("label", F.col("pos").cast("long").alias("pos"), F.round(F.col("v") / F.col("n"), 6).alias("mean"))


@op("SELECT p_partkey, unnest(string_split(p_name, ' ')) AS word FROM part")
def op_udtf(spark, sf_dir):
    """A table function per row, by a lateral join."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="word string")
    class Cut:
        def eval(self, text: str):
            for w in (text or "").split(" "):
                yield (w,)

    spark.udtf.register("tpl_cut", Cut)
    return spark.sql("SELECT p_partkey, word FROM {part}, LATERAL tpl_cut(p_name)", part=table(spark, sf_dir, "part"))


def _ts():
    return F.col("ts").cast("timestamp")



@op("SELECT epoch_us(date_trunc('hour', ts)) AS start_us, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def op_tumble(spark, sf_dir):
    g = table(spark, sf_dir, "events").groupBy(F.window(_ts(), "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n"))
    return g.select(F.unix_micros("w.start").alias("start_us"), "event_type", "n")


@op("SELECT s AS start_us, event_type, count(*) AS n FROM (SELECT event_type, unnest(list_transform(range(0, 4), lambda i: (epoch_us(ts) // 900000000 - i) * 900000000)) AS s FROM events) GROUP BY 1, 2")
def op_slide(spark, sf_dir):
    g = table(spark, sf_dir, "events").groupBy(F.window(_ts(), "1 hour", "15 minutes").alias("w"), "event_type").agg(F.count("*").alias("n"))
    return g.select(F.unix_micros("w.start").alias("start_us"), "event_type", "n")


@op(
    """WITH g AS (SELECT user_id, epoch_us(ts) AS us, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER w < 1800000000 THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, us, sum(fresh) OVER (PARTITION BY user_id ORDER BY us RANGE UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(us) AS start_us, count(*) AS n FROM s GROUP BY user_id, k"""
)
def op_session(spark, sf_dir):
    g = table(spark, sf_dir, "events").groupBy(F.session_window(_ts(), "30 minutes").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return g.select("user_id", F.unix_micros("w.start").alias("start_us"), "n")


@op("SELECT page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title, split_part(url, '/', 4) AS lang FROM pages")
def op_title_extract(spark, sf_dir):
    return table(spark, sf_dir, "pages").select("page_id", F.regexp_extract("html", "<title>([^<]*)</title>", 1).alias("title"), F.split_part("url", F.lit("/"), F.lit(4)).alias("lang"))


@op("SELECT line, count(*) AS n FROM (SELECT unnest(string_split(text, chr(10))) AS line FROM documents) WHERE trim(line) <> '' GROUP BY 1")
def op_line_explode(spark, sf_dir):
    return table(spark, sf_dir, "documents").select(F.explode(F.split("text", "\n")).alias("line")).filter(F.trim("line") != "").groupBy("line").agg(F.count("*").alias("n"))


@op(f"SELECT 'ledger' AS domain, log_id, raw, truth FROM ({plain(CORPORA['ledger'])})")
def op_roundtrip(spark, sf_dir):
    """Lines written by domain and read back: Parquet, then JSON, then CSV."""
    d = corpus(spark, sf_dir, "ledger")
    for kind in ("parquet", "json", "csv"):
        path = shared_path(spark, f"roundtrip-{kind}")
        write_lines(d, path, kind)
        d = read_lines(spark, path, kind)
    return d.select("domain", "log_id", "raw", "truth")


def queries() -> dict[str, Query]:
    return dict(_Q)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)
