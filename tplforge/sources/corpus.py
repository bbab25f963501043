"""Line corpora with known templates, rendered from the given tables.

One text serves Spark and the checking engine: `{table}` stands for a table.
Doubles become decimals before text, so both engines print the same digits.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

CORPORA: dict[str, str] = {
    "evt_simple": """
select event_id log_id, concat(event_type,' event from user ',cast(user_id as string),' amount ',cast(cast(value as decimal(18,2)) as string)) raw,
 concat(event_type,' event from user [USER] amount [AMOUNT]') truth from {events}""",
    "evt_rich": """
select event_id log_id,
 case event_id % 4 when 0 then concat(cast(cast(ts as date) as string),' ',event_type,' accepted for user ',cast(user_id as string))
  when 1 then concat(event_type,' rejected for user ',cast(user_id as string),' code ',regexp_extract(props,'[0-9]+',0))
  when 2 then concat('session s',cast(user_id as string),'-',cast(event_id as string),' ',event_type,' cost ',cast(cast(value as decimal(18,2)) as string),' units')
  else concat('peer 10.0.',cast(user_id % 256 as string),'.',regexp_extract(props,'[0-9]+',0),':8080 ',event_type,' finished') end raw,
 case event_id % 4 when 0 then concat('[DATE] ',event_type,' accepted for user [USER]')
  when 1 then concat(event_type,' rejected for user [USER] code [CODE]')
  when 2 then concat('session [SESSION] ',event_type,' cost [AMOUNT] units')
  else concat('peer [ADDR] ',event_type,' finished') end truth from {events}""",
    "ord_desk": """
select o_orderkey log_id,
 case o_orderkey % 2 when 0 then concat('order ',cast(o_orderkey as string),' status ',o_orderstatus,' priority ',replace(o_orderpriority,' ','_'),' total ',cast(cast(o_totalprice as decimal(18,2)) as string))
  else concat(cast(cast(o_orderdate as date) as string),' customer ',cast(o_custkey as string),' placed ',replace(o_orderpriority,' ','_'),' order now ',o_orderstatus) end raw,
 case o_orderkey % 2 when 0 then concat('order [ORDER] status ',o_orderstatus,' priority ',replace(o_orderpriority,' ','_'),' total [AMOUNT]')
  else concat('[DATE] customer [CUST] placed ',replace(o_orderpriority,' ','_'),' order now ',o_orderstatus) end truth from {orders}""",
    "ship_line": """
select ((l_orderkey*8+l_linenumber)*1000000+l_partkey)*100000+(year(l_shipdate)-1990)*372+month(l_shipdate)*31+day(l_shipdate) log_id, concat('part ',cast(l_partkey as string),' from supplier ',cast(l_suppkey as string),' ',
  case l_linenumber % 4 when 0 then 'picked' when 1 then 'packed' when 2 then 'loaded' else 'sent' end,' flag ',l_returnflag,' state ',l_linestatus,' on ',cast(cast(l_shipdate as date) as string)) raw,
 concat('part [PART] from supplier [SUPP] ',case l_linenumber % 4 when 0 then 'picked' when 1 then 'packed' when 2 then 'loaded' else 'sent' end,' flag ',l_returnflag,' state ',l_linestatus,' on [DATE]') truth from {lineitem}""",
    "part_shelf": """
select p_partkey log_id, concat('part ',cast(p_partkey as string),' ',lower(p_type),' ',p_name,' by ',p_brand,' size ',cast(p_size as string),' price ',cast(cast(p_retailprice as decimal(18,2)) as string)) raw,
 concat('part [PART] ',lower(p_type),' ',p_name,' by [BRAND] size [SIZE] price [AMOUNT]') truth from {part}""",
    "ledger": """
select c_custkey*2 log_id, concat('customer ',c_name,' segment ',lower(c_mktsegment),' in ',n_name,case when c_acctbal<0 then ' debit ' else ' credit ' end,cast(abs(cast(c_acctbal as decimal(18,2))) as string)) raw,
 concat('customer [NAME] segment ',lower(c_mktsegment),' in [NATION]',case when c_acctbal<0 then ' debit' else ' credit' end,' [AMOUNT]') truth from {customer} join {nation} on c_nationkey=n_nationkey
 union all select s_suppkey*2+1, concat('supplier ',s_name,' in ',n_name,case when s_acctbal<0 then ' owes ' else ' holds ' end,cast(abs(cast(s_acctbal as decimal(18,2))) as string)),
 concat('supplier [NAME] in [NATION]',case when s_acctbal<0 then ' owes' else ' holds' end,' [AMOUNT]') from {supplier} join {nation} on s_nationkey=n_nationkey""",
    "web_hits": """
select page_id log_id, concat(case page_id % 3 when 0 then 'GET' when 1 then 'POST' else 'HEAD' end,' ',url,' lang ',split_part(url,'/',4),case when page_id % 5 = 0 then ' missing 404' else ' served 200' end) raw,
 concat(case page_id % 3 when 0 then 'GET' when 1 then 'POST' else 'HEAD' end,' [URL] lang ',split_part(url,'/',4),case when page_id % 5 = 0 then ' missing [CODE]' else ' served [CODE]' end) truth from {pages}""",
    "chat_lines": "select conv_id * 1000 + turn log_id, concat(role, ' ', text) raw, cast(null as string) truth from {conversations}",
    "bench_lines": "select item_id log_id, text raw, cast(null as string) truth from {benchmark}",
}
#: tables of one size
FIXED = ("nation", "region")
#: corpora with known templates
TRUTH = ("evt_simple", "evt_rich", "ord_desk", "ship_line", "part_shelf", "ledger", "web_hits")
#: total budget and start-up budgets per corpus
BUDGETS = {"evt_simple": (50, (10, 10)), "ledger": (50, (10, 10))} | {c: (200, (50, 25)) for c in ("evt_rich", "ord_desk", "ship_line", "part_shelf", "web_hits")}

#: the workloads take a tenth of the budgets, because a label here covers a pattern (all lines of one shape) and most corpora
#: have fewer patterns than labels; ablation and sweeps, whose corpora are flat from there on, a fiftieth. So a budget decides something.
SCALE, SWEEP_SCALE = 10, 50


def scaled(name: str, scale: int = SCALE) -> tuple[int, tuple[int, ...]]:
    """Budget and start-up budgets of a corpus, divided by scale, 1 at least."""
    total, start = BUDGETS[name]
    return max(1, total // scale), tuple(max(1, x // scale) for x in start)


def tables_of(sql: str) -> list[str]:
    return sorted(set(re.findall(r"\{(\w+)\}", sql)))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def query(spark: SparkSession, sf_dir: str, sql: str, spread: bool = False) -> DataFrame:
    """A text with {table} placeholders as a DataFrame. spread: rows are dealt to all tasks first, since a small file is read by one or two."""
    tables = {t: table(spark, sf_dir, t) for t in tables_of(sql)}
    if spread:
        tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
        # by the key, which stands first
        tables = {t: d if t in FIXED else d.repartition(tasks, d.columns[0]) for t, d in tables.items()}
    return spark.sql(sql, **tables)


def plain(sql: str) -> str:
    """The same text with the tables' own names."""
    return re.sub(r"\{(\w+)\}", r"\1", sql)


def corpus(spark: SparkSession, sf_dir: str, name: str, spread: bool = False) -> DataFrame:
    """log_id, domain, raw, truth."""
    return query(spark, sf_dir, CORPORA[name], spread).select("log_id", F.lit(name).alias("domain"), "raw", "truth")


def document_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Non-blank lines of documents: domain doc_lines, log_id from document and place."""
    d = table(spark, sf_dir, "documents").select("doc_id", F.posexplode(F.split("text", "\n")).alias("pos", "raw"))
    return d.filter(F.length(F.trim("raw")) > 0).select((F.col("doc_id") * 1_000_000 + F.col("pos")).alias("log_id"), F.lit("doc_lines").alias("domain"), "raw", F.lit(None).cast("string").alias("truth"))
