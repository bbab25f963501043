"""Accuracy, cost and trace measures over predictions(domain, method, log_id, truth, pred, ...)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PRICE = 3.6e-6
KEYS = ("domain", "method")


def mla(df: DataFrame, keys=KEYS) -> DataFrame:
    """Share of lines whose predicted template is the true one."""
    return df.groupBy(*keys).agg(F.avg((F.col("pred") == F.col("truth")).cast("double")).alias("mla"))


def _group_rate(df: DataFrame, by: str, name: str, keys) -> DataFrame:
    clean = df.groupBy(*keys, by).agg(F.min((F.col("pred") == F.col("truth")).cast("int")).alias("ok"))
    return clean.groupBy(*keys).agg(F.avg(F.col("ok").cast("double")).alias(name))


def pta(df: DataFrame, keys=KEYS) -> DataFrame:
    """Share of predicted templates all of whose lines are right."""
    return _group_rate(df, "pred", "pta", keys)


def rta(df: DataFrame, keys=KEYS) -> DataFrame:
    """Share of true templates all of whose lines are right."""
    return _group_rate(df, "truth", "rta", keys)


def lines_of(df: DataFrame) -> Column:
    """How many lines a row stands for: n, or 1 where there is no such column."""
    return F.col("n") if "n" in df.columns else F.lit(1)


def _mean(df: DataFrame, value: Column) -> Column:
    """The mean over lines."""
    n = lines_of(df)
    return F.sum(value * n) / F.sum(n)


def cells_of(df: DataFrame, keys=KEYS) -> DataFrame:
    """n lines per (truth, pred)."""
    return df.groupBy(*keys, "truth", "pred").agg(F.sum(lines_of(df)).alias("n"))


def accuracy(df: DataFrame, keys=KEYS, cells: DataFrame | None = None) -> DataFrame:
    """All three from one pass: every figure follows from counts per (truth, pred). cells: these counts, if they are there already."""
    cells = cells_of(df, keys) if cells is None else cells
    right = F.col("truth") == F.col("pred")
    lines = cells.groupBy(*keys).agg((F.sum(F.when(right, F.col("n")).otherwise(0)) / F.sum("n")).alias("mla"))
    out = lines
    for by, name in (("pred", "pta"), ("truth", "rta")):
        clean = cells.groupBy(*keys, by).agg(F.min(right.cast("int")).alias("ok"))
        out = out.join(clean.groupBy(*keys).agg(F.avg(F.col("ok").cast("double")).alias(name)), list(keys))
    return out


def tokens(text: Column) -> Column:
    """A token for every four characters begun."""
    return F.ceil(F.length(text) / 4).cast("long")


def api_cost(df: DataFrame, keys=KEYS, price: float = PRICE) -> DataFrame:
    tokens = F.sum(F.col("tokens") * lines_of(df))
    return df.groupBy(*keys).agg(tokens.alias("tokens"), (tokens * price).alias("usd"), (_mean(df, F.col("tokens")) * price).alias("usd_per_line"))


def time_per_line(df: DataFrame, keys=KEYS, start: float = 0.2, per_token: float = 0.002) -> DataFrame:
    """Modelled seconds: a fixed part per call and a part per token."""
    return df.groupBy(*keys).agg((F.lit(start) + _mean(df, F.col("tokens")) * per_token).alias("seconds_per_line"))


def context_size(df: DataFrame, keys=KEYS) -> DataFrame:
    return df.groupBy(*keys).agg(_mean(df, F.size("demos")).alias("demos_mean"), F.max(F.size("demos")).alias("demos_max"), _mean(df, F.col("tokens")).alias("tokens_mean"), F.max("tokens").alias("tokens_max"))


def gen_error(words: Column, echo: Column) -> Column:
    """1 where the answer lost or invented words."""
    return F.when(words == echo, 0).otherwise(1)


def word_errors(labels: Column, true_labels: Column) -> Column:
    """Words whose label differs, over the positions both have."""
    n = F.least(F.size(labels), F.size(true_labels))
    return F.size(F.filter(F.zip_with(F.slice(labels, 1, n), F.slice(true_labels, 1, n), lambda x, y: x != y), lambda b: b))


def errors(df: DataFrame, keys=KEYS) -> DataFrame:
    return df.groupBy(*keys).agg(F.sum(gen_error(F.col("words"), F.col("echo")) * lines_of(df)).alias("gen_errors"), F.sum(word_errors(F.col("labels"), F.col("true_labels")) * lines_of(df)).alias("word_errors"))


def coverage(chosen: DataFrame, edges: DataFrame, u: int) -> DataFrame:
    """Share of lines that some chosen line stands for."""
    hit = edges.join(chosen.select(F.col("log_id").alias("src")), "src", "left_semi")
    return hit.agg((F.countDistinct("dst") / F.lit(float(max(u, 1)))).alias("coverage"))


def corpus_stats(lines: DataFrame) -> DataFrame:
    """Templates, distinct lines and distinct words per domain, of tokenised lines."""
    own = lines.groupBy("domain").agg(F.countDistinct("truth").alias("templates"), F.countDistinct("raw").alias("n_lines"))
    words = lines.select("domain", F.explode("words").alias("w")).groupBy("domain").agg(F.countDistinct("w").alias("n_words"))
    return own.join(words, "domain")


def delta(df: DataFrame, base: str, keys=("domain",), measures=("mla", "pta", "rta")) -> DataFrame:
    """Measures of every other method less those of `base`, in points."""
    b = df.filter(F.col("method") == base).select(*keys, *(F.col(m).alias(f"base_{m}") for m in measures))
    return df.filter(F.col("method") != base).join(b, list(keys)).select(*keys, "method", *((100 * (F.col(m) - F.col(f"base_{m}"))).alias(f"d_{m}") for m in measures))
