"""Prompts: instruction, labelled examples, the line and its words."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

INSTRUCTION = "Give every word of the last line its role: keep fixed words, replace variable ones by a type in brackets."


def build(line: Column, demos: Column) -> Column:
    """demos: array of struct(raw, template)."""
    shown = F.array_join(F.transform(demos, lambda d: F.concat(F.lit("Line: "), d["raw"], F.lit("\nTemplate: "), d["template"], F.lit("\n"))), "")
    words = F.array_join(F.split(line, r"\s+"), " | ")
    return F.concat(F.lit(INSTRUCTION + "\n"), shown, F.lit("Line: "), line, F.lit("\nWords: "), words, F.lit("\nTemplate:"))


def text(words: list[str], demos: list[tuple[tuple[str, ...], tuple[str, ...]]]) -> str:
    """The same for one line outside Spark."""
    shown = "".join(f"Line: {' '.join(w)}\nTemplate: {' '.join(t)}\n" for w, t in demos)
    return f"{INSTRUCTION}\n{shown}Line: {' '.join(words)}\nWords: {' | '.join(words)}\nTemplate:"


def attach(context: DataFrame, lines: DataFrame, labelled: DataFrame) -> DataFrame:
    """context(log_id, demos) with the prompt; labelled(log_id, raw, template) is bounded by the budget."""
    one = context.select("log_id", F.posexplode_outer("demos").alias("pos", "demo"))
    with_text = one.join(F.broadcast(labelled.select(F.col("log_id").alias("demo"), F.col("raw").alias("d_raw"), "template")), "demo", "left")
    shown = with_text.groupBy("log_id").agg(F.transform(F.array_sort(F.collect_list(F.when(F.col("template").isNotNull(), F.struct("pos", F.struct(F.col("d_raw").alias("raw"), "template").alias("d"))))), lambda x: x["d"]).alias("shown"))
    return lines.join(shown, "log_id").withColumn("prompt", build(F.col("raw"), F.col("shown"))).drop("shown")
