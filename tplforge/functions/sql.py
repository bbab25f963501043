"""The methods' functions under SQL names."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from tplforge.functions.words import SHAPES


def register(spark: SparkSession) -> None:
    """tpl_words, tpl_classed, tpl_residual, tpl_sed, tpl_difficulty, tpl_tokens as SQL functions; tpl_vars as a table function."""
    shape = "CASE " + " ".join(f"WHEN w RLIKE r'{p}' THEN '{n}'" for n, p in SHAPES) + " ELSE w END"
    made = {
        "tpl_words(raw STRING) RETURNS ARRAY<STRING>": r"filter(split(coalesce(raw, ''), r'\s+'), w -> w <> '')",
        "tpl_classed(ws ARRAY<STRING>) RETURNS ARRAY<STRING>": f"transform(ws, w -> {shape})",
        "tpl_residual(ws ARRAY<STRING>, known ARRAY<STRING>) RETURNS ARRAY<STRING>": "filter(ws, w -> NOT array_contains(known, w))",
        "tpl_sed(a ARRAY<STRING>, b ARRAY<STRING>) RETURNS INT": "levenshtein({}, {})".format(*(f"array_join(transform({x}, w -> decode(unhex(lpad(hex(array_position(array_distinct(concat(a, b)), w) + 256), 4, '0')), 'UTF-16BE')), '')" for x in "ab")),
        "tpl_difficulty(p DOUBLE, flag INT, a DOUBLE) RETURNS DOUBLE": "a * (1 - p) + (1 - a) * flag",
        "tpl_tokens(t STRING) RETURNS BIGINT": "CAST(ceil(length(t) / 4) AS BIGINT)",
    }
    for head, body in made.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")

    @udtf(returnType="pos int, label string, word string")
    class Vars:
        """The variable words of a line with their labels."""

        def eval(self, words: list, labels: list):
            for i, (w, x) in enumerate(zip(words or [], labels or [], strict=False)):
                if x.startswith("["):
                    yield i, x, w

    spark.udtf.register("tpl_vars", Vars)
