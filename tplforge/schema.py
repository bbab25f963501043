"""Declared schemas: nothing in this package infers one."""

from pyspark.sql import types as T

LINE = T.StructType([T.StructField("log_id", T.LongType()), T.StructField("domain", T.StringType()), T.StructField("raw", T.StringType()), T.StructField("truth", T.StringType())])
PROPS = "struct<k: int>"
ANSWER = "log_id long, labels array<string>, echo array<string>, probs array<double>"
DEMOS = "log_id long, demos array<long>, uncovered array<string>"
PICK = "rank int, log_id long, gain double, covered long, difficulty double"
TRACE = "r int, budget int, spent int, words_seen int, words_new int, open int, coverage double"
EVENTS = T.StructType(
    [
        T.StructField("event_id", T.LongType()),
        T.StructField("ts", T.TimestampNTZType()),
        T.StructField("user_id", T.LongType()),
        T.StructField("event_type", T.StringType()),
        T.StructField("value", T.DoubleType()),
        T.StructField("props", T.StringType()),
    ]
)
