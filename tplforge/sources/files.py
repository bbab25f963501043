"""Sources and sinks of lines: text, JSON lines, CSV, Parquet, a directory stream, a line generator."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from tplforge.schema import EVENTS, LINE


def read_text(spark: SparkSession, path: str, domain: str) -> DataFrame:
    """One line of a file is one log line. Ids are unique; they stay the same as long as files and split sizes do."""
    raw = spark.read.text(path).select(F.col("value").alias("raw"), F.col("_metadata.file_path").alias("f"), F.col("_metadata.file_block_start").alias("b"))
    return raw.select(F.xxhash64("f", "b", F.monotonically_increasing_id()).alias("log_id"), F.lit(domain).alias("domain"), "raw", F.lit(None).cast("string").alias("truth"))


def read_lines(spark: SparkSession, path: str, kind: str = "parquet") -> DataFrame:
    return spark.read.schema(LINE).format(kind).option("header", True).load(path)


def write_lines(df: DataFrame, path: str, kind: str = "parquet") -> None:
    """One folder per domain."""
    df.write.format(kind).option("header", True).partitionBy("domain").save(path)


def stream_events(spark: SparkSession, path: str) -> DataFrame:
    """events as a directory stream; event time needs a timestamp with zone."""
    return spark.readStream.schema(EVENTS).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


class _Part(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.rows, self.parts, self.verbs = int(options.get("rows", 1000)), int(options.get("partitions", 2)), options.get("verbs", "GET,POST,HEAD").split(",")

    def partitions(self):
        edge = [self.rows * i // self.parts for i in range(self.parts + 1)]
        return [_Part(a, b) for a, b in zip(edge, edge[1:], strict=False)]

    def read(self, partition: _Part) -> Iterator[tuple]:
        for i in range(partition.first, partition.last):
            verb = self.verbs[i % len(self.verbs)]
            yield i, "generated", f"{verb} 10.0.{i % 256}.{i // 256 % 256}:80 took {i * 7 % 1000} ms", f"{verb} [ADDR] took [AMOUNT] ms"


class GeneratedLines(DataSource):
    """spark.read.format("generated_lines").option("rows", n)"""

    @classmethod
    def name(cls) -> str:
        return "generated_lines"

    def schema(self):
        return LINE

    def reader(self, schema):
        return _Reader(self.options)
