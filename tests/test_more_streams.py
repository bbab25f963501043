"""Stateful streams, enrichment, delayed truth, batches for labelling, late rows."""

import collections

import pytest
from pyspark.sql import functions as F

from tplforge.sources.files import stream_events
from tplforge.streaming import lines as L

SF = "/root/testdata/sf0.001"


@pytest.fixture
def rocks(spark):
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    yield
    spark.conf.set(key, before)


def _stream(spark, path, df):
    df.repartition(1).write.parquet(str(path))
    return L.render(stream_events(spark, str(path)))


def test_new_words_per_key(spark, rocks, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet").limit(60)
    got = L.drain(L.new_words(_stream(spark, tmp_path / "e", events)), "t_new", str(tmp_path / "c"), "append").collect()
    want = collections.defaultdict(set)
    for r in L.render(events).collect():
        want[r["event_type"]].update(r["words"])
    seen = collections.Counter()
    for r in got:
        seen[r["event_type"]] += r["fresh"]
    assert dict(seen) == {k: len(v) for k, v in want.items()}


def test_label_requests_keep_the_budget(spark, rocks, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet").orderBy("ts")
    src = tmp_path / "e"
    for i in range(3):
        events.filter(F.col("event_id") % 3 == i).repartition(1).write.mode("append").parquet(str(src))
    stream = L.render(spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(str(src)).withColumn("ts", F.col("ts").cast("timestamp")))
    got = L.drain(L.label_requests(stream, 2), "t_requests", str(tmp_path / "c"), "append").collect()
    by = collections.Counter(r["event_type"] for r in got)
    assert got and all(n % 2 == 0 or n < 2 for n in by.values()) and len({r["log_id"] for r in got}) == len(got)


def test_enrichment_and_delayed_truth(spark, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet").limit(50)
    stream = _stream(spark, tmp_path / "e", events)
    labelled = spark.createDataFrame([("click event from user <int> amount <dec>", "click event from user [USER] amount [AMOUNT]")], "pattern string, template string")
    got = L.drain(L.with_labels(stream, labelled), "t_labels", str(tmp_path / "c1")).collect()
    assert len(got) == 50 and all((r["template"] is not None) == (r["event_type"] == "click") for r in got)
    truths = stream.select("log_id", (F.col("ts") + F.expr("INTERVAL 5 minutes")).alias("ts"), F.col("raw").alias("truth"))
    got = L.drain(L.confirmed(stream.select("log_id", "ts", "raw"), truths), "t_confirmed", str(tmp_path / "c2"))
    assert got.count() == 50 and got.filter("raw <> truth").count() == 0


def test_batches_and_late_rows(spark, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet").limit(80)
    taken = []
    q = L.label_batches(_stream(spark, tmp_path / "e", events), 7, lambda df, b: taken.append(min(b, df.count())), str(tmp_path / "c"))
    q.awaitTermination(120)
    assert sum(taken) == 7
    src = tmp_path / "late"
    late = events.withColumn("ts", F.col("ts") - F.expr("INTERVAL 900 days"))
    events.repartition(1).write.parquet(str(src))
    stream = L.render(stream_events(spark, str(src)))
    counted = L.tumbling(stream)

    def run():
        q = counted.writeStream.format("noop").outputMode("update").option("checkpointLocation", str(tmp_path / "c3")).trigger(availableNow=True).start()
        q.awaitTermination(120)
        return L.late_rows(q)

    assert run() == 0
    late.repartition(1).write.mode("append").parquet(str(src))
    assert run() > 0
