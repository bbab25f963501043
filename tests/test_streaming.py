import glob

from pyspark.sql import functions as F

from tplforge.functions import sql
from tplforge.sources.files import GeneratedLines, stream_events
from tplforge.streaming import lines as L

SF = "/root/testdata/sf0.001"


def test_stream_equals_batch(spark, tmp_path):
    src = tmp_path / "events"
    events = spark.read.parquet(f"{SF}/events.parquet")
    events.repartition(1).write.parquet(str(src))
    stream = L.render(stream_events(spark, str(src)))
    batch = L.render(events.withColumn("ts", F.col("ts").cast("timestamp")))
    for name, f in (("tumbling", L.tumbling), ("sliding", L.sliding), ("sessions", L.sessions), ("patterns", L.patterns)):
        mode = "append" if name == "sessions" else "complete"
        got = L.drain(f(stream), f"t_{name}", str(tmp_path / name), mode)
        want = f(batch)
        if mode == "complete":
            assert sorted(map(str, got.collect())) == sorted(map(str, want.collect()))
        else:
            assert {str(r) for r in got.collect()} <= {str(r) for r in want.collect()}
    assert glob.glob(str(src / "*.parquet"))


def test_repeats_go(spark, tmp_path):
    src = tmp_path / "events"
    events = spark.read.parquet(f"{SF}/events.parquet").limit(100)
    events.union(events.limit(20)).repartition(1).write.parquet(str(src))
    got = L.drain(L.once(L.render(stream_events(spark, str(src)))), "t_once", str(tmp_path / "c"))
    assert got.count() == 100


def test_sql_functions_and_generated_lines(spark):
    sql.register(spark)
    r = spark.sql("SELECT tpl_words(' a  12 ') w, tpl_classed(tpl_words('a 12')) c, tpl_residual(array('a','b'), array('a')) r, tpl_difficulty(0.6D, 0, 0.5D) d, tpl_tokens('abcde') t").first()
    assert (r.w, r.c, r.r, round(r.d, 6), r.t) == (["a", "12"], ["a", "<int>"], ["b"], 0.2, 2)
    got = spark.sql("SELECT * FROM tpl_vars(array('a', '12'), array('a', '[CODE]'))").collect()
    assert [tuple(x) for x in got] == [(1, "[CODE]", "12")]
    spark.dataSource.register(GeneratedLines)
    assert spark.read.format("generated_lines").option("rows", 10).load().count() == 10
