"""The cover by joins ends when nothing is gained, however many demos a line needs."""

from tplforge.operators.context import adaptive_sql


def test_long_line_is_covered(spark):
    words = [f"w{i}" for i in range(7)]
    lines = spark.createDataFrame([(1, words), (2, ["w3", "none"])], "log_id long, words array<string>")
    demos = spark.createDataFrame([(10 + i, [w]) for i, w in enumerate(words)], "log_id long, words array<string>")
    got = sorted(tuple(r) for r in adaptive_sql(lines, demos, 4).collect())
    assert got == sorted([(i + 1, 1, 10 + i) for i in range(7)] + [(1, 2, 13)])
