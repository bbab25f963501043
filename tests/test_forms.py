"""Answers by form and in batches are those of one line at a time; runs of a workload share what they begin with."""

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_distributed_rounds import _lines

from tplforge.functions.words import Similarity, vector, vectors
from tplforge.operators import models, rounds
from tplforge.operators.context import Demo
from tplforge.operators.models import Context, ContextTagger, Predictor, ShapeOnly, answered
from tplforge.operators.represent import edges_local
from tplforge.plans import methods

ODD = [
    (900, "job 1 took 1 ms at node n1"),
    (901, "job 1 took 2 ms at node n1"),
    (902, "2020-01-02 read 7 of 7 7 8"),
    (903, "GET http://x/1 then /a/b é9 ünï"),
    (904, ""),
    (905, "only constant words"),
]
DEMOS = [
    Demo(1, ("job", "1", "took", "5", "ms"), ("job", "[CODE]", "took", "5", "ms")),
    Demo(2, ("read", "7", "of", "9"), ("read", "7", "of", "[CODE]")),
    Demo(3, ("disk", "3", "failed"), ("disk", "[CODE]", "failed")),
]


def test_vectors_digit_by_digit():
    many = ["a", "order", "2020-01-02", "12", "3.50", "é9", "/a", "0xFF", "Brand#12", "ünï"]
    assert np.array_equal(vectors(many), np.array([vector(w) for w in many]))


@pytest.mark.parametrize("mode", ["adaptive", "none", "topk"])
@pytest.mark.parametrize("model", [ContextTagger(misread=500), ShapeOnly(misread=500), ContextTagger("vector", 0.25), ContextTagger(inject=300)], ids=["plain", "shape", "vector", "inject"])
def test_as_one_by_one(spark, mode, model):
    ctx = Context(mode=mode, k=2, similarity="vector" if model.similarity == "vector" else "classed", tau=0.25)
    d = _lines(spark).select("log_id", "words")
    d = d.union(spark.createDataFrame([(i, x.split()) for i, x in ODD], "log_id long, words array<string>"))
    p, asked = Predictor(model, ctx, DEMOS, 3), answered(d.withColumn("kept", F.col("log_id") + 1), model, ctx, DEMOS, 3).collect()
    assert len(asked) == d.count()
    for r in asked:
        a, chosen, missing, n = p.predict(r["log_id"], list(r["words"]))
        assert (r["labels"], r["echo"], r["demos"], r["uncovered"], r["tokens"], r["kept"]) == (a.labels, a.echo, chosen, missing, n, r["log_id"] + 1)
        assert r["probs"] == pytest.approx(a.probs, abs=1e-12)


def test_lines_of_one_form_are_asked_once(spark):
    """Of 3,000 lines in two forms the model sees two: one by one it would see all."""
    assert models.by_form(ContextTagger(misread=5), Context()) and not models.by_form(ContextTagger(inject=5), Context())
    d = spark.range(3000).select(F.col("id").alias("log_id"), F.split(F.concat(F.lit("job "), (F.col("id") + 10).cast("string"), F.when(F.col("id") % 2 == 0, " ended").otherwise(" began")), " ").alias("words"))
    seen = spark.sparkContext.accumulator(0)

    class Counting(Predictor):
        def predict(self, log_id, words):
            seen.add(1)
            return super().predict(log_id, words)

    kept, models.Predictor = models.Predictor, Counting
    try:
        got = answered(d, ContextTagger(), Context(), DEMOS)
        assert got.filter(F.array_join("labels", " ").isin("job [CODE] ended", "job [CODE] began")).count() == 3000
    finally:
        models.Predictor = kept


def test_distances_of_residuals_at_once():
    sim = Similarity("classed")
    res = {1: ["a", "1"], 2: ["a", "2"], 3: ["b", "c", "d", "e"], 4: [], 5: ["b", "c"], 6: ["a", "7"]}
    length = {1: 4, 2: 4, 3: 4, 4: 1, 5: 9, 6: 3}
    got = edges_local(res, length, 0.5, sim)
    assert got == {1: {1, 2, 3, 5, 6} - {3}, 2: {1, 2, 5, 6}, 3: {3, 5}, 4: {4}, 5: {1, 2, 3, 5}, 6: {1, 2, 6}}


def test_runs_share_their_lines(spark, monkeypatch):
    made = []

    class Base(rounds.Base):
        def __init__(self, lines):
            made.append(1)
            super().__init__(lines)

    monkeypatch.setattr(rounds, "Base", Base)
    two = methods.workload(lambda: [methods.method(spark, "/root/testdata/sf0.001", "ledger", w) for w in ("FULL", "S1")])
    two()
    assert len(made) == 1
    methods.method(spark, "/root/testdata/sf0.001", "ledger", "FULL")
    assert len(made) == 2
