"""Lines answered in batches, where words are alike by vectors, have the answers of single lines."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F
from test_distributed_rounds import _lines
from test_forms import DEMOS, ODD

from tplforge.functions.words import vector, vectors
from tplforge.operators import models, rounds
from tplforge.operators.batches import Batches, in_batches
from tplforge.operators.context import Demo
from tplforge.operators.models import Context, ContextTagger, Predictor
from tplforge.operators.prompt import text
from tplforge.plans import methods

#: equal words, words of one class, a word twice, words whose scores are equal, no word
MORE = [Demo(4, ("7", "7", "ab", "abc"), ("[CODE]", "7", "ab", "[NAME]")), Demo(5, (), ()), Demo(6, ("2020-02-03", "job", "n2"), ("[DATE]", "job", "[NAME]"))]


def _same(lines, model, ctx, demos):
    assert in_batches(model, ctx, demos)
    p, b = Predictor(model, ctx, demos, 3), Batches(model, ctx, demos, 3)
    got = []
    for part in (lines[: len(lines) // 2], lines[len(lines) // 2 :]):  # what is remembered holds for the next batch
        got += b.answer(pa.array([["no"], *part], pa.list_(pa.string())).slice(1)).to_pylist()
    for ws, r in zip(lines, got, strict=True):
        a, chosen, _, _ = p.predict(0, ws)
        assert (r["pred"], r["demos"]) == (" ".join(a.labels), chosen), ws
        assert r["rest"] + models._line_length(ws) == len(text(ws, [(p.by[d].words, p.by[d].labels) for d in chosen]))


@pytest.mark.parametrize("tau", [0, 0.25, 0.5, 0.75, 1])
def test_odd_lines(tau):
    rng = np.random.default_rng(5)
    some = ["job", "7", "8", "12.50", "ab", "abc", "abd", "n1", "n2", "2020-02-03", "2021-01-01", "/a/b", "é9", "disk", "failed", "took", "5"]
    lines = [x.split() for _, x in ODD] + [[str(w) for w in rng.choice(some, rng.integers(0, 9))] for _ in range(1500)]
    for demos in (DEMOS + MORE, DEMOS, MORE[1:2], []):
        _same(lines, ContextTagger("vector", tau, misread=500), Context(similarity="vector", tau=tau), demos)
    _same(lines[:300], ContextTagger("vector", tau), Context(similarity="vector", tau=0.3, strict_break=True), DEMOS + MORE)


@pytest.mark.parametrize("name", ["ord_desk", "evt_simple"])
@pytest.mark.parametrize("tau", [0, 0.75, 1])
def test_runs(spark, name, tau):
    d = methods.lines(spark, "/root/testdata/sf0.001", name).filter("log_id % 3 = 0")
    cfg = rounds.replace(methods.config(name), tau=tau, context=Context(similarity="vector", tau=tau), model=ContextTagger("vector", tau, misread=500))
    base, columns = rounds.Base(d), ["log_id", "truth", "labels", "echo", "demos", "tokens", "labelled", "pred"]
    many, each = ({r["log_id"]: r for r in rounds.run(d, cfg, base=base, compact=c).predictions.select(columns).collect()} for c in (True, False))
    assert many == each and len(many) == base.distinct.count()


def test_the_model_is_not_asked_line_by_line(spark, monkeypatch):
    """Two thousand lines of one form with words of their own: one by one, the model would answer all of them."""
    seen = spark.sparkContext.accumulator(0)

    class Counting(Predictor):
        def predict(self, log_id, words):
            seen.add(1)
            return super().predict(log_id, words)

    monkeypatch.setattr(models, "Predictor", Counting)
    d = _lines(spark).limit(1).select("domain", "truth", "labels").crossJoin(spark.range(2000)).select(
        F.col("id").alias("log_id"), "domain", "truth", "labels", F.split(F.concat(F.lit("job "), F.col("id").cast("string"), F.lit(" ended")), " ").alias("words"))
    cfg = rounds.Config(budget=2, start=(1,), context=Context(similarity="vector"), model=ContextTagger("vector"))
    got = rounds.run(d, cfg, compact=True).predictions
    assert got.groupBy("pred").count().agg(F.sum("count")).first()[0] == 2000
    assert seen.value < 100


def test_vectors_of_odd_words():
    rng = np.random.default_rng(1)
    many = ["", "a", "é", "1", "<>", "٣", *("".join(rng.choice(list("0123456789./:-#aB<éxF"), rng.integers(0, 12))) for _ in range(500))]
    assert np.array_equal(vectors(many), np.array([vector(w) for w in many])) and vectors([]).shape == (0, 64)
