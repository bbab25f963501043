"""The rounds beyond the driver's limit pick what the local ones pick."""

from dataclasses import replace

import pytest

from tplforge.functions.words import tokenize
from tplforge.operators import rounds
from tplforge.operators.models import Context, ContextTagger
from tplforge.plans import choose


def _lines(spark):
    shapes = ["job {} took {} ms at node n{}", "user u{} read file {} twice", "disk {} failed", "link {} to {} is slow now", "job {} ended well", "read {} of {}"]
    verbs = ["alpha", "beta", "gamma", "delta", "eps"]
    rows = []
    for i in range(150):
        raw = f"{verbs[i % 5]} " + shapes[i * i % 6].format(i, i + 1, i % 7)
        truth = " ".join("[N]" if any(ch.isdigit() for ch in w) else w for w in raw.split())
        rows.append((i, "d", raw, truth))
    return tokenize(spark.createDataFrame(rows, "log_id long, domain string, raw string, truth string"))


BASE = rounds.Config(budget=6, start=(2, 2), fixed=3, model=ContextTagger(inject=100))
CASES = {
    **{n: rounds.variant(BASE, n) for n in ("FULL", "-SED", "-RS", "-PC")},
    "options": replace(BASE, residual="none", charge_init=False, delta=0.3, adaptive_budget=False),
    "vector": replace(BASE, context=Context(similarity="vector", tau=0.3), tau=0.3),
}


@pytest.mark.parametrize("name", CASES)
def test_same_as_local(spark, monkeypatch, name):
    d = _lines(spark)
    want = rounds.run(d, CASES[name], final=False)
    monkeypatch.setattr(choose, "LOCAL_PATTERNS", 5)
    got = rounds.run(d, CASES[name], final=False)
    assert got.decisions["greedy"].choice == "distributed" and want.decisions["greedy"].choice == "driver"
    assert [x.id for x in got.labelled] == [x.id for x in want.labelled]
    assert [{**t, "coverage": None} for t in got.trace] == [{**t, "coverage": None} for t in want.trace]
    assert [t["coverage"] for t in got.trace] == pytest.approx([t["coverage"] for t in want.trace])
