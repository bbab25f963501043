"""Baselines beyond the driver's limit pick what the local ones pick."""

from test_distributed_rounds import _lines

from tplforge.operators import baselines


def test_same_as_local(spark, monkeypatch):
    d = _lines(spark)
    run = lambda: [x for x in (baselines.single_round(d, 4), baselines.multi_fixed(d, 6, 3))]
    want = run()
    monkeypatch.setattr(baselines, "LOCAL_PATTERNS", 5)
    for got, x in zip(run(), want, strict=True):
        assert [r.id for r in got.labelled] == [r.id for r in x.labelled] and got.trace == x.trace
    assert [r.id for r in baselines.diverse_start(d, 4)[1]] == [r.id for r in want[0].labelled]
    assert baselines.token_tagger(d, 4).predictions.count() == want[0].predictions.count()
