"""The ablation and the sweep of lambda take the surveyed budgets, beside a fiftieth of them."""

from collections import Counter

import pytest

from tplforge.plans import methods
from tplforge.sources.corpus import SWEEP_SCALE, scaled

RUNS = {"w5_ablation": 6, "w7_sweep_lambda": 5}


@pytest.mark.parametrize("name", RUNS)
def test_whole_budgets_are_run(spark, monkeypatch, name):
    ran = []

    def method(spark, sf_dir, n, which, cfg=None):
        ran.append((n, cfg.budget, cfg.start))
        return spark.createDataFrame([(n, which, "a", "a", False, 1)], "domain string, method string, truth string, pred string, labelled boolean, n long")

    monkeypatch.setattr(methods, "method", method)
    got = methods.queries()[name](spark, "").collect()
    corpora = {n for n, *_ in ran}
    assert Counter(ran) == {(n, *scaled(n, scale)): RUNS[name] for n in corpora for scale in (1, SWEEP_SCALE)}
    assert Counter((r["domain"], r["budget"]) for r in got) == {(n, scaled(n, scale)[0]): 2 * RUNS[name] for n in corpora for scale in (1, SWEEP_SCALE)}
