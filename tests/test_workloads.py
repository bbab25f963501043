"""The workloads run over the surveyed corpora, methods, values and a tenth of the budgets, and tell methods apart."""

import pytest

from tplforge.plans import methods
from tplforge.operators import rounds
from tplforge.sources.corpus import SWEEP_SCALE, TRUTH, scaled

TWO = {"ord_desk", "evt_simple"}
SURVEYED = {
    "w2_effectiveness": (set(TRUTH), 5),
    "w3_w4_cost": (set(TRUTH), 3),
    "w5_ablation": ({"part_shelf", "evt_rich", "ord_desk", "evt_simple"}, 6),
    "w6_sweep_budget": (TWO, 5),
    "w7_sweep_lambda": (TWO, 5),
    "w8_sweep_delta": ({"ord_desk"}, 5),
    "w9_sweep_tau": (TWO, 5),
    "w10_errors_lambda": ({"evt_rich"}, 3),
    "w11_errors_a": ({"evt_rich"}, 3),
}


class Stop(Exception):
    pass


@pytest.mark.parametrize("name", SURVEYED)
def test_surveyed(spark, monkeypatch, name):
    ran = []

    def stop(parts):
        raise Stop

    class Frame:
        def withColumn(self, *_):
            return self

        select = withColumn

    monkeypatch.setattr(methods, "method", lambda spark, sf_dir, n, which, cfg=None: ran.append((n, which, cfg)) or Frame())
    monkeypatch.setattr(methods, "scored", lambda p: p)
    monkeypatch.setattr(methods.M, "errors", lambda p: p)
    monkeypatch.setattr(methods, "_union", stop)
    with pytest.raises(Stop):
        methods.queries()[name](spark, "")
    corpora, each = SURVEYED[name]
    assert {n for n, _, _ in ran} == corpora and len(ran) == each * len(corpora)
    for n, _, cfg in ran:
        if cfg is not None and name != "w6_sweep_budget":
            assert (cfg.budget, cfg.start) == scaled(n, SWEEP_SCALE)
    if name == "w6_sweep_budget":
        assert {c.budget for _, _, c in ran} == {1, 2, 3, 4, 5}


def test_rounds_happen(spark):
    for name in ("part_shelf", "ord_desk"):
        got = rounds.run(methods.lines(spark, "/root/testdata/sf0.001", name), methods.config(name), final=False)
        assert len(got.trace) >= 3 and sum(t["spent"] for t in got.trace) <= methods.config(name).budget
        budgets = [t["budget"] for t in got.trace]
        assert budgets[2:] == sorted(budgets[2:], reverse=True) or methods.config(name).budget < 10


def test_ablations_differ(spark):
    """With few labels, leaving out the difficulty costs accuracy; both populations are reported."""
    got = {(r["population"], r["method"]): r for r in methods.w5_ablation(spark, "/root/testdata/sf0.001", ("evt_rich",)).collect()}
    assert {p for p, _ in got} == {"all", "unlabelled"} and len(got) == 12
    deltas = {m: got["unlabelled", m]["d_mla"] for _, m in got if m != "FULL"}
    assert deltas["-PC"] < -1 and len({round(d, 3) for d in deltas.values()}) >= 3
    assert all(got["all", m]["mla"] >= got["unlabelled", m]["mla"] - 1e-9 for _, m in got)
