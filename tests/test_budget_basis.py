"""Rounds take the word counts that the configuration names."""

from dataclasses import replace

import pytest
from test_distributed_rounds import BASE, _lines

from tplforge.operators import budget, rounds


@pytest.mark.parametrize("basis", ["cumulative", "per_round"])
def test_round_trace_follows_basis(spark, basis):
    cfg = replace(BASE, budget=18, start=(4, 3), words_basis=basis)
    got = rounds.run(_lines(spark), cfg, final=False).trace
    words = [t["words_seen"] for t in got]
    assert [t["budget"] for t in got] == budget.trace(words, 18, cfg.start, basis)
    assert budget.trace(words, 18, cfg.start, basis) != budget.trace(words, 18, cfg.start, "per_round" if basis == "cumulative" else "cumulative")
