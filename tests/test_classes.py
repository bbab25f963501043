"""Lines that no prediction by form tells apart share a row, and give the results of single lines."""

from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F
from test_distributed_rounds import _lines

from tplforge.operators import baselines, rounds
from tplforge.operators.context import Demo, TopK
from tplforge.plans import methods


@pytest.mark.parametrize("which", ["FULL", "-AD"])
@pytest.mark.parametrize("most", [10_000, 0])
def test_rows_of_many_lines(spark, monkeypatch, which, most):
    monkeypatch.setattr(rounds, "LOCAL_CLASSES", most)
    d = methods.lines(spark, "/root/testdata/sf0.001", "ord_desk")
    base, cfg = rounds.Base(d), rounds.variant(methods.config("ord_desk"), which)
    few, each = (rounds.run(d, cfg, base=base, compact=c).predictions for c in (True, False))
    columns = ["truth", "pred", "labelled", "demos", "tokens"]
    counted = Counter()
    for r in few.select(*columns, "n").collect():
        counted[r["truth"], r["pred"], r["labelled"], tuple(r["demos"]), r["tokens"]] += r["n"]
    assert counted == Counter((r["truth"], r["pred"], r["labelled"], tuple(r["demos"]), r["tokens"]) for r in each.select(*columns).collect())
    assert few.count() < base.distinct.count() == sum(counted.values())


def test_words_kept_verbatim_are_not_shared(spark):
    """A variable word that the truth keeps makes templates of its own, so such lines stay single."""
    d = _lines(spark)
    assert rounds.Base(d).compact()
    kept = d.withColumn("labels", F.col("words"))
    assert not rounds.Base(kept).compact()


def test_masked_lines_are_counted(spark):
    d = methods.lines(spark, "/root/testdata/sf0.001", "ledger")
    whole, few = baselines.as_typed(baselines.parse_tree(d)), baselines.as_typed(baselines.parse_tree(baselines.mask_count(d)))
    cells = lambda p: {tuple(r) for r in methods.M.cells_of(p, ("domain",)).collect()}
    assert cells(whole) == cells(few) and few.count() < whole.count()


def test_examples_of_a_column():
    lines = [["a", "b", "7"], [], ["a"], ["7", "8", "9", "a"]]
    top = TopK([Demo(5, ("a", "1"), ("a", "[X]")), Demo(3, ("b", "c"), ("b", "c")), Demo(4, ("9",), ("[X]",))], 2)
    got = top.pick_arrow(pa.array([["no"], *lines], pa.list_(pa.string())).slice(1))
    assert got.to_pylist() == top.pick_all(lines) and np.array_equal(top.pick(lines[0]), got.to_pylist()[0])
