"""Worked examples, exact optima and properties of the methods, on literals."""

import itertools
import math
import random

import numpy as np
import pytest

from tplforge.functions.distance import sed_words
from tplforge.functions.words import Similarity
from tplforge.operators import budget
from tplforge.operators.context import Demo, MatchIndex, adaptive
from tplforge.operators.models import ContextTagger
from tplforge.operators.select import dpp_local, greedy_local, objective

EXACT, CLASSED = Similarity("exact"), Similarity("classed")
S, A, B = "com.cse.ust.hk:8080 POST".split(), "proxy.cse.cuhk.edu.hk:5070 POST".split(), "com.cse.ust.hk:8080 GET".split()


def test_worked_distances():
    assert [sed_words(S, x, EXACT) for x in (A, B, S)] == [1, 1, 0]
    assert [sed_words(S, x, CLASSED) for x in (A, B, S)] == [0, 1, 0]
    assert [sed_words(S, x, CLASSED, "as_printed") for x in (A, B, S)] == [2, 1, 2]
    assert [sed_words(["POST"], x, EXACT, "as_printed") for x in (["POST"], ["GET"])] == [1, 0]


def _plain(a, b, sim):
    if not a or not b:
        return len(a) + len(b)
    return min(_plain(a[1:], b[1:], sim) + (not sim.same(a[0], b[0])), _plain(a[1:], b, sim) + 1, _plain(a, b[1:], sim) + 1)


def test_distance_is_the_recursion_and_keeps_its_bounds():
    rng = random.Random(7)
    for _ in range(300):
        a, b = ([rng.choice("pqrs") for _ in range(rng.randint(0, 6))] for _ in range(2))
        d = sed_words(a, b, EXACT)
        assert d == _plain(a, b, EXACT) == sed_words(b, a, EXACT)
        assert abs(len(a) - len(b)) <= d <= max(len(a), len(b))


U6 = {1: {1, 2, 3}, 2: {3, 4}, 3: {5}, 4: {4}, 5: {5, 6}, 6: {6}}
C6 = dict(zip(range(1, 7), (0.1, 0.2, 0.9, 0.3, 0.2, 0.6), strict=True))


@pytest.mark.parametrize(
    ("form", "lam", "picks", "gains"),
    [
        ("separable", 0, [1, 5, 2], [0.5, 1 / 3, 1 / 6]),
        ("separable", 0.5, [3, 6, 1], [0.53333, 0.38333, 0.3]),
        ("separable", 1, [3, 6, 4], [0.9, 0.6, 0.3]),
        ("as_printed", 0, [1, 5, 2], [0.5, 7 / 6, 4 / 3]),
        ("as_printed", 0.5, [3, 1, 6], [0.53333, 0.63333, 0.88333]),
        ("as_printed", 1, [3, 6, 4], [0.9, 0.6, 0.3]),
    ],
)
def test_worked_selection(form, lam, picks, gains):
    for lazy in (True, False):
        got = greedy_local(U6, C6, 3, lam, form, lazy=lazy)
        assert [g[1] for g in got] == picks
        assert [g[2] for g in got] == pytest.approx(gains, abs=1e-4)


def test_greedy_is_within_its_bound():
    rng = random.Random(3)
    for _ in range(40):
        covers = {i: {i} | {rng.randrange(8) for _ in range(rng.randint(0, 4))} for i in range(8)}
        c = {i: rng.random() for i in range(8)}
        got = objective([g[1] for g in greedy_local(covers, c, 3, 0.4)], covers, c, 0.4, 8)
        best = max(objective(x, covers, c, 0.4, 8) for x in itertools.combinations(range(8), 3))
        assert got >= (1 - 1 / math.e) * best - 1e-9


def test_printed_objective_has_growing_gains():
    covers, c = {1: {1, 2}, 2: {3}, 3: set()}, {1: 0.1, 2: 0.1, 3: 0.1}
    gain = lambda form, base: objective([*base, 3], covers, c, 0.5, 4, form) - objective(base, covers, c, 0.5, 4, form)
    assert [gain("separable", b) for b in ([], [1], [1, 2])] == pytest.approx([0.05] * 3)
    assert [gain("as_printed", b) for b in ([], [1], [1, 2])] == pytest.approx([0.05, 0.3, 0.425])


def test_worked_budgets():
    assert budget.trace([400, 500, 560, 590, 600, 600, 600, 600, 600, 600], 200, (50, 25)) == [50, 25, 20, 17, 16, 15, 15, 15, 15, 12]
    assert budget.trace([40, 55, 60, 62, 63, 63, 63, 63], 50, (10, 10)) == [10, 10, 7, 6, 5, 4, 4, 4]


class FirstLetter(Similarity):
    def score(self, a, b):
        return 1.0 if a[0] == b[0] else -1.0

    def shape(self, w):
        return w[0]


def test_worked_context():
    demos = [Demo(1, ("a2", "b"), ("a2", "b")), Demo(2, ("a3", "c"), ("a3", "c")), Demo(3, ("a4",), ("a4",))]
    index = MatchIndex(demos, FirstLetter("classed"))
    assert adaptive(["a1", "b", "c"], index) == ([1, 2], [])
    assert adaptive(["a1", "b", "c"], index, "as_printed") == ([1, 2, 3], [])
    assert adaptive(["a1", "z"], index)[1] == ["z"]
    assert adaptive([], index) == ([], [])


def test_context_is_within_its_bound():
    rng = random.Random(5)
    for _ in range(60):
        demos = [Demo(i, tuple(rng.sample("abcdefgh", rng.randint(1, 4))), ()) for i in range(6)]
        line = rng.sample("abcdefgh", 5)
        got, missing = adaptive(line, MatchIndex(demos, EXACT))
        need = set(line) - set(missing)
        best = next(k for k in range(7) if any(need <= {w for d in x for w in d.words} for x in itertools.combinations(demos, k)))
        assert len(got) <= (1 + math.log(max(1, len(line)))) * best + 1e-9


def test_tagger_on_worked_lines():
    demo = Demo(1, tuple(A), ("[ADDR]", "POST"))
    t = ContextTagger()
    known, unknown = t.answer(1, S, [demo], CLASSED), t.answer(2, ["com.cse.ust.hk:8080", "DELETE"], [demo], CLASSED)
    assert known.labels == ["[ADDR]", "POST"]
    assert sum(unknown.probs) < sum(known.probs)


def test_diverse_start_takes_different_vectors():
    v = np.array([[1, 0, 0], [1, 0.01, 0], [0, 1, 0], [0, 0, 1]], float)
    assert set(dpp_local([10, 11, 12, 13], v, 3)) in ({10, 12, 13}, {11, 12, 13})
    assert dpp_local([], v[:0], 3) == []
    assert sorted(dpp_local([1, 2], v[:2], 9)) == [1, 2]
