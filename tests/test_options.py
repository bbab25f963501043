"""Worked answers, and the options that rounds, contexts and selection can take."""

import math
import random
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_distributed_rounds import _lines

from tplforge.functions.confidence import difficulty, inconsistent, mean_prob
from tplforge.functions.measures import gen_error, word_errors
from tplforge.functions.words import Similarity, tokenize
from tplforge.operators import rounds
from tplforge.operators import select as S
from tplforge.operators.context import Demo, MatchIndex, adaptive
from tplforge.operators.models import CANDIDATES, Answer, ContextTagger, consistent, tagged
from tplforge.operators.represent import edges, knn_edges, knn_index, patterns, score, sizes
from tplforge.plans import choose

# The worked lines
LINE = ["com.cse.ust.hk:8080", "POST"]
CODE_LINE = "rts: kernel terminated for reason 1004".split()


def test_confident_but_wrong_answer(spark):
    """Flagged where the echo differs or a label is no candidate; not where both are as they should be."""
    rows = [
        ("echo", LINE, ["com.cse.ust.hk:8080", "GET"], ["[ADDR]", "[NAME]"]),
        ("label", LINE, LINE, ["[ADDR]", "[STATUS]"]),
        ("count", LINE, LINE, ["[ADDR]"]),
        ("limit", LINE, LINE, ["[ADDR]", "[CODE]"]),
        ("right", LINE, LINE, ["[ADDR]", "POST"]),
    ]
    df = spark.createDataFrame([(*r, [0.95, 0.95]) for r in rows], "name string, words array<string>, echo array<string>, labels array<string>, probs array<double>")
    flag = inconsistent(F.col("words"), F.col("echo"), F.col("labels"), F.array(*map(F.lit, CANDIDATES)))
    got = {r["name"]: r for r in df.select("name", flag.alias("flag"), difficulty(mean_prob(F.col("probs")), flag, 0.5).alias("c")).collect()}
    assert {n: r["flag"] for n, r in got.items()} == {"echo": 1, "label": 1, "count": 1, "limit": 0, "right": 0}
    assert got["label"]["c"] == pytest.approx(0.525) and got["right"]["c"] == pytest.approx(0.025)
    for name, words, echo, labels in rows:
        assert consistent(words, Answer(labels, echo, [0.95] * 2)) == (not got[name]["flag"])


def test_two_kinds_of_errors(spark):
    true = [*CODE_LINE[:-1], "[CODE]"]
    rows = [("short", CODE_LINE[:-3], true[:-3]), ("word", CODE_LINE, CODE_LINE), ("right", CODE_LINE, true)]
    df = spark.createDataFrame([(n, CODE_LINE, e, x, true) for n, e, x in rows], "name string, words array<string>, echo array<string>, labels array<string>, t array<string>")
    got = {r[0]: (r[1], r[2]) for r in df.select("name", gen_error(F.col("words"), F.col("echo")), word_errors(F.col("labels"), F.col("t"))).collect()}
    assert got == {"short": (1, 0), "word": (0, 1), "right": (0, 0)}


def test_keywords_in_brackets():
    assert tagged(["[ADDR]", "POST"], LINE) == ["[ADDR]", "<POST>"]


def test_rare_words_are_misread():
    t, demo = ContextTagger(misread=1000), Demo(1, ("alpha", "7"), ("alpha", "[CODE]"))
    sim = Similarity("classed")
    assert t.answer(1, ["alpha", "9"], [demo], sim).labels == ["alpha", "[CODE]"]
    assert t.answer(1, ["omega", "9"], [demo], sim).labels[0] in CANDIDATES
    assert ContextTagger().answer(1, ["omega", "9"], [demo], sim).labels[0] == "omega"


def test_strict_break_ends_the_scan():
    demos = [Demo(1, ("z",), ()), Demo(2, ("a", "z"), ()), Demo(3, ("b",), ())]
    index = MatchIndex(demos, Similarity("exact"))
    line = ["a", "z", "b"]
    assert adaptive(line, index) == ([2, 3], [])
    # after demo 2 the first demo has no gain: the scan ends there
    assert adaptive(line, index, strict_break=True) == ([2], [])


@pytest.mark.parametrize("name", ["-AD", "-AB", "similar", "misread", "strict"])
def test_more_of_the_same_as_local(spark, monkeypatch, name):
    base = rounds.Config(budget=9, start=(2, 2), fixed=3, model=ContextTagger(misread=500))
    cfg = {
        "similar": replace(base, residual="similar"),
        "misread": replace(base, rounding="ceil", length_basis="residual"),
        "strict": replace(base, context=replace(base.context, strict_break=True)),
    }.get(name) or rounds.variant(base, name)
    d = _lines(spark)
    want = rounds.run(d, cfg, final=False)
    monkeypatch.setattr(choose, "LOCAL_PATTERNS", 5)
    got = rounds.run(d, cfg, final=False)
    assert [x.id for x in got.labelled] == [x.id for x in want.labelled] and len(want.trace) >= 3
    assert [t["budget"] for t in got.trace] == [t["budget"] for t in want.trace]


def test_similar_residual_drops_more():
    sim = Similarity("classed")
    cfg, known, shapes = rounds.Config(residual="similar"), {"POST", "a.b.c:80"}, {"POST", "<addr>"}
    assert rounds._left(LINE, known, cfg, sim, shapes) == []
    assert rounds._left(LINE, known, replace(cfg, residual="exact"), sim, shapes) == [LINE[0]]
    assert rounds._left(LINE, known, replace(cfg, residual="none"), sim, shapes) == LINE


def test_decaying_cover(spark):
    """Repeats count half as much each time: brute force, the local and the distributed form."""
    rng = random.Random(4)
    covers = {i: {i} | {rng.randrange(10) for _ in range(4)} for i in range(10)}
    c = {i: round(rng.random(), 3) for i in range(10)}
    lam, times, left, want = 0.2, dict.fromkeys(range(10), 0), set(c), []
    while len(want) < 6:
        best = min(left, key=lambda i: (-round((1 - lam) * sum(0.5 ** times[j] for j in covers[i]) / 10 + lam * c[i], 12), i))
        want.append(best)
        left.discard(best)
        for j in covers[best]:
            times[j] += 1
    for lazy in (True, False):
        assert [g[1] for g in S.greedy_local(covers, c, 6, lam, lazy=lazy, decay=0.5)] == want
    cd = spark.createDataFrame(list(c.items()), "log_id long, difficulty double")
    ed = spark.createDataFrame([(i, j) for i, v in covers.items() for j in v], "src long, dst long")
    got = S.greedy(cd, ed, 6, lam, decay=0.5).orderBy("rank").collect()
    assert [r["log_id"] for r in got] == want
    assert [r["covered"] for r in got] == [len(set().union(*(covers[i] for i in want[: k + 1]))) for k in range(6)]
    assert [g[1] for g in S.greedy_local(covers, c, 6, lam)] != want


def test_sampled_greedy_is_near_the_full_one(spark):
    rng = random.Random(9)
    covers = {i: {i} | {rng.randrange(40) for _ in range(5)} for i in range(40)}
    c = {i: rng.random() for i in range(40)}
    cd = spark.createDataFrame(list(c.items()), "log_id long, difficulty double")
    ed = spark.createDataFrame([(i, j) for i, v in covers.items() for j in v], "src long, dst long")
    value = lambda picks: S.objective(picks, covers, c, 0.3, 40)
    full = value([g[1] for g in S.greedy_local(covers, c, 6, 0.3)])
    some = [r["log_id"] for r in S.greedy(cd, ed, 6, 0.3, eps=0.1).collect()]
    assert len(set(some)) == 6 and value(some) >= (1 - 1 / math.e - 0.1) * full
    local = [g[1] for g in S.greedy_sampled(covers, c, 6, 0.3)]
    assert len(set(local)) == 6 and value(local) >= (1 - 1 / math.e - 0.1) * full


def test_sizes_by_cells(spark):
    """Counted by cells of sizes, every pattern stands for as many as its edges say."""
    rng = random.Random(1)
    rows = [(i, [rng.choice("abcdefgh") for _ in range(rng.randint(1, 9))]) for i in range(80)]
    df = spark.createDataFrame(rows, "log_id long, words array<string>").withColumn("left", F.filter("words", lambda w: w > "d"))
    for pats in (patterns(df, "exact"), patterns(df, "exact", "left")):
        for delta in (0.0, 0.3, 0.5, 1.0):
            want = {r["src"]: r["size"] for r in score(edges(pats, delta)).collect()}
            assert {r["src"]: r["size"] for r in sizes(pats, delta).collect()} == want


def test_lines_of_documents_by_brute_force(spark):
    from tplforge.functions.distance import sed_words

    rng = random.Random(2)
    base = [[rng.choice("pqrstuvw") + str(rng.randrange(30)) for _ in range(rng.randint(1, 40))] for _ in range(20)]
    texts = base + [[w if rng.random() > 0.05 else "new" for w in b] for b in base]
    df = tokenize(spark.createDataFrame([(i, " ".join(t)) for i, t in enumerate(texts)], "log_id long, raw string"))
    distinct = {}
    for i, t in enumerate(texts):
        distinct.setdefault(tuple(t), i)
    lines = {i: t for t, i in distinct.items()}
    want = {i: sum(sed_words(list(a), list(b), Similarity("exact")) <= 0.1 * min(len(a), len(b)) for b in lines.values()) for i, a in lines.items()}
    assert {r["src"]: r["size"] for r in sizes(patterns(df, "exact"), 0.1).collect()} == want and max(want.values()) > 1


def test_index_recall(spark):
    e = spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet")
    q = e.filter(F.col("vec_id") % 50 == 0)
    want = {(r["src"], r["dst"]) for r in knn_edges(e, 5, queries=q).collect()}
    got = {(r["src"], r["dst"]) for r in knn_index(e, 5, queries=q).collect()}
    assert len(got & want) >= 0.9 * len(want)
    small = spark.createDataFrame([(i, np.random.default_rng(i).random(4).tolist()) for i in range(9)], "vec_id long, embedding array<double>")
    assert sorted(map(tuple, knn_index(small, 2).collect())) == sorted(map(tuple, knn_edges(small, 2).collect()))


def test_diverse_start_from_tables(spark):
    """The distributed picks are those of the matrix form."""
    rows = spark.read.parquet("/root/testdata/sf0.001/embeddings.parquet").limit(80).collect()
    df = spark.createDataFrame([(r["vec_id"], [float(x) for x in r["embedding"]]) for r in rows], "vec_id long, embedding array<double>")
    want = S.dpp_local([r["vec_id"] for r in rows], np.array([r["embedding"] for r in rows], float), 7)
    assert [r["id"] for r in S.dpp_map(df, 7).orderBy("rank").collect()] == want


def test_tree_of_limited_width(spark):
    """Beyond the fan-out, lines of later first words share a leaf."""
    from tplforge.operators.baselines import parse_tree

    d = tokenize(spark.createDataFrame([(i, "d", f"w{chr(97 + i)} is on", "x") for i in range(6)], "log_id long, domain string, raw string, truth string"))
    groups = lambda n: {r["log_id"]: r["pred"] for r in parse_tree(d, fanout=n).collect()}
    assert len(set(groups(100).values())) == 6
    few = groups(2)
    assert few[0] == "wa is on" and few[1] == "wb is on" and {few[i] for i in range(2, 6)} == {"<*> is on"}
