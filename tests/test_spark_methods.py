"""The distributed forms against the local ones, and edge cases, on small frames."""

import random

from pyspark.sql import functions as F

from tplforge.functions import measures as M
from tplforge.functions.distance import sed, sed_arrow, sed_fold, sed_words
from tplforge.functions.words import Similarity, graph, residual, tokenize
from tplforge.operators import rounds as R
from tplforge.operators import select as S
from tplforge.operators.baselines import parse_tree
from tplforge.operators.represent import edges, patterns


def test_distance_forms_agree(spark):
    rng = random.Random(7)
    rows = [(i, [rng.choice("pqrs") for _ in range(rng.randint(0, 6))], [rng.choice("pqrs") for _ in range(rng.randint(0, 6))]) for i in range(60)]
    df = spark.createDataFrame(rows, "i int, a array<string>, b array<string>")
    a, b = F.col("a"), F.col("b")
    got = df.select("i", sed(a, b).alias("n"), sed_fold(a, b).alias("f"), sed_fold(a, b, "as_printed").alias("p"), sed_arrow("exact")("a", "b").alias("u")).collect()
    sim = Similarity("exact")
    for r in got:
        _, x, y = rows[r.i]
        want = sed_words(x, y, sim)
        assert (r.n, r.f, r.u) == (want, want, want)
        assert r.p == sed_words(x, y, sim, "as_printed")


def test_pruned_edges_lose_nothing(spark):
    rng = random.Random(1)
    rows = [(i, [rng.choice("abcdefgh") for _ in range(rng.randint(1, 7))]) for i in range(60)]
    df = spark.createDataFrame(rows, "log_id long, words array<string>")
    pats = patterns(df, "exact")
    for delta in (0.0, 0.3, 0.5, 1.0):
        a, b = (sorted(map(tuple, edges(pats, delta, prune=p).collect())) for p in (True, False))
        assert a == b


def test_distributed_greedy_equals_local(spark):
    rng = random.Random(2)
    covers = {i: {i} | {rng.randrange(12) for _ in range(3)} for i in range(12)}
    c = {i: rng.random() for i in range(12)}
    cd = spark.createDataFrame(list(c.items()), "log_id long, difficulty double")
    ed = spark.createDataFrame([(i, j) for i, v in covers.items() for j in v], "src long, dst long")
    for form in ("separable", "as_printed"):
        got = [(r["log_id"], r["covered"]) for r in S.greedy(cd, ed, 4, 0.5, form).orderBy("rank").collect()]
        assert got == [(g[1], g[3]) for g in S.greedy_local(covers, c, 4, 0.5, form)]
    assert S.greedy(cd.limit(0), ed, 4, 0.5).count() == 0
    assert S.greedy_sharded(cd, ed, 4, 0.5, 3).count() == 4


def test_accuracy_example(spark):
    rows = [("t1", "t1")] * 3 + [("t1", "x")] + [("t2", "t2")] * 2 + [("t3", "t2")]
    df = spark.createDataFrame([("d", "m", *r) for r in rows], "domain string, method string, truth string, pred string")
    r = M.accuracy(df).first()
    assert (round(r.mla, 6), round(r.pta, 6), round(r.rta, 6)) == (round(5 / 7, 6), round(1 / 3, 6), round(1 / 3, 6))
    assert round(M.mla(df).first().mla, 6) == round(5 / 7, 6)
    assert round(M.pta(df).first().pta, 6) == round(M.rta(df).first().rta, 6) == round(1 / 3, 6)


def test_words_of_odd_lines(spark):
    df = tokenize(spark.createDataFrame([(1, "a b  a"), (2, ""), (3, None), (4, " \t ")], "log_id long, raw string"))
    assert {r.log_id: r.n_words for r in df.collect()} == {1: 3, 2: 0, 3: 0, 4: 0}
    e, v = graph(df)
    assert e.count() == 3 and {r.word: (r.df, r.n) for r in v.collect()} == {"a": (1, 2), "b": (1, 1)}
    assert df.select(residual(F.col("words"), F.array(F.lit("a"))).alias("r")).first().r == ["b"]


def _lines(spark, n=40):
    rows = [(i, "d", f"user {i} did {('login', 'logout')[i % 2]} in {i * 3}.50 s", f"user [USER] did {('login', 'logout')[i % 2]} in [AMOUNT] s") for i in range(n)]
    return tokenize(spark.createDataFrame(rows, "log_id long, domain string, raw string, truth string"))


def test_rounds_keep_their_promises(spark):
    lines = _lines(spark)
    cfg = R.Config(budget=2, start=(1, 1))
    got = R.run(lines, cfg)
    assert len(got.labelled) <= 2 and sum(t["spent"] for t in got.trace) <= 2
    r = M.accuracy(got.predictions.withColumn("method", F.lit("FULL"))).first()
    assert (r.mla, r.pta, r.rta) == (1.0, 1.0, 1.0)
    for name in ("-SED", "-RS", "-PC", "-AD", "-AB"):
        assert R.run(lines, R.variant(cfg, name)).predictions.count() == 40
    assert R.run(lines, R.Config(budget=0)).labelled == []
    assert R.run(lines.limit(0), cfg).predictions.count() == 0


def test_parse_tree_groups(spark):
    got = parse_tree(_lines(spark))
    assert {r.pred for r in got.select("pred").distinct().collect()} <= {"user <*> did login in <*> s", "user <*> did logout in <*> s", "user <*> did <*> in <*> s"}
    assert got.count() == 40
