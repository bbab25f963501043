"""Near copies among whole lines are found by runs of words, and none is lost."""

import random

import pytest
from pyspark.sql import functions as F

from tplforge.functions.distance import sed_words
from tplforge.functions.words import Similarity
from tplforge.operators import represent


def _texts(seed, vocab, n):
    rnd = random.Random(seed)
    out = []
    for _ in range(n):
        t = [rnd.choice(vocab) for _ in range(rnd.choice((1, 5, 9, 10, 11, 19, 20, 21, 40)))]
        out.append(t)
        for _ in range(3):
            c = list(t)
            for _ in range(rnd.randint(1, max(1, len(t) // 8))):
                at, how = rnd.randrange(len(c) + 1), rnd.randrange(3)
                c[at : at + (how > 0)] = [rnd.choice(vocab)] if how < 2 else []
            out.append(c)
    return [t for t in out if t]


@pytest.mark.parametrize(("seed", "vocab", "delta"), [(1, "abc", 0.1), (2, "ab", 0.1), (3, [f"w{i}" for i in range(400)], 0.1), (4, "abcdefgh", 0.2)])
def test_none_lost(spark, seed, vocab, delta):
    texts = _texts(seed, list(vocab), 40)
    d = spark.createDataFrame(list(enumerate(texts)), "log_id long, words array<string>")
    lines = represent.whole_lines(d)
    got = {r["src"]: r["size"] for r in represent.sizes_whole(lines, delta).collect()}
    first = {}
    for i, t in enumerate(texts):
        first.setdefault(tuple(t), i)
    sim = Similarity("exact")
    want = {i: sum(sed_words(list(a), list(b), sim) <= delta * min(len(a), len(b)) for b in first) for a, i in first.items()}
    assert got == want and max(want.values()) > 1


def test_few_pairs_are_compared(spark):
    """400 lines of 30 words out of 60: nearly all pairs share a rare word, none shares a run of five."""
    rnd = random.Random(5)
    d = spark.createDataFrame([(i, [f"w{rnd.randrange(60)}" for _ in range(30)]) for i in range(400)], "log_id long, words array<string>")
    side = represent.whole_lines(d).select("log_id", "res", F.col("n_words").alias("p"), F.col("n_words").alias("len"))
    assert represent._sharing_grams(side, 0.1, 5).count() < 100 < 10_000 < represent._sharing(side, 0.1).count()
