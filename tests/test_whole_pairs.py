"""Pairs of whole lines are compared by codes as far as the bound, and by their words where the codes leave them."""

import random
import time

import pytest
from pyspark.sql import functions as F

from tplforge.functions.distance import sed_bits, sed_words
from tplforge.functions.words import Similarity
from tplforge.operators import represent


def test_bits_are_the_distance():
    rnd, sim = random.Random(1), Similarity("exact")
    for _ in range(2000):
        vocab = "ab" if rnd.random() < 0.4 else "abcdef"
        a, b = ([rnd.choice(vocab) for _ in range(rnd.randrange(14))] for _ in "ab")
        if rnd.random() < 0.5:
            b = a[: rnd.randrange(len(a) + 1)] + b[:3] + a[-2:]
        want = sed_words(a, b, sim)
        assert [sed_bits(a, b, k) for k in (0, 1, 3, 20)] == [min(want, k + 1) for k in (0, 1, 3, 20)]


def _copies(rnd, n, length, edits):
    base = [f"w{rnd.randrange(10 * length)}" for _ in range(length)]
    out = []
    for i in range(n):
        c = list(base)
        for _ in range(edits):
            c[rnd.randrange(length)] = f"x{i}-{rnd.randrange(9)}"
        out.append(c)
    return out


def _sizes(spark, texts):
    d = spark.createDataFrame(list(enumerate(texts)), "log_id long, words array<string>")
    return {r["src"]: r["size"] for r in represent.sizes_whole(represent.whole_lines(d), 0.1).collect()}


@pytest.mark.parametrize("code", [lambda arr: F.array_join(F.transform(arr, lambda w: F.lit("a")), ""), None])
def test_words_decide_where_codes_are_equal(spark, monkeypatch, code):
    if code:
        monkeypatch.setattr(represent, "_code", code)
    texts, sim = _copies(random.Random(2), 12, 40, 3), Similarity("exact")
    want = {i: sum(sed_words(a, b, sim) <= 4 for b in texts) for i, a in enumerate(texts)}
    assert _sizes(spark, texts) == want and min(want.values()) < max(want.values())


def test_long_copies_take_no_square_of_their_words(spark):
    texts = _copies(random.Random(3), 40, 1500, 20)
    began = time.time()
    assert _sizes(spark, texts) == dict.fromkeys(range(40), 40)
    assert time.time() - began < 30
