"""Distances of lines: cosine of mean vectors, and edit distance over words.

The edit distance of two word lists costs 1 for a word more or less and, under
`similar_free`, 0 for a pair of similar words and 1 for another pair; under
`as_printed` the two costs are exchanged. With 0/1 costs and similarity an
equivalence it is the string distance of lists written as one character per
word, which runs natively; other cases run in Arrow batches.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

from tplforge.functions.words import Similarity, classed


def cosine(a: Column, b: Column) -> Column:
    """Cosine of two arrays of numbers; null where one has no length."""
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)
    n = F.sqrt(dot(a, a)) * F.sqrt(dot(b, b))
    return F.when(n > 0, dot(a, b) / n)


def _glyphs(arr: Column, names: Column) -> Column:
    """One character per word: its place among the words of the pair, from a block without surrogates."""
    one = lambda w: F.decode(F.unhex(F.lpad(F.hex((F.array_position(names, w) + 0x100).cast("long")), 4, "0")), "UTF-16BE")
    return F.array_join(F.transform(arr, one), "")


def sed(a: Column, b: Column, similarity: str = "exact") -> Column:
    """Native edit distance of two word arrays, similar words free. A pair may hold 50,000 distinct words."""
    if similarity == "classed":
        a, b = classed(a), classed(b)
    names = F.array_distinct(F.concat(a, b))
    return F.when(a == b, F.lit(0)).otherwise(F.levenshtein(_glyphs(a, names), _glyphs(b, names)))


def sed_fold(a: Column, b: Column, polarity: str = "similar_free") -> Column:
    """The same recurrence as folds over the rows of the table; either polarity. The portable reference form."""
    hit, miss = (0, 1) if polarity == "similar_free" else (1, 0)

    def next_row(row: Column, w: Column) -> Column:
        def cell(acc: Column, j: Column) -> Column:
            cost = F.when(F.element_at(b, j) == w, hit).otherwise(miss)
            best = F.least(F.element_at(acc, -1) + 1, F.element_at(row, j + 1) + 1, F.element_at(row, j) + cost)
            return F.concat(acc, F.array(best))

        start = F.array(F.element_at(row, 1) + 1)
        return F.when(F.size(b) == 0, start).otherwise(F.aggregate(F.sequence(F.lit(1), F.greatest(F.size(b), F.lit(1))), start, cell))

    return F.element_at(F.aggregate(a, F.sequence(F.lit(0), F.size(b)), next_row), -1)


def sed_words(a: list[str], b: list[str], sim: Similarity, polarity: str = "similar_free", most: int | None = None) -> int:
    """Two-row form for one pair; gives most+1 once the distance must exceed `most`."""
    hit, miss = (0, 1) if polarity == "similar_free" else (1, 0)
    row = list(range(len(b) + 1))
    for i, w in enumerate(a, 1):
        new = [i]
        for j, x in enumerate(b, 1):
            new.append(min(new[-1] + 1, row[j] + 1, row[j - 1] + (hit if sim.same(w, x) else miss)))
        row = new
        if most is not None and min(row) > most:
            return most + 1
    return row[-1]


def sed_bits(a: list[str], b: list[str], most: int) -> int:
    """Edit distance of two word lists, equal words free, one bit of a whole number per word; most+1 once it must exceed `most`."""
    n, start, end = min(len(a), len(b)), 0, 0
    while start < n and a[start] == b[start]:  # common ends cost nothing
        start += 1
    while end < n - start and a[-1 - end] == b[-1 - end]:
        end += 1
    a, b = a[start : len(a) - end], b[start : len(b) - end]
    if abs(len(a) - len(b)) > most:
        return most + 1
    if not a or not b:
        return max(len(a), len(b))
    at: dict[str, int] = {}
    for i, w in enumerate(a):
        at[w] = at.get(w, 0) | 1 << i
    full, last = (1 << len(a)) - 1, 1 << (len(a) - 1)
    # bits of up and down: where a column of the table rises or falls from one word of a to the next
    up, down, dist, left = full, 0, len(a), len(b)
    for w in b:
        eq = at.get(w, 0)
        diag = ((eq & up) + up ^ up) | eq
        rise, fall = down | ~(diag | up) & full, up & diag
        dist += 1 if rise & last else -1 if fall & last else 0
        left -= 1
        if dist - left > most:
            return most + 1
        rise, fall, keep = (rise << 1 | 1) & full, fall << 1 & full, eq | down
        up, down = fall | ~(keep | rise) & full, rise & keep
    return dist


def sed_within():
    """A column function: whether two texts of one word per row are at most so many words apart. In Arrow batches."""

    @F.pandas_udf("boolean")
    def run(a: pd.Series, b: pd.Series, most: pd.Series) -> pd.Series:
        return pd.Series([sed_bits(x.split("\n"), y.split("\n"), k) <= k for x, y, k in zip(a, b, most, strict=True)], dtype=bool)

    return run


def sed_arrow(similarity: str = "vector", tau: float = 0.5, polarity: str = "similar_free"):
    """A column function of two word arrays for similarity that is no equivalence, in Arrow batches."""

    @F.pandas_udf("int")
    def run(a: pd.Series, b: pd.Series) -> pd.Series:
        sim = Similarity(similarity, tau)
        return pd.Series([sed_words(list(x), list(y), sim, polarity) for x, y in zip(a, b, strict=True)])

    return run


def threshold(delta: float, a_len: Column, b_len: Column) -> Column:
    return F.lit(delta) * F.least(a_len, b_len)
