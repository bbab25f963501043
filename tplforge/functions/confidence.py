"""How sure a model's answer is: mean word probability, consistency flag, difficulty."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def mean_prob(probs: Column) -> Column:
    """Mean of the word probabilities; 0 for an answer without words."""
    n = F.size(probs)
    return F.when(n > 0, F.aggregate(probs, F.lit(0.0), lambda s, p: s + p) / n).otherwise(F.lit(0.0))


def inconsistent(words: Column, echo: Column, labels: Column, candidates: Column | None = None) -> Column:
    """0 where the echo equals the input, every word has a label and each label is a candidate; else 1.

    Labels that repeat the word itself are keywords and always candidates.
    """
    ok = (words == echo) & (F.size(labels) == F.size(words))
    if candidates is not None:
        ok = ok & (F.size(F.array_except(F.array_except(labels, words), candidates)) == 0)
    return F.when(F.coalesce(ok, F.lit(False)), 0).otherwise(1)


def difficulty(p: Column, flag: Column, a: float = 0.5) -> Column:
    """a(1-p) + (1-a)flag: larger is harder."""
    return F.lit(a) * (1 - p) + F.lit(1 - a) * flag
