"""Label budgets per round, and the words identified so far."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def next_budget(prev: int, before: int, now: int, left: int, rounding: str = "floor") -> int:
    """prev * (1 - (now-before)/now), the factor held to 0..2, at least 1, at most what is left."""
    factor = min(2.0, max(0.0, 1 - (now - before) / now)) if now else 1.0
    value = prev * factor
    n = {"floor": math.floor(value + 1e-9), "ceil": math.ceil(value - 1e-9), "nearest": round(value)}[rounding]
    return min(left, max(1, n))


def compared(seen: list[int], basis: str = "cumulative") -> tuple[int, int]:
    """The counts before and now; seen starts with 0 and has what was known after each round."""
    if basis == "cumulative":
        return seen[-2], seen[-1]
    return (seen[-2] - seen[-3] if len(seen) > 2 else 0), seen[-1] - seen[-2]


def trace(words: list[int], total: int, start: tuple[int, ...], basis: str = "cumulative", rounding: str = "floor") -> list[int]:
    """Budgets of all rounds; words[r] is the count after round r, so round r goes by those of the two before it."""
    out, left = [], total
    seen = words if basis == "cumulative" else [b - a for a, b in zip([0, *words], words, strict=False)]
    for r in range(len(words)):
        if left <= 0:
            break
        b = min(left, start[r]) if r < len(start) else next_budget(out[-1], seen[r - 2] if r > 1 else 0, seen[r - 1], left, rounding)
        out.append(b)
        left -= b
    return out


def words_seen(labelled: DataFrame) -> int:
    """Distinct words of labelled lines."""
    return labelled.select(F.explode("words").alias("w")).agg(F.countDistinct("w")).first()[0]
