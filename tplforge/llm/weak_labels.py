"""Weak supervision: expectation-maximisation over overlapping voters.

Each of R voters says accept (1), reject (0) or abstains (-1). Documents with
the same votes are alike, so all that the estimation needs is the count of
every vote pattern: at most 3**R rows, whatever the corpus. Those counts are
taken over all documents; the posterior of each pattern then returns by a join
whose small side has at most 3**R rows.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Voter:
    """accept and reject are conditions; where neither holds (or is null) the voter abstains."""

    name: str
    reject: Column
    accept: Column

    def vote(self) -> Column:
        return F.when(self.reject, 0).when(self.accept, 1).otherwise(-1).cast("int")


def with_pattern(df: DataFrame, voters: list[Voter], name: str = "votes") -> DataFrame:
    """Votes packed into one number of base 3, first voter lowest."""
    packed = reduce(lambda a, x: a + x, ((v.vote() + 1).cast("long") * 3**i for i, v in enumerate(voters)))
    return df.withColumn(name, packed)


def unpack(patterns: np.ndarray, n: int) -> np.ndarray:
    return np.stack([patterns // 3**i % 3 for i in range(n)], axis=1) - 1


#: pseudo-counts of (reject, accept) by class: a rule seldom rejects what is good, and
#: sees only some kinds of bad documents, so on bad ones it may say anything
PRIOR_BAD, PRIOR_GOOD = (2.0, 1.0), (0.05, 3.0)


def fit_patterns(votes: np.ndarray, weight: np.ndarray, rounds: int = 200, prior: float = 0.85, strength: float = 4.0) -> tuple[np.ndarray, float, np.ndarray]:
    """Posterior of `good` for each pattern, the share of good ones, and each voter's accuracy.

    What is estimated is how often each voter rejects and accepts on good and on bad
    documents; an abstention says nothing. It begins with every rejection halving the odds four times over, which also
    settles which of the two classes is the good one. accuracy[j] is the share of voter j's
    votes that are right under the posteriors.
    """
    n, r = votes.shape
    if not n:
        return np.full(n, prior), prior, np.full(r, 0.5)
    said = np.stack([votes == v for v in (0, 1)], axis=2).astype(float)  # pattern, voter, outcome
    post = 1 / (1 + (1 - prior) / prior * 16.0 ** (votes == 0).sum(axis=1))
    total = weight.sum()
    pseudo = strength * np.stack([np.tile(PRIOR_BAD, (r, 1)), np.tile(PRIOR_GOOD, (r, 1))])
    share = prior
    for _ in range(rounds):
        g, b = weight * post, weight * (1 - post)
        share = float((g.sum() + strength * prior) / (total + strength))
        theta = pseudo + np.stack([np.einsum("p,pjo->jo", b, said), np.einsum("p,pjo->jo", g, said)])
        theta = theta / theta.sum(axis=2, keepdims=True)
        odds = np.log(share / (1 - share)) + np.einsum("pjo,jo->p", said, np.log(theta[1]) - np.log(theta[0]))
        new = 1 / (1 + np.exp(-np.clip(odds, -50, 50)))
        moved, post = np.abs(new - post).max(), new
        if moved < 1e-9:
            break
    right = (weight * post) @ (votes == 1) + (weight * (1 - post)) @ (votes == 0)
    return post, share, right / np.maximum(weight @ (votes >= 0), 1e-9)


def posteriors(df: DataFrame, voters: list[Voter], name: str = "p_good") -> DataFrame:
    """df with the posterior of being good. df is read twice: hand over stored features."""
    spark = df.sparkSession
    voted = with_pattern(df, voters)
    seen = voted.groupBy("votes").count().collect()  # at most 3**len(voters) rows
    pattern = np.array([r["votes"] for r in seen], np.int64)
    votes = unpack(pattern, len(voters))
    post, _, _ = fit_patterns(votes, np.array([r["count"] for r in seen], float))
    rows = [(int(p), float(q)) for p, q in zip(pattern, post, strict=True)]
    known = spark.createDataFrame(rows, f"votes long, {name} double")
    return voted.join(F.broadcast(known), "votes", "left").drop("votes")
