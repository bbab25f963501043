"""Mixing to target weights with soft membership.

A classifier fitted on a labelled table (a bounded, documented sample of it)
gives every document its posterior over domains. A document of n tokens adds
r * n * p_k expected tokens to domain k at rate r. Rates between 0 and `ceiling`
are found by projected gradient descent on the squared errors of the domain
totals, measured in shares of all tokens, so that a domain with hardly any tokens
weighs hardly anything, plus `pull` times the token-weighted squared distance of
the rates from 1, which settles what the targets leave open.

In the metric that weighs documents by their tokens, a document's gradient depends
on its posterior alone. Posteriors are therefore put into the cells of a lattice
whose number is bounded by the lattice and not by the corpus (at most CELLS). One
distributed pass sums the tokens and the expected tokens of each domain per cell;
the rounds run on those sums, with no further pass over documents, until the rates
stand still; and a cell's rate goes back to its documents by a join. A domain's
total is exact: what is rounded is which documents share a rate.

Targets are shares of a mix that leaves the domain of the largest share about its
own tokens. A domain cannot be raised beyond `ceiling` times the tokens it has:
where its share asks for more, the target is that much and the others keep their
shares; `Fit.unreachable` says by how much it was cut.

Null and empty texts have no tokens and cannot move a total; they get the rate of
their cell like others. Rows that repeat a doc_id are rated one by one, rows
without a doc_id too. Very long texts are whole documents of many tokens. Ties of
posteriors have one cell and one rate. Labels without a document, or null ones, are
not learnt from; a document with several labels has the least domain name. With no
labels every posterior is uniform. An empty table gives an empty result. Columns
of other names play no part.
"""

from __future__ import annotations

from dataclasses import dataclass
from math import comb

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tplforge.llm.common import fresh_names, stored, texts
from tplforge.llm.hashed_linear import fit, predict, sample_features, sample_rows

FIT_ROWS = 6000
DOMAINS = ("good", "poor", "toxic")
#: shares of the tokens of the mix
TARGETS = (0.95, 0.05, 0.0)
#: lattice points, at most; steps of the lattice, at most
CELLS, STEPS = 100_000, 64
ROUNDS = 20_000
PULL = 1e-3
#: a document is repeated no more often
CEILING = 4.0
#: rates that near to 1 are one copy, others are rounded by chance
NEAR = 0.1


def label_domain() -> Column:
    return F.when(F.col("toxic") == 1, "toxic").when(F.col("quality") == 0, "poor").when(F.col("quality") == 1, "good")


def lattice_steps(domains: int, cells: int = CELLS, most: int = STEPS) -> int:
    """The finest lattice of shares that has at most `cells` points."""
    steps = most
    while steps > 1 and comb(steps + domains - 1, domains - 1) > cells:
        steps -= 1
    return steps


@dataclass
class Fit:
    """Rates per cell, and what they come to."""

    cell: np.ndarray
    rate: np.ndarray
    target: np.ndarray
    begun: np.ndarray
    total: np.ndarray
    unreachable: np.ndarray
    loss: list[float]


def posteriors(docs: DataFrame, labels: DataFrame, domain: Column, domains: tuple[str, ...] = DOMAINS, id_col: str = "doc_id", text_col: str = "text", fit_rows: int = FIT_ROWS) -> DataFrame:
    """doc_id, n_words, the posterior p_<domain> and its lattice cell of every row."""
    docs = texts(docs, id_col, text_col)
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), domain.alias("domain")).filter(F.col("domain").isin(*domains)).groupBy("doc_id").agg(F.min("domain").alias("domain"))
    chosen = sample_rows(known, "doc_id", fit_rows)
    rows = docs.join(F.broadcast(chosen), "doc_id").limit(2 * fit_rows)  # the sample's bound holds the size of chosen
    sparse, target = sample_features(rows, [F.col("domain") == d for d in domains])
    return predict(docs, fit(sparse, target), [f"p_{d}" for d in domains], lattice_steps(len(domains)))


def targets(begun: np.ndarray, weights: tuple[float, ...], ceiling: float = CEILING) -> tuple[np.ndarray, np.ndarray]:
    """Tokens wanted of each domain, and how many of its share are out of reach."""
    share = np.array(weights, float) / sum(weights)
    lead = int(share.argmax())
    asked = share * (begun[lead] / share[lead])
    reached = np.minimum(asked, ceiling * begun)
    return reached, asked - reached


def descend(tokens: np.ndarray, expected: np.ndarray, target: np.ndarray, rounds: int = ROUNDS, pull: float = PULL, ceiling: float = CEILING, tolerance: float = 1e-9) -> tuple[np.ndarray, list[float]]:
    """Rates of cells: tokens (cells) and expected tokens of each domain (cells x domains)."""
    live = tokens > 0
    rate = np.ones(len(tokens))
    size = tokens.sum()
    if not live.any():
        return rate, []
    n, e = tokens[live] / size, expected[live] / size
    p, want = e / n[:, None], target / size
    step = 1 / (np.linalg.eigvalsh((p * n[:, None]).T @ p).max() + pull)
    r, losses = np.ones(len(n)), []
    for _ in range(rounds):
        gap = r @ e - want
        losses.append(float(gap @ gap + pull * (n * (r - 1) ** 2).sum()) / 2)
        new = np.clip(r - step * (p @ gap + pull * (r - 1)), 0, ceiling)
        moved, r = np.abs(new - r).max(), new
        if moved <= tolerance:
            break
    rate[live] = r
    return rate, losses


def fit_rates(scored: DataFrame, weights: tuple[float, ...] = TARGETS, domains: tuple[str, ...] = DOMAINS, rounds: int = ROUNDS, pull: float = PULL, ceiling: float = CEILING) -> Fit:
    """scored(n_words, p_<domain>, cell): one pass; as many rows reach the driver as the lattice has points at most."""
    names = [f"p_{d}" for d in domains]
    sums = scored.groupBy("cell").agg(F.sum("n_words").alias("n"), *(F.sum(F.col("n_words") * F.col(a)).alias(a) for a in names)).toArrow().sort_by("cell")
    cell, tokens = sums["cell"].to_numpy(), sums["n"].to_numpy().astype(float)
    expected = np.stack([sums[a].to_numpy() for a in names], axis=1)
    begun = expected.sum(axis=0)
    want, out_of_reach = targets(begun, weights, ceiling)
    rate, losses = descend(tokens, expected, want, rounds, pull, ceiling)
    return Fit(cell, rate, want, begun, rate @ expected, out_of_reach, losses)


def mix(docs: DataFrame, labels: DataFrame, weights: tuple[float, ...] = TARGETS, domains: tuple[str, ...] = DOMAINS, fit_rows: int = FIT_ROWS, rounds: int = ROUNDS, ceiling: float = CEILING) -> DataFrame:
    """doc_id, n_words, posteriors, rate and n_copies of every row.

    n_copies is the rate rounded up or down by the hash of doc_id, so that it is right on the average; rates
    within NEAR of 1 are one copy, so that documents which the targets hardly touch are not lost by chance.
    """
    scored = stored(posteriors(docs, labels, label_domain(), domains, fit_rows=fit_rows), "mixing")
    found = fit_rates(scored, weights, domains, rounds, ceiling=ceiling)
    rates = docs.sparkSession.createDataFrame([(int(c), round(float(r), 6)) for c, r in zip(found.cell, found.rate, strict=True)], "cell long, rate double")  # at most CELLS rows
    draw = F.pmod(F.xxhash64(F.lit("mixing"), "doc_id"), F.lit(1 << 20)) / F.lit(float(1 << 20))
    copies = F.when(F.abs(F.col("rate") - 1) <= NEAR, 1).otherwise(F.floor(F.col("rate") + draw)).cast("int")
    return scored.join(F.broadcast(rates), "cell").drop("cell").withColumn("n_copies", copies)


def contract(docs: DataFrame, labels: DataFrame) -> DataFrame:
    return mix(docs, labels).select("doc_id", "n_words", *(F.round(f"p_{d}", 6).alias(f"p_{d}") for d in DOMAINS), "rate", "n_copies")


def apply_mix(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """docs whose number of copies is not zero, with mix_rate and mix_copies (the most of a doc_id's rows).

    Columns of these names that docs has already are replaced. Rows without a doc_id are rated as one.
    """
    rated = mix(docs, labels).filter("n_copies > 0")
    docs = docs.drop("mix_rate", "mix_copies")
    key = fresh_names(docs, "id")[0]
    rated = rated.groupBy(F.col("doc_id").alias(key)).agg(F.max("rate").alias("mix_rate"), F.max("n_copies").alias("mix_copies"))
    return docs.join(rated, docs["doc_id"].eqNullSafe(F.col(key))).drop(key)
