"""Votes, expectation-maximisation and the scorer worked out again, document by document."""

import math
import random

import numpy as np
import pytest
from test_operators import _doc, _texts

from tplforge.llm import hashed_linear, quality_classifier, quality_rules
from tplforge.llm.text_features import count_features
from tplforge.llm.weak_labels import PRIOR_BAD, PRIOR_GOOD, fit_patterns

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, votes string, fp string, seed long, runs int, n_words string, kept string, rate double, stack int"


def _votes(r, words_too=False):
    """1 accept, 0 reject, -1 abstain, by the rules as they are described."""
    n, letters = max(r["n_words"], 1), max(r["n_letters"], 1)
    upper, repeat, echo, length = r["n_upper"] / letters, r["n_repeat_words"] / n, r["n_echo_words"] / n, r["word_chars"] / n
    pick = lambda reject, accept: 0 if reject else 1 if accept else -1
    out = [
        pick(r["n_symbols"] / n > 0.25, r["n_symbols"] / n < 0.05),
        pick(r["n_symbols"] > 0.06 * r["word_chars"], r["n_symbols"] < 0.02 * r["word_chars"]),
        pick(upper > 0.4 and letters >= 20, upper < 0.15 and letters >= 20),
        pick(r["n_exclaim"] > 0.2 * n, r["n_exclaim"] < 0.05 * n),
        pick(repeat > 0.15 and echo > 0.03, repeat < 0.02 and r["n_words"] >= 30),
        pick(echo > 0.1, echo < 0.03 and r["n_words"] >= 30),
        pick(r["n_dup_lines"] >= 4, False),
        pick(length > 25 or length < 1.5, 2.5 <= length <= 12),
    ]
    return [*out, pick(r["n_words"] < 3, r["n_words"] >= 30)] if words_too else out


def _by_document(votes, rounds=200, prior=0.85, strength=4.0):
    """The same estimation with one term per document and plain loops."""
    r = len(votes[0])
    post = [1 / (1 + (1 - prior) / prior * 16.0 ** sum(v == 0 for v in vs)) for vs in votes]
    for _ in range(rounds):
        share = (sum(post) + strength * prior) / (len(votes) + strength)
        odds = [math.log(share / (1 - share))] * len(votes)
        for j in range(r):
            good, bad = ([strength * p for p in prior_of] for prior_of in (PRIOR_GOOD, PRIOR_BAD))
            for vs, p in zip(votes, post, strict=True):
                if vs[j] >= 0:
                    good[vs[j]] += p
                    bad[vs[j]] += 1 - p
            for d, vs in enumerate(votes):
                if vs[j] >= 0:
                    odds[d] += math.log(good[vs[j]] / sum(good)) - math.log(bad[vs[j]] / sum(bad))
        new = [1 / (1 + math.exp(-min(50, max(-50, o)))) for o in odds]
        moved, post = max(abs(a - b) for a, b in zip(new, post, strict=True)), new
        if moved < 1e-9:
            break
    return post


@pytest.fixture(scope="module")
def docs(spark):
    rng = random.Random(21)
    junk = [" ".join(rng.choice(("AB!!", "###", "x$$$", "CD EF")) for _ in range(40)) for _ in range(12)] + ["line\n" * 9 + "a few more words than ten are here now", "so so so so " * 10]
    return spark.createDataFrame([_doc(i, t) for i, t in enumerate(_texts() + junk)], SCHEMA).repartition(3).cache()


def test_rules_and_posteriors_by_document(docs):
    counts = sorted(count_features(docs).collect(), key=lambda r: r["doc_id"])
    want = _by_document([_votes(r) for r in counts])
    got = {r["doc_id"]: r for r in quality_rules.contract(docs).collect()}
    kept = 0
    for r, p in zip(counts, want, strict=True):
        failed = r["n_words"] < 10 or 100 * r["n_repeat_words"] > 20 * r["n_words"]
        assert got[r["doc_id"]]["p_good"] == pytest.approx(p, abs=1e-5)
        assert got[r["doc_id"]]["base_failed"] == failed
        assert got[r["doc_id"]]["kept"] == (not failed and p >= 0.5)
        kept += got[r["doc_id"]]["kept"]
    assert 0 < kept < len(counts)


def test_patterns_stand_for_their_documents():
    rng = np.random.default_rng(3)
    votes = rng.integers(-1, 2, (200, 5))
    patterns, weight = np.unique(votes, axis=0, return_counts=True)
    post, share, accuracy = fit_patterns(patterns, weight.astype(float))
    of = {tuple(p): q for p, q in zip(patterns.tolist(), post.tolist(), strict=True)}
    want = _by_document(votes.tolist())
    assert [of[tuple(v)] for v in votes.tolist()] == pytest.approx(want, abs=1e-6)
    assert 0 < share < 1 and (accuracy >= 0).all() and (accuracy <= 1).all()


def test_scorer_by_hand(docs):
    """The scores of the query from a model fitted here on the same rows, summed feature by feature."""
    texts = {r["doc_id"]: (r["text"] or "").encode() for r in docs.select("doc_id", "text").collect()}
    counts = sorted(count_features(docs).collect(), key=lambda r: r["doc_id"])
    weak = dict(zip([r["doc_id"] for r in counts], _by_document([_votes(r, True) for r in counts]), strict=True))
    ids = sorted(texts)
    sparse = hashed_linear.features([texts[i] for i in ids], quality_classifier.WORD_GAIN)[:3]
    model = hashed_linear.fit(sparse, np.array([[1 - weak[i], weak[i]] for i in ids]), word_gain=quality_classifier.WORD_GAIN)
    got = {r["doc_id"]: r for r in quality_classifier.score(docs).collect()}
    for k, i in enumerate(ids):
        mine = sparse[0] == k
        z = [float(sum(v * model.weights[f, j] for f, v in zip(sparse[1][mine].tolist(), sparse[2][mine].tolist(), strict=True)) + model.bias[j]) for j in (0, 1)]
        p = 1 / (1 + math.exp(z[0] - z[1]))
        # sums of the fit run in another order on the executors' rows
        assert got[i]["score"] == pytest.approx(p, abs=0.02) and got[i]["keep"] == (got[i]["score"] >= 0.5)


def test_fit_reaches_the_optimum():
    """The gradient of the fitted loss is near zero, by plain sums."""
    rng = np.random.default_rng(5)
    raw = [" ".join(rng.choice(["aa", "bb", "cc", "dd"], 12, p=p)).encode() for p in ([0.5, 0.3, 0.2, 0], [0, 0.2, 0.3, 0.5]) for _ in range(60)]
    y = np.repeat(np.eye(2), 60, axis=0)
    d, f, v, _ = hashed_linear.features(raw)
    m = hashed_linear.fit((d, f, v), y, rounds=800, least=1)
    p = m.posteriors(raw)[0]
    loss = lambda w: -np.mean(np.sum(y * np.log(hashed_linear.Model(w, m.bias).posteriors(raw)[0] + 1e-12), axis=1)) + 1e-3 * float((w.astype(float) ** 2).sum())
    base = loss(m.weights)
    for feature in np.unique(f)[:12].tolist():
        for step in (-0.02, 0.02):
            w = m.weights.copy()
            w[feature, 0] += step
            assert loss(w) >= base - 2e-4
    assert ((p[:, 1] > 0.5) == (y[:, 1] == 1)).mean() > 0.9
