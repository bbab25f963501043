"""The stage's near copies against all pairs compared by their five-word shingles."""

import random

from tplforge.llm import simhash, similar_texts


def _kept(rows, bound=0.8, k=5):
    ids = [i for i, _ in rows]
    sets = [frozenset(simhash.shingle_hashes((t or "").encode(), k)) for _, t in rows]
    root = {i: i for i in ids}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    links = 0
    for x, a in enumerate(sets):
        for y in range(x):
            b = sets[y]
            if a == b or len(a & b) / len(a | b) >= bound:
                links += a != b
                lo, hi = sorted((find(ids[x]), find(ids[y])))
                root[hi] = lo
    return {find(i) for i in ids}, links


def test_near_copies_of_any_kind(spark, monkeypatch):
    """Chains of edits, a group of near copies, a passage that many share; every document is in the sample."""
    rng = random.Random(11)
    word = lambda: f"w{rng.randrange(5000)}"
    rows = []
    passage = [word() for _ in range(60)]
    for _ in range(40):
        base = [word() for _ in range(rng.randint(8, 200))]
        rows.append(base)
        for _ in range(4):
            base = list(base)
            for _ in range(rng.randint(0, 1 + len(base) // 60)):
                base[rng.randrange(len(base))] = word()
            rows.append(base + [word() for _ in range(rng.randint(0, 3))])
    rows += [passage + [word() for _ in range(rng.randint(20, 120))] for _ in range(40)]
    hub = [word() for _ in range(150)]
    rows += [[word() if rng.random() < 0.004 else w for w in hub] for _ in range(60)]
    texts = [" ".join(r) for r in rows] + [None, "", "one", "One", "a b c d", "a b c d e"]
    rng.shuffle(texts)
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    want, links = _kept(list(enumerate(texts)))
    assert links > 300
    old = {r["component_id"] for r in simhash.contract(docs).collect()}
    assert len(old) > len(want)
    for sample, block in ((64, 1 << 18), (1, 50)):
        monkeypatch.setattr(similar_texts, "SAMPLE", sample)
        monkeypatch.setattr(similar_texts, "BLOCK", block)
        assert {r["doc_id"] for r in simhash.keep_one(docs).collect()} == want
