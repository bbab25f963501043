"""The graph of the fixed-size baseline against all pairs."""

import numpy as np

from tplforge.functions.words import vector
from tplforge.operators.baselines import _nearest


def test_nearest_and_not_lowest_ids():
    words = {i: [f"w{i % 7}", f"w{i % 5}", "link", f"x{i // 3}"] for i in range(40)}
    unit = {}
    for i, ws in words.items():
        v = np.mean([vector(w) for w in ws], axis=0)
        unit[i] = v / np.linalg.norm(v)
    got = _nearest(words, 5)
    low = 0
    for i in words:
        cos = sorted((-round(float(unit[i] @ unit[j]), 6), j) for j in words if j != i)
        assert got[i] == {i} | {j for c, j in cos[:5] if -c >= 0.3}
        low += got[i] != {i, *sorted(j for c, j in cos if -c >= 0.3)[:5]}
    assert low
