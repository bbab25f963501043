"""A linear scorer over hashed features, fitted on a bounded sample of rows.

Features of a text: which words it has (lower case, only letters and digits),
which four-letter word beginnings, and how its words share among shapes
(capitals, symbols, equal to the word before, ...). They are worked out for many
texts at once by array operations over their bytes, without a step per word; a
text of any length is cut into its words and never shortened. Texts without words
(null, empty, blank) have the one shape of a short text.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tplforge.llm.common import byte_slices, mix, raw_bytes

DIMS = 1 << 16
HALF = DIMS // 2
SHAPES = ("lower", "title", "capital", "symbol", "digit", "other", "echo", "short_text")
SHAPE_GAIN = 6.0
#: bytes of texts worked on at a time: an array operation's temporaries are some ten times that
STEP_BYTES = 1 << 19
#: bytes that a word is told by, beside its length
TOLD = 16
_SPACE, _LOW, _UP, _DIGIT, _SYMBOL, _HIGH, _MARK = range(7)


def _byte_classes() -> np.ndarray:
    out = np.full(256, _MARK, np.uint8)
    for chars, c in ((b" \t\n\v\f\r", _SPACE), (bytes(range(97, 123)), _LOW), (bytes(range(65, 91)), _UP), (b"0123456789", _DIGIT), (b"#*$%&|<>", _SYMBOL), (bytes(range(128, 256)), _HIGH)):
        out[list(chars)] = c
    return out


_CLASS = _byte_classes()
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def _step(raw: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Text number * DIMS + feature of all words and beginnings, sorted and each once; shape shares; words per text."""
    n = len(raw)
    buf = np.frombuffer(b" ".join(raw) + b" ", np.uint8)
    cls = _CLASS[buf]
    space = cls == _SPACE
    # a word begins behind a space and ends before one
    edge = np.flatnonzero(np.diff(space.view(np.int8), prepend=np.int8(1)))
    start, end = edge[0::2], edge[1::2]
    ends_of = np.cumsum(np.fromiter(map(len, raw), np.int64, n) + 1)
    doc = np.searchsorted(ends_of, start, side="right")
    counts = np.bincount(doc, minlength=n)
    shape = np.zeros((n, len(SHAPES)))
    shape[:, 7] = counts < 10
    if not len(start):
        return np.empty(0, np.int64), shape, counts

    def per_word(c: int) -> np.ndarray:
        upto = np.zeros(len(cls) + 1, np.int32)
        np.cumsum(cls == c, out=upto[1:])
        return upto[end] - upto[start]

    low, up, symbol = per_word(_LOW) + per_word(_HIGH), per_word(_UP), per_word(_SYMBOL)
    # letters and digits of all words, one after another
    inside = np.flatnonzero((cls >= _LOW) & (cls <= _DIGIT) | (cls == _HIGH))
    kept = np.concatenate([_LOWER[buf[inside]], np.zeros(TOLD, np.uint8)])
    at = np.searchsorted(inside, start)
    length = np.searchsorted(inside, end) - at
    told = np.zeros((2, len(start)), np.uint64)
    for j in range(TOLD):
        b = np.where(j < length, kept[at + j], 0).astype(np.uint64)
        told[j // 8] |= b << np.uint64(8 * (j % 8))
    word = mix(told[0] + mix(told[1] ^ np.uint64(0x9E3779B97F4A7C15)) + length.astype(np.uint64))
    begin = mix((told[0] & np.uint64(0xFFFFFFFF)) ^ np.uint64(0xC2B2AE3D27D4EB4F) * (length > 4).astype(np.uint64))
    w = (word % np.uint64(HALF)).astype(np.int64)
    p = (begin % np.uint64(HALF - len(SHAPES))).astype(np.int64) + HALF
    has = length > 0
    present = np.unique(np.concatenate([doc[has] * DIMS + w[has], doc[has] * DIMS + p[has]]))
    first, last = cls[np.minimum(start, len(cls) - 1)], cls[end - 1]
    # the last of several that hold counts
    kind = np.full(len(start), 5)
    kind[(low > 0) & (up == 1) & (first == _UP)] = 1
    kind[(low > 0) & (up == 0)] = 0
    kind[(up > 1) & (low == 0)] = 2
    kind[first == _DIGIT] = 4
    kind[(symbol * 3 >= end - start) | (last == _SYMBOL)] = 3
    share = np.bincount(doc * len(SHAPES) + kind, minlength=n * len(SHAPES)).reshape(n, len(SHAPES)).astype(float)
    same = (word[1:] == word[:-1]) & (doc[1:] == doc[:-1]) & has[1:]
    share[:, 6] = np.bincount(doc[1:][same], minlength=n)
    shape[:, :7] = SHAPE_GAIN * share[:, :7] / np.maximum(counts, 1)[:, None]
    return present, shape, counts


def features(raw: list[bytes], word_gain: float = 1.0) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Sparse rows: text number, feature, value (of a word that is there: word_gain); and the words of each text."""
    parts, at, total = [], 0, []
    while at < len(raw):
        end, size = at, 0
        while end < len(raw) and (end == at or size + len(raw[end]) <= STEP_BYTES):
            size += len(raw[end])
            end += 1
        present, shape, counts = _step(raw[at:end])
        sd, sf = np.nonzero(shape)
        d = np.concatenate([present // DIMS, sd]) + at
        f = np.concatenate([present % DIMS, DIMS - len(SHAPES) + sf])
        parts.append((d.astype(np.int32), f.astype(np.int32), np.concatenate([np.full(len(present), word_gain), shape[sd, sf]]).astype(np.float32)))
        total.append(counts)
        at = end
    if not parts:
        return np.empty(0, np.int32), np.empty(0, np.int32), np.empty(0, np.float32), np.empty(0, np.int64)
    return *(np.concatenate(x) for x in zip(*parts, strict=True)), np.concatenate(total)


@dataclass
class Model:
    weights: np.ndarray  # DIMS x classes
    bias: np.ndarray
    word_gain: float = 1.0

    def posteriors(self, raw: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Posterior of each class and number of words of each text."""
        d, f, v, counts = features(raw, self.word_gain)
        k = len(self.bias)
        logit = np.stack([np.bincount(d, v * self.weights[f, j], minlength=len(raw)) for j in range(k)], axis=1) + self.bias
        e = np.exp(logit - logit.max(axis=1, keepdims=True)) if len(raw) else logit
        return e / e.sum(axis=1, keepdims=True), counts


def sample_features(docs: DataFrame, target: list[Column], word_gain: float = 1.0) -> tuple[tuple[np.ndarray, np.ndarray, np.ndarray], np.ndarray]:
    """Features and targets of the rows of a sample, docs(text, ...): texts stay on the executors.

    A row brings at most DIMS features, however long its text is.
    """
    k = len(target)
    rows = docs.select(F.col("text").cast("string").alias("text"), F.array(*(t.cast("double") for t in target)).alias("y"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in byte_slices(batches, "text"):
            d, f, v, _ = features(raw_bytes(b, "text"), word_gain)
            order = np.argsort(d, kind="stable")
            ends = np.concatenate([[0], np.cumsum(np.bincount(d, minlength=b.num_rows))]).astype(np.int32)
            yield pa.record_batch([pa.ListArray.from_arrays(pa.array(ends), pa.array(x[order])) for x in (f, v)] + [b.column("y")], names=["f", "v", "y"])

    got = rows.mapInArrow(run, "f array<int>, v array<float>, y array<double>").toArrow()
    f, v = (np.concatenate([np.empty(0, t), *(c.flatten().to_numpy() for c in got.column(n).chunks)]) for n, t in (("f", np.int32), ("v", np.float32)))
    sizes = np.concatenate([np.empty(0, np.int64), *(np.diff(c.offsets.to_numpy()) for c in got.column("f").chunks)])
    y = np.concatenate([np.empty(0), *(c.flatten().to_numpy() for c in got.column("y").chunks)]).reshape(-1, k)
    return (np.repeat(np.arange(len(sizes), dtype=np.int32), sizes), f, v), y


def fit(sparse: tuple[np.ndarray, np.ndarray, np.ndarray], target: np.ndarray, rounds: int = 80, rate: float = 0.3, ridge: float = 2e-3, word_gain: float = 1.0, least: int = 40) -> Model:
    """Multinomial logistic fit by adaptive gradient steps; target: share of each class for each text.

    Sums run over the features in order of texts (forward) and in order of features (backward), one class at a time.
    """
    n, k = target.shape
    w, b = np.zeros((DIMS, k)), np.log(np.maximum(target.mean(axis=0), 1e-3)) if n else np.zeros(k)
    if not n:
        return Model(w.astype(np.float32), b, word_gain)
    d, f, v = sparse
    # what only a few texts of the sample have can be learnt by heart, and is no evidence elsewhere
    common = np.bincount(f, minlength=DIMS) >= min(least, max(1, n // 20))
    d, f, v = d[common[f]], f[common[f]], v[common[f]]
    # only the features that are used take part in the steps
    used, f = np.unique(f, return_inverse=True)
    by_text, by_feature = np.argsort(d, kind="stable"), np.argsort(f, kind="stable")
    rows, row_at = np.unique(d[by_text], return_index=True)
    col_at = np.unique(f[by_feature], return_index=True)[1]
    f_row, v_row = f[by_text], v[by_text]
    d_col, v_col = d[by_feature], v[by_feature]
    x, seen, sb = np.zeros((len(used), k), np.float32), np.full((len(used), k), 1e-8), np.full(k, 1e-8)
    for _ in range(rounds if len(used) else 0):
        logit = np.tile(b, (n, 1))
        for j in range(k):
            logit[rows, j] += np.add.reduceat(v_row * np.ascontiguousarray(x[:, j])[f_row], row_at)
        e = np.exp(logit - logit.max(axis=1, keepdims=True))
        err = ((e / e.sum(axis=1, keepdims=True) - target) / n).astype(np.float32)
        g = ridge * x
        for j in range(k):
            g[:, j] += np.add.reduceat(v_col * np.ascontiguousarray(err[:, j])[d_col], col_at)
        seen += g * g
        x -= (rate * g / np.sqrt(seen)).astype(np.float32)
        gb = err.sum(axis=0)
        sb += gb * gb
        b = b - rate * gb / np.sqrt(sb)
    w[used] = x
    return Model(w.astype(np.float32), b, word_gain)


def sample_rows(df: DataFrame, key: str, rows: int) -> DataFrame:
    """At most `rows` rows, chosen by the hash of a key: all of them where there are no more."""
    n = df.count()
    if n > rows:
        share = int(rows / n * (1 << 32))
        df = df.filter(F.pmod(F.xxhash64(F.lit("sample"), F.col(key)), F.lit(1 << 32)) < share)
    return df.limit(rows + 4 * int(rows**0.5) + 1)


def predict(docs: DataFrame, model: Model, names: list[str], cells: int = 0) -> DataFrame:
    """docs(doc_id, text) -> doc_id, n_words and the posterior of each class; with cells, the lattice cell of the posteriors too."""
    held = docs.sparkSession.sparkContext.broadcast((model.weights, model.bias, model.word_gain))  # DIMS x classes

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = Model(*held.value)
        for b in byte_slices(batches, "text"):
            p, counts = m.posteriors(raw_bytes(b, "text"))
            cols, heads = [b.column("doc_id"), pa.array(counts.astype(np.int64)), *(pa.array(p[:, j]) for j in range(p.shape[1]))], ["doc_id", "n_words", *names]
            if cells:
                cols, heads = [*cols, pa.array(lattice(p, cells))], [*heads, "cell"]
            yield pa.record_batch(cols, names=heads)

    return docs.mapInArrow(run, "doc_id long, n_words long, " + ", ".join(f"{n} double" for n in names) + (", cell long" if cells else ""))


def lattice(p: np.ndarray, steps: int) -> np.ndarray:
    """The number of the point nearest to each row of shares among those whose shares are multiples of 1/steps."""
    low = np.floor(p * steps).astype(np.int64)
    rest = p * steps - low
    missing = steps - low.sum(axis=1)
    rank = np.argsort(np.argsort(-rest, axis=1, kind="stable"), axis=1, kind="stable")
    point = low + (rank < missing[:, None])
    return point @ (steps + 1) ** np.arange(p.shape[1], dtype=np.int64)
