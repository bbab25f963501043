"""Language identification: words first, then shorter and shorter character n-grams.

A word met in training scores its log frequency in each language. Any other
word falls back to the longest n for which some of its n-grams (of the word
between boundary marks) were met, and scores their mean log frequency minus a
charge for each step back. A text's score is the sum over its words.

Words are runs of letters (Unicode category L, with the marks that follow them).
Fitted on a bounded, documented sample of labelled rows (`fit_rows`), whose words are
counted on the executors: what reaches the driver is the counts. A text that is null or
has no letter is `und` with score 0; with no labelled rows every text is `und`. Texts
of any length are judged whole. Rows are judged one by one, repeated doc_ids and rows
without one included; languages that tie go to the first by name. An empty table gives
an empty result. Columns of other names play no part.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tplforge.llm.common import MEMO_ENTRIES, byte_slices, texts
from tplforge.llm.hashed_linear import sample_rows

FIT_ROWS = 6000
LONGEST = 4
MIN_COUNT = 3
STEP_BACK = 0.5
_RUNS = regex.compile(r"\p{L}[\p{L}\p{M}]*")


@dataclass
class Model:
    langs: list[str]
    words: dict[str, tuple[float, ...]]
    grams: list[dict[str, int]]  # by length, from 1: place in the table of that length
    tables: list[np.ndarray]

    def word(self, w: str) -> np.ndarray:
        if (known := self.words.get(w)) is not None:
            return np.array(known)
        marked = f"<{w}>"
        for n in range(LONGEST, 0, -1):
            look = self.grams[n - 1].get
            found = [g for i in range(len(marked) - n + 1) if (g := look(marked[i : i + n])) is not None]
            if found:
                return self.tables[n - 1][found].sum(axis=0) / len(found) - STEP_BACK * (LONGEST + 1 - n)
        return np.zeros(len(self.langs))


def _frequencies(counts: list[Counter], least: int) -> dict[str, tuple[float, ...]]:
    totals = [sum(c.values()) + 1.0 for c in counts]
    names = Counter()
    for c in counts:
        names.update(c)
    return {w: tuple(math.log((c[w] + 0.05) / t) for c, t in zip(counts, totals, strict=True)) for w, n in names.items() if n >= least}


def word_counts(found: list[tuple[str, str]]) -> Counter:
    """(language, word) -> occurrences in found, pairs of language and text."""
    out = Counter()
    for lang, text in found:
        out.update((lang, w) for w in _RUNS.findall(text.lower()))
    return out


def model_of(counts: Counter) -> Model:
    """The model of word_counts."""
    langs = sorted({x for x, _ in counts})
    words = {x: Counter() for x in langs}
    for (x, w), n in counts.items():
        words[x][w] += n
    grams, tables = [], []
    for n in range(1, LONGEST + 1):
        by = []
        for x in langs:
            c = Counter()
            for w, k in words[x].items():
                m = f"<{w}>"
                for i in range(len(m) - n + 1):
                    c[m[i : i + n]] += k
            by.append(c)
        known = _frequencies(by, 1)
        grams.append({g: i for i, g in enumerate(known)})
        tables.append(np.array(list(known.values())).reshape(len(known), len(langs)))
    return Model(langs, _frequencies([words[x] for x in langs], MIN_COUNT), grams, tables)


def fit(rows: DataFrame) -> Model:
    """rows(x, t): language and text of a bounded sample; its words are counted before they reach the driver."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in byte_slices(batches, "t"):
            c = word_counts(list(zip(b.column("x").to_pylist(), b.column("t").to_pylist(), strict=True)))
            yield pa.record_batch([pa.array([k[0] for k in c], pa.string()), pa.array([k[1] for k in c], pa.string()), pa.array(list(c.values()), pa.int64())], names=["x", "w", "n"])

    got = rows.mapInArrow(run, "x string, w string, n long").groupBy("x", "w").agg(F.sum("n").alias("n")).toArrow()
    return model_of(Counter({(x, w): n for x, w, n in zip(*(got[c].to_pylist() for c in ("x", "w", "n")), strict=True)}))


class TokenScores(dict):
    """raw token -> number of its row in `table`; row 0 is for tokens without letters."""

    def __init__(self, model: Model):
        self.model, self.rows, self.table = model, 1, np.zeros((1 << 12, max(1, len(model.langs))))

    def __missing__(self, token: str) -> int:
        runs = _RUNS.findall(token.lower())
        n = 0
        if runs:
            n = self.rows
            self.rows += 1
            if n >= len(self.table):
                self.table = np.concatenate([self.table, np.zeros_like(self.table)])
            self.table[n, : len(self.model.langs)] = sum(self.model.word(w) for w in runs)
        self[token] = n
        return n


def predict_texts(scores: TokenScores, found: list[str]) -> tuple[list[str], np.ndarray]:
    look = scores.__getitem__
    ids = [np.fromiter(map(look, t), np.int64, len(t)) for t in (x.split() for x in found)]
    lang, p = [], np.zeros(len(found))
    for i, x in enumerate(ids):
        x = x[x > 0]
        if not len(x) or not scores.model.langs:
            lang.append("und")
            continue
        s = scores.table[x].sum(axis=0)
        j = int(s.argmax())
        lang.append(scores.model.langs[j])
        p[i] = 1 / np.exp(s - s[j]).sum()
    return lang, p


def identify(docs: DataFrame, labelled: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", fit_rows: int = FIT_ROWS) -> DataFrame:
    """doc_id, lang_pred, score of every row of docs, learnt from at most about fit_rows of `labelled`."""
    known = labelled.select(F.col(id_col).alias("i"), F.col(text_col).cast("string").alias("t"), F.col(lang_col).cast("string").alias("x")).filter("x IS NOT NULL AND t IS NOT NULL")
    held = docs.sparkSession.sparkContext.broadcast(fit(sample_rows(known, "i", fit_rows).select("x", "t")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scores = TokenScores(held.value)
        for b in byte_slices(batches, "text"):
            if len(scores) > MEMO_ENTRIES:
                scores = TokenScores(held.value)
            lang, p = predict_texts(scores, [t or "" for t in b.column("text").to_pylist()])
            yield pa.record_batch([b.column("doc_id"), pa.array(lang, pa.string()), pa.array(p)], names=["doc_id", "lang_pred", "score"])

    return texts(docs, id_col, text_col).mapInArrow(run, "doc_id long, lang_pred string, score double")


def contract(docs: DataFrame) -> DataFrame:
    """Learnt from rows that are not held out; a row without a doc_id is neither held out nor learnt from."""
    rest = lambda c: F.pmod(F.crc32(c.cast("string")), F.lit(4))
    found = identify(docs, docs.filter(rest(F.col("doc_id")) != 2))
    return found.select("doc_id", F.coalesce(rest(F.col("doc_id")) == 2, F.lit(False)).alias("held_out"), "lang_pred", F.round("score", 9).alias("score"))
