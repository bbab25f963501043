"""Contexts and labels of many lines at once, where words are alike by their vectors.

A line's context follows from the sets of examples that its words are alike to, a word's label from its scores, its
place, the word before and the context. So a batch has one matrix of scores, its words by those of the examples; a
context is chosen once per kind of line, and a label once per word, place, word before and context. The last digits of
a matrix product are not those of single products: where they could decide, single products are taken.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tplforge.functions.words import shape_of, vectors
from tplforge.operators.context import Demo, adaptive
from tplforge.operators.models import CANDIDATES, PRIOR, Context, ContextTagger, Predictor, _prompt_rest, line_length

#: scores nearer than this are compared by single products
NEAR = 1e-9
#: contexts that a task remembers
MOST = 200_000


def in_batches(model, ctx: Context, demos: list[Demo]) -> bool:
    """Whether Batches gives the answers of Predictor."""
    alike = model.similarity == ctx.similarity == "vector" if type(model) is ContextTagger else False
    return alike and not model.inject and ctx.mode == "adaptive" and ctx.cover == "target" and all(len(d.words) <= len(d.labels) for d in demos)


class _Sets:
    """Stands in for MatchIndex: a word is a pair of a number of its own and the number of its set of examples."""

    def __init__(self, demos: list[Demo]):
        self.demos, self.ids, self.number, self.members = demos, [d.id for d in demos], {}, []

    def of(self, hits: np.ndarray) -> np.ndarray:
        """Number of the set in every row of hits (words by examples)."""
        if not self.ids:
            self.members = [{}]
            return np.zeros(len(hits), np.int32)
        packed = np.ascontiguousarray(np.packbits(hits, axis=1))
        kinds, row = np.unique(packed.view(np.dtype((np.void, packed.shape[1]))).ravel(), return_inverse=True)
        first = np.zeros(len(kinds), np.int64)
        first[row] = np.arange(len(hits))
        texts = [k.tobytes() for k in kinds]
        for kind, at in zip(texts, first, strict=True):
            if kind not in self.number:
                self.number[kind] = len(self.members)
                self.members.append({self.ids[d]: 0 for d in np.flatnonzero(hits[at])})
        return np.array([self.number[k] for k in texts], np.int32)[row]

    def matches(self, word: tuple[int, int]) -> dict[int, int]:
        return self.members[word[1]]


class Batches:
    """What Predictor answers, for columns of words."""

    def __init__(self, model: ContextTagger, ctx: Context, demos: list[Demo], rnd: int = 0):
        self.model, self.ctx, self.demos, self.p = model, ctx, demos, Predictor(model, ctx, demos, rnd)
        self.words = list(dict.fromkeys(w for d in demos for w in d.words))
        self.at = {w: k for k, w in enumerate(self.words)}
        self.v = vectors(self.words)
        self.table = list(dict.fromkeys([*(x for d in demos for x in d.labels), *PRIOR.values(), *CANDIDATES]))
        self.label = {x: k for k, x in enumerate(self.table)}
        self.sets, self.contexts = _Sets(demos), {}
        self.number: dict[tuple[int, ...], int] = {}
        self.chosen: list[tuple[int, ...]] = []

    def answer(self, lines: pa.Array) -> pa.StructArray:
        """pred, demos and rest, the characters of the prompt beside the line's, of every list of words."""
        size = pc.fill_null(pc.list_value_length(lines), 0).to_numpy(zero_copy_only=False).astype(np.int64)
        named = lines.flatten().dictionary_encode()
        names, word = named.dictionary.to_pylist(), named.indices.to_numpy().astype(np.int64)
        own = np.array([self.at.get(w, -1) for w in names], np.int64)
        context, tag, exact = self._scores(names, own)
        hits = np.array([(context[:, [self.at[w] for w in d.words]] >= self.ctx.tau).any(axis=1) for d in self.demos]).reshape(len(self.demos), len(names)).T
        g = self._contexts(size, word, self.sets.of(hits))
        start = np.cumsum(size) - size
        place = np.arange(len(word)) - np.repeat(start, size)
        # 0 at the begin of a line, -1 for words that no example has
        before = np.where(own < 0, -1, own + 1)[np.r_[0, word[:-1]]] if len(word) else word
        before = np.where(place == 0, 0, before)
        label, of = np.zeros(len(word), np.int64), np.repeat(g, size)
        for k in np.unique(of):
            at = np.flatnonzero(of == k)
            label[at] = self._labels(self.chosen[k], names, word[at], before[at], place[at], tag, exact)
        flat = pa.array([*self.table, *names], pa.string()).take(pa.array(label))
        text = pc.binary_join(pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(size)].astype(np.int32)), flat), " ")
        at = pa.array(g)
        rest = [_prompt_rest([], [self.p.by[d] for d in c]) for c in self.chosen]
        return pa.StructArray.from_arrays([text, pa.array([list(c) for c in self.chosen], pa.list_(pa.int64())).take(at), pa.array(rest, pa.int64()).take(at)], names=["pred", "demos", "rest"])

    def _scores(self, names: list[str], own: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Scores of the words (rows) with the examples' words for the context and for the model, and which are those of single products."""
        v = vectors(names)
        s = v @ self.v.T
        # vectors without a common place have a product of 0 in any order
        exact = (v != 0).astype(np.float32) @ (self.v != 0).T.astype(np.float32) == 0
        s[exact] = 0.0
        close = np.abs(s - 0.9) < NEAR
        for tau in {self.ctx.tau, self.model.tau}:
            close |= np.abs(s - tau) < NEAR
        for u, k in zip(*np.nonzero(close & ~exact), strict=True):
            s[u, k] = v[u] @ self.v[k]
        tag = np.where(s >= self.model.tau, np.minimum(s, 0.9), -np.inf)
        exact |= close | (s >= 0.9)
        same = np.flatnonzero(own >= 0)
        s[same, own[same]] = 1.0
        tag[same, own[same]] = [1.0 if shape_of(names[u]) == names[u] else 0.9 for u in same]
        exact[same, own[same]] = True
        return s, tag, exact

    def _contexts(self, size: np.ndarray, word: np.ndarray, kind: np.ndarray) -> np.ndarray:
        """Places in self.chosen of the lines' examples, which follow from the sets of their different words."""
        row, n = np.repeat(np.arange(len(size)), size), max(1, len(kind))
        one = np.unique(row * n + word)
        row, kinds = one // n, kind[one % n] if len(one) else one.astype(np.int32)
        held = kinds[np.lexsort((kinds, row))].tobytes()
        ends = (4 * np.searchsorted(row, np.arange(len(size) + 1))).tolist()
        out = np.empty(len(size), np.int64)
        for i, (a, b) in enumerate(zip(ends, ends[1:], strict=False)):
            key = held[a:b]
            if (k := self.contexts.get(key)) is None:
                if len(self.contexts) > MOST:
                    self.contexts.clear()
                words = list(enumerate(np.frombuffer(key, np.int32).tolist()))
                picked = tuple(adaptive(words, self.sets, self.ctx.cover, self.ctx.strict_break)[0])
                if (k := self.number.get(picked)) is None:
                    k = self.number[picked] = len(self.chosen)
                    self.chosen.append(picked)
                self.contexts[key] = k
            out[i] = k
        return out

    def _labels(self, chosen: tuple[int, ...], names: list[str], word: np.ndarray, before: np.ndarray, place: np.ndarray, tag: np.ndarray, exact: np.ndarray) -> np.ndarray:
        """Labels of words behind others at places: numbers in self.table, or behind it, the word itself."""
        demos = [self.p.by[d] for d in chosen]
        wide = int(place.max()) + 1
        key, back = np.unique((word * (len(self.words) + 2) + before + 1) * wide + place, return_inverse=True)
        place, key = key % wide, key // wide
        before, word = key % (len(self.words) + 2) - 1, key // (len(self.words) + 2)
        col = np.array([self.at[w] for d in demos for w in d.words], np.int64)
        out, unseen, tied = np.zeros(len(word), np.int64), np.ones(len(word), bool), np.zeros(len(word), bool)
        if len(col):
            prev = np.array([self.at[d.words[j - 1]] + 1 if j else 0 for d in demos for j in range(len(d.words))])
            at = np.array([j for d in demos for j in range(len(d.words))])
            says = np.array([-1 if x == w else self.label[x] for d in demos for w, x in zip(d.words, d.labels, strict=False)])
            score = tag[word][:, col] + (0.05 * (prev == before[:, None]) + 0.01 * (at == place[:, None]))
            best = score.argmax(axis=1)  # the first of equals
            top = score[np.arange(len(word)), best]
            unseen = np.isneginf(top)
            sure = exact[word][:, col]
            tied = ((score > top[:, None] - NEAR) & (col != col[best][:, None]) & ~(sure & sure[np.arange(len(word)), best][:, None])).any(axis=1) & ~unseen
            out = np.where(says[best] < 0, len(self.table) + word, says[best])
        for i in np.flatnonzero(tied):
            w = names[word[i]]
            # a word that no example has is behind none of theirs
            behind = "" if before[i] == 0 else self.words[before[i] - 1] if before[i] > 0 else "\n"
            x = self.model._best(w, behind, int(place[i]), demos, self.p.tag_sim)[1]
            out[i] = len(self.table) + word[i] if x == w else self.label[x]
        guess = {u: self.model.unseen(names[u], self.p.tag_sim)[0] for u in np.unique(word[unseen]).tolist()}
        for i in np.flatnonzero(unseen):
            x = guess[word[i]]
            out[i] = len(self.table) + word[i] if x == names[word[i]] else self.label[x]
        return out[back]


def answered_batches(lines: DataFrame, model: ContextTagger, ctx: Context, demos: list[Demo], rnd: int = 0) -> DataFrame:
    """Lines with labels, echo, demos, tokens and pred; the labelled set (bounded by the budget) is broadcast."""
    spark = lines.sparkSession
    held = spark.sparkContext.broadcast((model, ctx, demos, rnd))
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 2 * spark.sparkContext.defaultParallelism)

    @F.arrow_udf("pred string, demos array<long>, rest long")
    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        b = Batches(*held.value)
        for words in batches:
            yield b.answer(words)

    asked = lines.repartition(tasks, "log_id").withColumn("_a", run.asNondeterministic()("words"))
    labels = F.when(F.size("words") == 0, F.array().cast("array<string>")).otherwise(F.split("_a.pred", " "))  # no label holds a blank
    tokens = F.ceil((F.col("_a.rest") + line_length(F.col("words"))) / 4).cast("long")
    return asked.withColumns({"labels": labels, "echo": F.col("words"), "demos": F.col("_a.demos"), "tokens": tokens, "pred": F.col("_a.pred")}).drop("_a")
