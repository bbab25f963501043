"""Labelled examples for a line: as few as cover its words, or a fixed number of similar ones."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tplforge.functions.words import Similarity, vector, vectors
from tplforge.schema import DEMOS
from tplforge.session import stored


@dataclass(frozen=True)
class Demo:
    id: int
    words: tuple[str, ...]
    labels: tuple[str, ...]


def best_match(word: str, demo: Demo, sim: Similarity) -> tuple[int, float] | None:
    """Place and score of the demo's word nearest to `word`, if it counts as similar."""
    best = max(((sim.score(word, x), -i) for i, x in enumerate(demo.words)), default=None)
    if best is None or best[0] < (sim.tau if sim.kind == "vector" else 0):
        return None
    return -best[1], best[0]


class MatchIndex:
    """word -> for each demo with a similar word, the place of the nearest one; remembered per word."""

    def __init__(self, demos: list[Demo], sim: Similarity):
        self.demos, self.sim, self.known = demos, sim, {}
        self.where: dict[str, list[tuple[int, int]]] = {}
        if sim.kind != "vector":
            for d in demos:
                for i, w in enumerate(d.words):
                    for key in {w, sim.shape(w) if sim.kind == "classed" else w}:
                        self.where.setdefault(key, []).append((d.id, i))

    def matches(self, w: str) -> dict[int, int]:
        if (m := self.known.get(w)) is None:
            if self.sim.kind == "vector":
                m = {d.id: got[0] for d in self.demos if (got := best_match(w, d, self.sim))}
            else:
                m = {}
                for key in (w, self.sim.shape(w) if self.sim.kind == "classed" else w):
                    for d, i in self.where.get(key, ()):
                        m.setdefault(d, i)
            if len(self.known) > 200_000:
                self.known.clear()
            self.known[w] = m
        return m


def adaptive(words: list[str], index: MatchIndex, cover: str = "target", strict_break: bool = False) -> tuple[list[int], list[str]]:
    """Greedy cover: demo ids in order of choice, and the words no demo covers.

    cover="target" counts covered words of the line; "as_printed" counts the demos' own matched words.
    strict_break ends the scan of demos at the first without gain.
    """
    gains: dict[int, set] = {}
    reached = set()
    by_id = {d.id: d for d in index.demos} if cover == "as_printed" else {}
    for p, w in enumerate(words):
        m = index.matches(w)
        if m:
            reached.add(w)
        for d, i in m.items():
            gains.setdefault(d, set()).add(w if cover == "target" else by_id[d].words[i])
    out, done = [], set()
    while gains:
        best, most = None, 0
        for d in sorted(gains):
            g = len(gains[d] - done)
            if not g and strict_break:
                break
            if g > most:
                best, most = d, g
        if best is None:
            break
        done |= gains.pop(best)
        out.append(best)
    return out, [w for w in dict.fromkeys(words) if w not in reached]


class TopK:
    """The k demos with the nearest mean word vectors; ties to the lower id."""

    def __init__(self, demos: list[Demo], k: int):
        self.ids = np.array([d.id for d in demos], np.int64)
        self.k, self.memo = k, {}
        self.m = np.array([self.mean(d.words) for d in demos]) if demos else np.empty((0, 64))

    def mean(self, words) -> np.ndarray:
        if not len(words):
            return np.zeros(64)
        v = sum(vector(w) if w not in self.memo else self.memo[w] for w in words) / len(words)
        n = np.linalg.norm(v)
        return v / n if n else v

    def pick(self, words: list[str]) -> list[int]:
        if not len(self.ids):
            return []
        s = np.round(self.m @ self.mean(words), 9)
        order = np.lexsort((self.ids, -s))[: self.k]
        return self.ids[order].tolist()

    def pick_all(self, lines: list[list[str]]) -> list[list[int]]:
        """pick() for a batch, with one matrix for all its words."""
        if not len(self.ids) or not lines:
            return [[] for _ in lines]
        if len(self.memo) > 50_000:
            self.memo.clear()
        new = [w for w in dict.fromkeys(w for ws in lines for w in ws) if w not in self.memo]
        self.memo.update(zip(new, vectors(new), strict=True))
        words = {w: k for k, w in enumerate(dict.fromkeys(w for ws in lines for w in ws))}
        v = np.array([self.memo[w] for w in words]).reshape(-1, 64)
        return self._nearest(np.array([len(ws) for ws in lines]), np.array([words[w] for ws in lines for w in ws], np.int64), v).tolist()

    def pick_arrow(self, lines: pa.Array) -> pa.Array:
        """pick_all() for a column of words; nothing is done line by line."""
        size = pc.fill_null(pc.list_value_length(lines), 0).to_numpy(zero_copy_only=False).astype(np.int64)
        if not len(self.ids) or not len(size):
            return pa.array([[]] * len(size), pa.list_(pa.int64()))
        if len(self.memo) > 50_000:
            self.memo.clear()
        named = lines.flatten().dictionary_encode()
        words = named.dictionary.to_pylist()
        new = [w for w in words if w not in self.memo]
        self.memo.update(zip(new, vectors(new), strict=True))
        got = self._nearest(size, named.indices.to_numpy().astype(np.int64), np.array([self.memo[w] for w in words]).reshape(-1, 64))
        ends = np.arange(len(size) + 1, dtype=np.int32) * got.shape[1]
        return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.ascontiguousarray(got).ravel()))

    def _nearest(self, size: np.ndarray, place: np.ndarray, v: np.ndarray) -> np.ndarray:
        """Ids per line, for lines of so many words, which stand one behind the other in place, as rows of v."""
        begin = np.cumsum(size) - size
        total = np.zeros((len(size), 64))
        for p in range(size.max()):
            at = np.flatnonzero(size > p)
            total[at] += v[place[begin[at] + p]]
        total /= np.maximum(size, 1)[:, None]
        n = np.sqrt(np.einsum("ij,ij->i", total, total))[:, None]
        s = np.round(total / np.where(n > 0, n, 1) @ self.m.T, 9)
        rank = np.argsort(self.ids, kind="stable")
        order = np.argsort(-s[:, rank], axis=1, kind="stable")[:, : self.k]
        return self.ids[rank][order]


def context_frame(lines: DataFrame, demos: list[Demo], mode: str = "adaptive", k: int = 5, sim: Similarity | None = None, cover: str = "target", strict_break: bool = False) -> DataFrame:
    """log_id, demos, uncovered for lines(log_id, words). The labelled set is bounded by the label budget."""
    held = lines.sparkSession.sparkContext.broadcast((demos, sim or Similarity()))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        d, s = held.value
        index, top = MatchIndex(d, s), TopK(d, k)
        for pdf in batches:
            got = [adaptive(list(w), index, cover, strict_break) if mode == "adaptive" else (top.pick(list(w)), []) for w in pdf.words]
            yield pd.DataFrame({"log_id": pdf.log_id, "demos": [g[0] for g in got], "uncovered": [g[1] for g in got]})

    return lines.select("log_id", "words").mapInPandas(run, DEMOS)


def adaptive_sql(lines: DataFrame, demos: DataFrame, rounds: int | None = None) -> DataFrame:
    """The cover by joins and window ranks (exact similarity), one round per choice: rank, log_id, demo.

    Goes on until no line gains another demo. rounds: choices for which one plan is made at a time; it bounds
    the plan and not the cover.
    """
    from pyspark.sql import Window as W

    need = lines.select("log_id", F.explode(F.array_distinct("words")).alias("w"))
    have = demos.select(F.col("log_id").alias("demo"), F.explode(F.array_distinct("words")).alias("w"))
    out, r = None, 0
    while True:
        part = None
        for _ in range(max(1, rounds or 1)):
            r += 1
            gain = need.join(have, "w").groupBy("log_id", "demo").agg(F.count("*").alias("gain"))
            best = gain.withColumn("k", F.row_number().over(W.partitionBy("log_id").orderBy(F.desc("gain"), "demo"))).filter("k = 1").select(F.lit(r).alias("rank"), "log_id", "demo")
            part = best if part is None else part.union(best)
            need = need.join(best.join(have, "demo").select("log_id", "w"), ["log_id", "w"], "left_anti")
        part, need = stored(part, "context-picks"), stored(need, "context-need")
        out = part if out is None else out.union(part)
        if part.filter(F.col("rank") == r).isEmpty():
            return out
