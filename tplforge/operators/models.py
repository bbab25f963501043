"""Template models and the annotator. A model answers with labels, the words it echoes, and probabilities.

The models here are deterministic stand-ins for a language model; a remote one has
the same interface and is declared, not called.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass, replace

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tplforge.functions.words import VARIABLE, Similarity, form, shape_of
from tplforge.operators.context import Demo, MatchIndex, TopK, adaptive
from tplforge.operators.prompt import text as prompt_text
from tplforge.session import stored

#: shape class -> type that the model guesses without an example
PRIOR = {"<date>": "[DATE]", "<dec>": "[AMOUNT]", "<addr>": "[ADDR]", "<url>": "[URL]", "<int>": "[CODE]", "<hex>": "[CODE]", "<id>": "[NAME]"}
CANDIDATES = tuple("[USER] [AMOUNT] [DATE] [CODE] [SESSION] [ADDR] [ORDER] [CUST] [PART] [SUPP] [BRAND] [SIZE] [NAME] [NATION] [URL]".split())


@dataclass
class Answer:
    labels: list[str]
    echo: list[str]
    probs: list[float]


@dataclass(frozen=True)
class ContextTagger:
    """Labels words after the examples it is shown; inject: share of lines (per 1000) with a made-up error.

    misread: share of words (per 1000) that the model takes for a variable, of a type it makes up, as long as no
    example shows them: what a language model does with rare words.
    """

    similarity: str = "classed"
    tau: float = 0.5
    inject: int = 0
    seed: int = 7
    misread: int = 0

    def answer(self, log_id: int, words: list[str], demos: list[Demo], sim: Similarity, rnd: int = 0) -> Answer:
        labels, probs = [], []
        for i, w in enumerate(words):
            best = self._best(w, words[i - 1] if i else "", i, demos, sim)
            if best:
                labels.append(best[1])
                probs.append(0.99 if best[2] else 0.5 + 0.5 * min(best[0], 0.98))
            else:
                label, prob = self.unseen(w, sim)
                labels.append(label)
                probs.append(prob)
        out = Answer(labels, list(words), probs)
        return self._err(log_id, rnd, out) if self.inject else out

    def unseen(self, w: str, sim: Similarity) -> tuple[str, float]:
        """Label and probability of a word that no example fits."""
        if (guess := PRIOR.get(sim.shape(w))) is not None:
            return guess, 0.4
        h = zlib.crc32(f"{w}/{self.seed}".encode())
        return CANDIDATES[h // 1000 % len(CANDIDATES)] if h % 1000 < self.misread else w, 0.3

    def _best(self, w: str, before: str, i: int, demos: list[Demo], sim: Similarity) -> tuple[float, str, bool] | None:
        """Score, label and equality of the examples' word that fits w best, behind `before` at place i."""
        best, near = None, {}
        for d in demos:
            for j, x in enumerate(d.words):
                if (s := near.get(x)) is None:
                    if x == w:
                        # a variable met before says what it was there, not what it is here
                        s = 1.0 if sim.shape(w) == w else 0.9
                    else:
                        s = sim.score(w, x)
                        s = min(s, 0.9) if s >= (sim.tau if sim.kind == "vector" else 0) else -2.0
                    near[x] = s
                if s == -2.0:
                    continue
                s += 0.05 * ((d.words[j - 1] if j else "") == before) + 0.01 * (i == j)
                if best is None or s > best[0]:
                    best = (s, w if d.labels[j] == x else d.labels[j], x == w)
        return best

    def _err(self, log_id: int, rnd: int, a: Answer) -> Answer:
        h = zlib.crc32(f"{log_id}/{rnd}/{self.seed}".encode())
        unsure = sum(p < 0.9 for p in a.probs)
        # the more of a line is unknown, the likelier it goes wrong
        if h % 1000 >= self.inject * (1 + 2 * unsure) or not a.labels:
            return a
        if h >> 12 & 1:
            a.labels, a.echo, a.probs = a.labels[:-1], a.echo[:-1], a.probs[:-1]
        else:
            variable = [i for i, (x, w) in enumerate(zip(a.labels, a.echo, strict=True)) if x != w]
            if variable:
                i = variable[(h >> 16) % len(variable)]
                a.labels[i] = a.echo[i]
        if h >> 14 & 1:
            a.probs = [max(p, 0.95) for p in a.probs]
        return a


@dataclass(frozen=True)
class ShapeOnly(ContextTagger):
    """The model without any example."""

    def answer(self, log_id, words, demos, sim, rnd=0):
        return ContextTagger.answer(self, log_id, words, [], sim, rnd)


@dataclass(frozen=True)
class EchoTruth:
    """Always right: the upper bound. Truths travel as the only demo's labels."""

    def answer(self, log_id, words, demos, sim, rnd=0):
        d = next((d for d in demos if d.id == log_id), None)
        return Answer(list(d.labels if d else words), list(words), [1.0] * len(words))


@dataclass(frozen=True)
class HttpModel:
    """Interface of a remote model: one call per distinct (pattern, context); never called offline."""

    url: str
    requests_per_second: float = 1.0

    def answer(self, log_id, words, demos, sim, rnd=0):
        raise NotImplementedError("no network here")


@dataclass(frozen=True)
class Context:
    """How examples are chosen for a line."""

    mode: str = "adaptive"
    k: int = 5
    cover: str = "target"
    similarity: str = "classed"
    tau: float = 0.5
    strict_break: bool = False


class Predictor:
    """Context and model for one labelled set, with what was answered before remembered by words."""

    def __init__(self, model, ctx: Context, demos: list[Demo], rnd: int = 0):
        self.model, self.ctx, self.rnd = model, ctx, rnd
        self.by = {d.id: d for d in demos}
        self.sim = Similarity(ctx.similarity, ctx.tau)
        self.tag_sim = Similarity(getattr(model, "similarity", "classed"), getattr(model, "tau", 0.5))
        self.index, self.top = MatchIndex(demos, self.sim), TopK(demos, ctx.k) if ctx.mode == "topk" else None
        self.one_form, self.known, self.answers = by_form(model, ctx), known_words(demos), {}

    def predict(self, log_id: int, words: list[str]) -> tuple[Answer, list[int], list[str], int]:
        if self.ctx.mode == "none":
            chosen, missing = [], []
        elif self.ctx.mode == "topk":
            chosen, missing = self.top.pick(words), []
        else:
            chosen, missing = adaptive(words, self.index, self.ctx.cover, self.ctx.strict_break)
        return self._ask(log_id, words, chosen, missing)

    def _ask(self, log_id: int, words: list[str], chosen: list[int], missing: list[str]) -> tuple[Answer, list[int], list[str], int]:
        demos = [self.by[d] for d in chosen]
        a = self.model.answer(log_id, words, demos, self.tag_sim, self.rnd)
        n = -(-len(prompt_text(words, [(d.words, d.labels) for d in demos])) // 4)
        return a, chosen, missing, n

    def predict_all(self, ids: list[int], lines: list[list[str]]) -> Iterator[tuple[Answer, list[int], list[str], int]]:
        """predict() for a batch: word vectors are made at once, examples of similar lines are ranked at once."""
        seen = [w for ws in lines for w in ws]
        for sim in {id(s): s for s in (self.sim, self.tag_sim)}.values():
            if sim.kind == "vector":
                sim.learn(seen)
        if self.ctx.mode != "topk":
            for i, ws in zip(ids, lines, strict=True):
                yield self.predict(i, ws)
            return
        for i, ws, chosen in zip(ids, lines, self.top.pick_all(lines), strict=True):
            if not self.one_form:
                yield self._ask(i, ws, chosen, [])
                continue
            key = (tuple(chosen), *self._form(ws))
            if (got := self.answers.get(key)) is None:
                if len(self.answers) > 50_000:
                    self.answers.clear()
                a, *_, n = self._ask(i, list(key[1:]), chosen, [])
                got = self.answers[key] = (a.labels, a.probs, _prompt_rest(list(key[1:]), [self.by[d] for d in chosen]))
            labels, probs, rest = got
            own = [w if x[:1] == VARIABLE else x for x, w in zip(labels, ws, strict=True)]
            yield Answer(own, ws, probs), chosen, [], -(-(rest + _line_length(ws)) // 4)

    def _form(self, words: list[str]) -> list[str]:
        """form() of a line, but for words that the examples hold."""
        first: dict[str, int] = {}
        out = []
        for i, w in enumerate(words, 1):
            s = self.sim.shape(w)
            out.append(w if s == w or w in self.known else f"{VARIABLE}{s}={first.setdefault(w, i)}")
        return out


def _line_length(words: list[str]) -> int:
    """Characters of a prompt that its line makes up: it is written once with blanks and once with bars."""
    return 2 * sum(map(len, words)) + 4 * max(0, len(words) - 1)


def line_length(words: Column) -> Column:
    """The same of a column."""
    return 2 * F.aggregate(words, F.lit(0), lambda s, w: s + F.length(w)) + 4 * F.greatest(F.lit(0), F.size(words) - 1)


def _prompt_rest(words: list[str], demos: list[Demo]) -> int:
    """Characters of a prompt beside those of its line."""
    return len(prompt_text(words, [(d.words, d.labels) for d in demos])) - _line_length(words)


def by_form(model, ctx: Context) -> bool:
    """Whether answers depend on nothing but the words that examples hold, and on the form of the others.

    So it is for the stand-in models as long as words are alike by class and no line is picked for a made-up error.
    """
    return type(model) in (ContextTagger, ShapeOnly) and not model.inject and "vector" not in (model.similarity, ctx.similarity)


def known_words(demos: list[Demo]) -> set[str]:
    return {w for d in demos for w in (*d.words, *d.labels)}


ANSWERED = "labels array<string>, echo array<string>, probs array<double>, demos array<long>, uncovered array<string>, tokens long"


def predict(lines: DataFrame, model, ctx: Context, demos: list[Demo], rnd: int = 0) -> DataFrame:
    """Answers for lines(log_id, words), distinct by words; the labelled set (bounded by the budget) is broadcast."""
    shown = lines.select("log_id", "words", *(["form"] if "form" in lines.columns else []))
    return answered(shown, model, ctx, demos, rnd).select("log_id", "labels", "echo", "probs", "demos", "uncovered", "tokens")


def answered(lines: DataFrame, model, ctx: Context, demos: list[Demo], rnd: int = 0) -> DataFrame:
    """predict() beside all columns of the lines. `form`, where lines have it, is that of their words."""
    if by_form(model, ctx) and (ctx.mode in ("adaptive", "none") or "demos" in lines.columns):
        return _answered_forms(lines, model, ctx, demos, rnd)
    spark = lines.sparkSession
    held = spark.sparkContext.broadcast((model, ctx, demos, rnd))
    # a line costs far more than its bytes say, so a few bytes are still worth all tasks
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 2 * spark.sparkContext.defaultParallelism)

    @F.pandas_udf(ANSWERED)
    def run(batches: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.DataFrame]:
        p = Predictor(*held.value)
        for ids, words in batches:
            lists = [w.tolist() for w in words]
            rows = [(a.labels, None if a.echo == ws else a.echo, a.probs, chosen, missing, n) for ws, (a, chosen, missing, n) in zip(lists, p.predict_all(ids.tolist(), lists), strict=True)]
            yield pd.DataFrame(rows, columns=["labels", "echo", "probs", "demos", "uncovered", "tokens"])

    # not to be worked out once more for a filter
    asked = lines.repartition(tasks, "log_id").withColumn("_a", run.asNondeterministic()("log_id", "words"))
    found = {c: F.coalesce(F.col("_a.echo"), F.col("words")) if c == "echo" else F.col(f"_a.{c}") for c in ("labels", "echo", "probs", "demos", "uncovered", "tokens")}
    return asked.withColumns(found).drop("_a", "form")


def nearest_examples(lines: DataFrame, ctx: Context, demos: list[Demo]) -> DataFrame:
    """The lines with demos, the ids of the k nearest examples."""
    spark = lines.sparkSession
    held = spark.sparkContext.broadcast((demos, ctx.k))

    @F.arrow_udf("array<long>")
    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        top = TopK(*held.value)
        for words in batches:
            yield top.pick_arrow(words)

    return lines.withColumn("demos", run.asNondeterministic()("words"))


def answer_rows(rows: list, model, ctx: Context, demos: list[Demo], rnd: int = 0) -> Iterator[tuple[list[str], list[int], int]]:
    """Labels, examples and tokens of a few rows(words, form, length, demos where they are chosen already); the model is asked once per form."""
    p, asked = Predictor(model, ctx, demos, rnd), {}
    for r in rows:
        ws = tuple(w if w in p.known else f for w, f in zip(r["words"], r["form"], strict=True))
        chosen = tuple(r["demos"]) if ctx.mode == "topk" else None
        if (got := asked.get((ws, chosen))) is None:
            a, picked, *_ = p.predict(0, list(ws)) if chosen is None else p._ask(0, list(ws), list(chosen), [])
            got = asked[ws, chosen] = a.labels, picked, _prompt_rest(list(ws), [p.by[d] for d in picked])
        labels, picked, rest = got
        yield [w if x[:1] == VARIABLE else x for x, w in zip(labels, r["words"], strict=True)], picked, -(-(rest + r["length"]) // 4)


def _answered_forms(lines: DataFrame, model, ctx: Context, demos: list[Demo], rnd: int) -> DataFrame:
    """answered() where lines of one form have one answer: the model is asked once per form, lines take theirs by a join."""
    held = lines.sparkSession.sparkContext.broadcast((model, ctx, demos, rnd))
    # constant words are their own form, known or not
    known = F.array(*map(F.lit, sorted(w for w in known_words(demos) if shape_of(w) != w))).cast("array<string>")
    shape_free = F.col("form") if "form" in lines.columns else form(F.col("words"))
    chosen = ["demos"] if "demos" in lines.columns else []
    keyed = lines.withColumn("_form", F.zip_with("words", shape_free, lambda w, f: F.when(f.startswith(VARIABLE) & F.array_contains(known, w), w).otherwise(f))).drop("form")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        p = Predictor(*held.value)
        for pdf in batches:
            rows = []
            for key, near in zip(pdf._form, pdf.demos if chosen else pdf._form, strict=True):
                ws = list(key)
                a, picked, missing, _ = p._ask(0, ws, near.tolist(), []) if chosen else p.predict(0, ws)
                rows.append((ws, a.labels, a.probs, picked, missing, _prompt_rest(ws, [p.by[d] for d in picked])))
            yield pd.DataFrame(rows, columns=["_form", "_labels", "probs", "demos", "_missing", "_rest"])

    forms = keyed.select("_form", *chosen).distinct()
    found = stored(forms.mapInPandas(run, "_form array<string>, _labels array<string>, probs array<double>, demos array<long>, _missing array<string>, _rest long"), "answers")
    own = lambda x, w: F.when(x.startswith(VARIABLE), w).otherwise(x)
    size = F.col("length") if "length" in lines.columns else line_length(F.col("words"))
    missing = F.transform("_missing", lambda x: own(x, F.get("words", F.substring_index(x, "=", -1).try_cast("int") - 1)))
    return keyed.join(found, ["_form", *chosen]).withColumns(
        {"labels": F.zip_with("_labels", "words", own), "echo": F.col("words"), "uncovered": missing, "tokens": F.ceil((F.col("_rest") + size) / 4).cast("long")}
    ).drop("_form", "_labels", "_missing", "_rest")


def templates(pred: DataFrame) -> DataFrame:
    return pred.withColumn("pred", F.array_join("labels", " "))


class TruthAnnotator:
    """Labels of chosen lines by a join with the truth."""

    def __init__(self, lines: DataFrame):
        self.lines = lines

    def label(self, picks: list[int]) -> list[Demo]:
        rows = self.lines.filter(F.col("log_id").isin(picks)).select("log_id", "words", "labels").collect()  # at most the round's budget
        return [Demo(r["log_id"], tuple(r["words"]), tuple(r["labels"])) for r in sorted(rows, key=lambda r: r["log_id"])]


def consistent(words: list[str], a: Answer) -> bool:
    """The answer echoes the line, has a label for every word, and no label but candidates and the words themselves."""
    return a.echo == words and len(a.labels) == len(words) and set(a.labels) <= _ALLOWED | set(words)


_ALLOWED = frozenset(CANDIDATES)


def tagged(labels: list[str], words: list[str]) -> list[str]:
    """Keywords in brackets of their own instead of verbatim: the other style of writing a template."""
    return [f"<{x}>" if x == w else x for x, w in zip(labels, words, strict=True)]


def with_injection(model: ContextTagger, per_thousand: int) -> ContextTagger:
    return replace(model, inject=per_thousand)
