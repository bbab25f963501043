"""The round loop: context, prediction, budget, selection, labels, until the budget is spent.

Rounds work on patterns (lines alike but for variable words), which follow the
number of templates and not of lines. Their table is what grows slowest; its
size is checked before the bookkeeping of a round goes to the driver, and above
the limit selection stays distributed. The final pass predicts every distinct line.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tplforge.functions.confidence import difficulty, inconsistent, mean_prob
from tplforge.functions.words import VARIABLE, Similarity, classed, form, residual, shape, shape_of, vector
from tplforge.functions.words import words as words_of
from tplforge.operators import budget as budgets
from tplforge.operators.batches import answered_batches, in_batches
from tplforge.operators.context import Demo
from tplforge.operators.models import CANDIDATES, Context, ContextTagger, Predictor, answer_rows, answered, by_form, consistent, known_words, line_length, nearest_examples, predict, templates
from tplforge.operators.represent import cosine_edges, distinct_lines, edges, edges_local, patterns
from tplforge.operators.select import dpp_local, dpp_map, greedy, greedy_local
from tplforge.plans.choose import LOCAL_CLASSES, choose
from tplforge.session import stored


@dataclass(frozen=True)
class Config:
    budget: int = 200
    start: tuple[int, ...] = (50, 25)
    lam: float = 0.5
    delta: float = 0.5
    a: float = 0.5
    tau: float = 0.5
    fixed: int = 40
    distance: str = "sed"  # or "cosine"
    use_rs: bool = True
    use_pc: bool = True
    adaptive_budget: bool = True
    objective: str = "separable"
    residual: str = "exact"  # "similar" drops words alike to labelled ones too (same shape, or cosine >= tau), "none" drops none
    length_basis: str = "full"
    words_basis: str = "cumulative"
    rounding: str = "floor"
    charge_init: bool = True
    cosine_cut: float = 0.5
    max_rounds: int | None = None
    context: Context = Context()
    model: object = ContextTagger()


@dataclass
class Result:
    labelled: list[Demo]
    trace: list[dict] = field(default_factory=list)
    predictions: DataFrame | None = None
    decisions: dict = field(default_factory=dict)


@dataclass
class _Pattern:
    id: int
    words: list[str]
    labels: list[str]
    weight: int


def _cosine_covers(left: dict[int, list[str]], cut: float) -> dict[int, set[int]]:
    ids = sorted(left)
    m = np.array([np.mean([vector(w) for w in left[i]], axis=0) if left[i] else np.zeros(64) for i in ids]).reshape(-1, 64)
    n = np.linalg.norm(m, axis=1, keepdims=True)
    m = m / np.where(n > 0, n, 1)
    near = m @ m.T >= cut
    return {i: {ids[j] for j in np.flatnonzero(near[k])} | {i} for k, i in enumerate(ids)}


def diverse(pats: dict[int, _Pattern], k: int) -> list[int]:
    ids = sorted(pats)
    if not ids:
        return []
    m = np.array([np.mean([vector(w) for w in pats[i].words], axis=0) if pats[i].words else np.zeros(64) for i in ids])
    return dpp_local(ids, m, k)


def mean_vectors(table: DataFrame) -> DataFrame:
    """log_id and v, the mean word vector of every row."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            v = [np.mean([vector(w) for w in ws], axis=0).tolist() if len(ws) else [0.0] * 64 for ws in pdf.words]
            yield pd.DataFrame({"log_id": pdf.log_id, "v": v})

    return table.select("log_id", "words").mapInPandas(run, "log_id long, v array<double>")


def _left(words: list[str], known: set[str], cfg: Config, sim: Similarity, shapes: set[str]) -> list[str]:
    """The words that the labelled lines do not identify."""
    if cfg.residual == "none":
        return words
    left = [w for w in words if w not in known]
    if cfg.residual == "similar":
        left = [w for w in left if not (any(sim.same(w, x) for x in known) if sim.kind == "vector" else sim.kind == "classed" and sim.shape(w) in shapes)]
    return left


def _residual_column(known: list[str], cfg: Config) -> Column:
    """The same as a column of words; the labelled words are bounded by the label budget."""
    words = F.col("words")
    if cfg.residual == "none":
        return words
    exact = residual(words, F.array(*map(F.lit, known)).cast("array<string>"))
    sim = Similarity(cfg.context.similarity, cfg.tau)
    if cfg.residual == "exact" or sim.kind == "exact":
        return exact
    if sim.kind == "classed":
        shapes = F.array(*map(F.lit, sorted({sim.shape(w) for w in known}))).cast("array<string>")
        return F.filter(exact, lambda w: ~F.array_contains(shapes, shape(w)))
    held = set(known)

    @F.pandas_udf("array<string>")
    def left(ws: pd.Series) -> pd.Series:
        return pd.Series([_left(list(x), held, cfg, sim, set()) for x in ws])

    return left(words)


def _groups(open_: DataFrame, known: list[str], cfg: Config) -> tuple[DataFrame, DataFrame]:
    """(log_id, grp) and (src, dst) of groups: who stands for whom, as covers_of has it."""
    own = open_.select("log_id", F.col("log_id").alias("grp"))
    if not cfg.use_rs:
        return own, own.select(F.col("grp").alias("src"), F.col("grp").alias("dst"))
    if cfg.distance == "cosine":
        return own, cosine_edges(mean_vectors(open_), cfg.cosine_cut)
    kind = cfg.context.similarity
    rows = open_.select("log_id", "words", _residual_column(known, cfg).alias("r"))
    # equal residuals and lengths stand for the same lines
    key = F.struct((classed(F.col("r")) if kind == "classed" else F.col("r")).alias("res"), F.size("words").alias("n_words"))
    member = rows.select("log_id", F.min("log_id").over(W.partitionBy(key)).alias("grp"))
    return member, edges(patterns(rows, kind, "r"), cfg.delta, cfg.length_basis, kind, cfg.tau).select("src", "dst")


def covers_of(open_: dict[int, _Pattern], known: set[str], cfg: Config, spark=None) -> dict[int, set[int]]:
    """Who stands for whom among open patterns, by residual edit distance or by cosine."""
    sim = Similarity(cfg.context.similarity, cfg.tau)
    if cfg.distance == "cosine":
        return _cosine_covers({i: p.words for i, p in open_.items()}, cfg.cosine_cut)
    shapes = {sim.shape(w) for w in known}
    res = {i: _left(p.words, known, cfg, sim, shapes) for i, p in open_.items()}
    length = {i: len(p.words if cfg.length_basis == "full" else res[i]) for i, p in open_.items()}
    if choose(len(open_))["pairs"].choice == "driver" or spark is None or sim.kind == "vector":
        return edges_local(res, length, cfg.delta, sim)
    rows = [(i, [sim.shape(w) if sim.kind == "classed" else w for w in res[i]], length[i]) for i in sorted(open_)]
    e = edges(spark.createDataFrame(rows, "log_id long, res array<string>, n_words int"), cfg.delta, "full", "exact")
    out = {i: {i} for i in open_}
    for r in e.select("src", "dst").toLocalIterator():
        out[r["src"]].add(r["dst"])
    return out


class Base:
    """What every run over the same lines begins with: the distinct lines with their forms, and their patterns."""

    def __init__(self, lines: DataFrame):
        distinct = distinct_lines(lines.drop("raw", "n_words"))
        self.distinct = stored(distinct.withColumn("form", form(F.col("words"))), "rounds-lines")
        # variable words of one shape are one pattern, whatever similarity the distances use
        self.table = stored(patterns(self.distinct.drop("weight"), "classed"), "rounds-patterns")
        self.n, self._local, self._classes = self.table.count(), None, None

    def local(self) -> dict[int, _Pattern]:
        """The patterns on the driver, for callers that have checked how many there are."""
        if self._local is None:
            rows = self.table.select("log_id", "words", "labels", "weight").collect()
            self._local = {r["log_id"]: _Pattern(r["log_id"], list(r["words"]), list(r["labels"]), r["weight"]) for r in rows}
        return self._local

    def compact(self) -> bool:
        """Whether predictions by form are the same for all lines of a class: the patterns' examples keep no variable word verbatim."""
        if choose(self.n)["greedy"].choice == "distributed":
            return False
        return not any(w == x and shape_of(w) != w for p in self.local().values() for w, x in zip(p.words, p.labels, strict=False))

    def classes(self) -> DataFrame:
        """The distinct lines by form, truth and length of text, n lines per row; asked for where compact() holds.

        Examples are patterns, so words of patterns stay as they are and no run tells lines of one class apart.
        The patterns' own lines, which may be labelled, are classes of their own.
        """
        if self._classes is None:
            pats = self.local()
            held = sorted({w for p in pats.values() for w in (*p.words, *p.labels) if shape_of(w) != w})
            key = F.zip_with("words", "form", lambda w, f: F.when(f.startswith(VARIABLE) & ~w.isin(held), f).otherwise(w)) if held else F.col("form")
            alone = F.when(F.col("log_id").isin(sorted(pats)), F.col("log_id")) if pats else F.lit(None).cast("long")
            rows = self.distinct.select("domain", "truth", key.alias("words"), line_length(F.col("words")).alias("length"), alone.alias("alone"), "log_id", "weight")
            self._classes = stored(_grouped(rows, "domain", "truth", "words", "length", "alone"), "rounds-classes")
            self._rows = _rows_of(self._classes)
        return self._classes

    def class_rows(self) -> list | None:
        """classes() on the driver, or None if they are too many."""
        self.classes()
        return self._rows


def run(lines: DataFrame, cfg: Config, final: bool = True, base: Base | None = None, compact: bool = False) -> Result:
    """lines: tokenised, with labels (the annotator's truth) and domain. base: Base(lines), if it is there already.
    compact: predictions that are alike may share a row, of n lines.

    Empty tables and budgets of 0 give an empty labelled set and predictions without examples.
    """
    spark = lines.sparkSession
    base = base or Base(lines)
    distinct, table = base.distinct, base.table
    decisions = choose(base.n, similarity=cfg.context.similarity)
    if decisions["greedy"].choice == "distributed":
        return _run_distributed(distinct, table, cfg, decisions, final)
    pats = base.local()  # size checked above
    labelled: list[Demo] = []
    left, open_, trace = cfg.budget, dict(pats), []
    seen, prev = [0], 0  # words known at the start of each round
    r = 0
    while left > 0 and open_ and (cfg.max_rounds is None or r < cfg.max_rounds):
        known = {w for d in labelled for w in d.words}
        if r == 0:
            b = min(left, cfg.start[0] if cfg.adaptive_budget else cfg.fixed)
            picks, cov = diverse(open_, b), None
        else:
            now = len(known)
            if not cfg.adaptive_budget:
                b = min(left, cfg.fixed)
            elif r < len(cfg.start):
                b = min(left, cfg.start[r])
            else:
                b = budgets.next_budget(prev, *budgets.compared([*seen, now], cfg.words_basis), left, cfg.rounding)
            seen.append(now)
            p = Predictor(cfg.model, cfg.context, labelled, r)
            c = {}
            for i, x in open_.items():
                ans = p.predict(i, x.words)[0]
                mean = sum(ans.probs) / len(ans.probs) if ans.probs else 0.0
                flag = int(not consistent(x.words, ans))
                c[i] = cfg.a * (1 - mean) + (1 - cfg.a) * flag if cfg.use_pc else 0.0
            lam = cfg.lam if cfg.use_rs and cfg.use_pc else 1.0 if cfg.use_pc else 0.0
            cover = covers_of(open_, known, cfg, spark) if cfg.use_rs else {i: {i} for i in open_}
            got = greedy_local(cover, c, b, lam, cfg.objective, {i: x.weight for i, x in open_.items()}, lazy=cfg.objective == "separable")
            picks = [g[1] for g in got]
            cov = got[-1][3] / max(1, sum(x.weight for x in open_.values())) if got else 0.0
        if not picks:
            break
        labelled += [Demo(i, tuple(pats[i].words), tuple(pats[i].labels)) for i in picks]
        for i in picks:
            open_.pop(i, None)
        prev = b
        if r or cfg.charge_init:
            left -= len(picks)
        words = {w for d in labelled for w in d.words}
        trace.append({"r": r, "budget": b, "spent": len(picks), "words_seen": len(words), "words_new": len(words - known), "open": len(open_), "coverage": cov})
        r += 1
    out = Result(labelled, trace, None, decisions)
    if final:
        out.predictions = predictions(base, cfg, labelled, compact)
    return out


def _run_distributed(distinct: DataFrame, table: DataFrame, cfg: Config, decisions: dict, final: bool) -> Result:
    """The same rounds where the patterns do not fit the driver: only picks, labels and counts reach it."""
    labelled: list[Demo] = []
    left, trace, prev, seen, r = cfg.budget, [], 0, [0], 0
    open_ = stored(table, "rounds-open")
    while left > 0 and (cfg.max_rounds is None or r < cfg.max_rounds):
        known = sorted({w for d in labelled for w in d.words})
        now, cov = len(known), None
        if r == 0:
            b = min(left, cfg.start[0] if cfg.adaptive_budget else cfg.fixed)
            picks = [g["id"] for g in dpp_map(mean_vectors(open_), b, "log_id", "v").orderBy("rank").collect()]  # b rows
        else:
            b = min(left, cfg.fixed) if not cfg.adaptive_budget else min(left, cfg.start[r]) if r < len(cfg.start) else budgets.next_budget(prev, *budgets.compared([*seen, now], cfg.words_basis), left, cfg.rounding)
            seen.append(now)
            member, e = _groups(open_, known, cfg)
            if cfg.use_pc:
                pred = predict(open_, cfg.model, cfg.context, labelled, r)
                c = pred.join(open_.select("log_id", "words"), "log_id").select("log_id", difficulty(mean_prob(F.col("probs")), inconsistent(F.col("words"), F.col("echo"), F.col("labels"), F.array(*map(F.lit, CANDIDATES))), cfg.a).alias("difficulty"))
            else:
                c = open_.select("log_id", F.lit(0.0).alias("difficulty"))
            lam = cfg.lam if cfg.use_rs and cfg.use_pc else 1.0 if cfg.use_pc else 0.0
            weight = stored(open_.select("log_id", "weight").join(member, "log_id").groupBy(F.col("grp").alias("dst")).agg(F.sum("weight").alias("w")), "rounds-weight")
            got = greedy(c.join(member, "log_id"), e, b, lam, cfg.objective, weight).orderBy("rank").collect()  # b rows
            picks = [g["log_id"] for g in got]
            cov = got[-1]["covered"] / max(1, weight.agg(F.sum("w")).first()[0] or 1) if got else 0.0
        rows = open_.filter(F.col("log_id").isin(picks)).select("log_id", "words", "labels").collect() if picks else []
        if not rows:
            break
        rows.sort(key=lambda x: picks.index(x["log_id"]))
        labelled += [Demo(x["log_id"], tuple(x["words"]), tuple(x["labels"])) for x in rows]
        open_ = open_.filter(~F.col("log_id").isin(picks))
        open_ = stored(open_, "rounds-open")
        prev = b
        if r or cfg.charge_init:
            left -= len(rows)
        words = {w for d in labelled for w in d.words}
        trace.append({"r": r, "budget": b, "spent": len(rows), "words_seen": len(words), "words_new": len(words) - now, "open": open_.count(), "coverage": cov})
        r += 1
    return Result(labelled, trace, final_pass(distinct, cfg, labelled) if final else None, decisions)


def predictions(base: Base, cfg: Config, labelled: list[Demo], compact: bool = False) -> DataFrame:
    """final_pass(), compact where predictions follow from the form, and in batches, without probabilities, where words are alike by vectors."""
    if compact and in_batches(cfg.model, cfg.context, labelled):
        return final_pass(base.distinct, cfg, labelled, batches=True)
    if not (compact and by_form(cfg.model, cfg.context) and base.compact()):
        return final_pass(base.distinct, cfg, labelled)
    if cfg.context.mode == "topk":
        return _few_or_many(_by_examples(base, cfg, labelled), None, cfg, labelled)
    table = base.classes()
    return _few_or_many(table, base.class_rows(), cfg, labelled)


def _rows_of(table: DataFrame) -> list | None:
    """The rows of a table, if they are few enough for the driver."""
    rows = table.limit(LOCAL_CLASSES + 1).collect()
    return rows if len(rows) <= LOCAL_CLASSES else None


def _few_or_many(table: DataFrame, rows: list | None, cfg: Config, labelled: list[Demo]) -> DataFrame:
    if rows is None and cfg.context.mode == "topk":
        rows = _rows_of(table)
    if rows is None:
        return final_pass(table, cfg, labelled)
    known, out = {d.id for d in labelled}, []
    for r, (labels, chosen, tokens) in zip(rows, answer_rows(rows, cfg.model, cfg.context, labelled, 99), strict=True):
        own = r["log_id"] in known
        out.append((r["log_id"], r["domain"], r["truth"], r["words"], r["labels"], r["weight"], r["n"], labels, r["words"], chosen, tokens, own, r["truth"] if own else " ".join(labels)))
    names = [f.name for f in _PREDICTED]
    cols = list(zip(*out, strict=True)) or [()] * len(names)
    return table.sparkSession.createDataFrame(pa.Table.from_arrays([pa.array(c, f.type) for c, f in zip(cols, _PREDICTED, strict=True)], schema=_PREDICTED))


_TEXTS = pa.list_(pa.string())
_PREDICTED = pa.schema(
    [("log_id", pa.int64()), ("domain", pa.string()), ("truth", pa.string()), ("words", _TEXTS), ("true_labels", _TEXTS), ("weight", pa.int64()), ("n", pa.int64())]
    + [("labels", _TEXTS), ("echo", _TEXTS), ("demos", pa.list_(pa.int64())), ("tokens", pa.int64()), ("labelled", pa.bool_()), ("pred", pa.string())]
)


def _by_examples(base: Base, cfg: Config, labelled: list[Demo]) -> DataFrame:
    """The distinct lines by their nearest examples, form, truth and length of text, n lines per row."""
    of = {d.id: sorted(w for w in known_words([d]) if shape_of(w) != w) for d in labelled}
    texts = lambda ws: F.array(*map(F.lit, ws)).cast("array<string>")
    held = F.create_map(*(x for i, ws in of.items() for x in (F.lit(i).cast("long"), texts(ws)))) if of else None
    near = nearest_examples(base.distinct.select("log_id", "domain", "truth", "words", "form", "weight"), cfg.context, labelled)
    # other words of a line than those of its own examples follow from its form
    known = F.flatten(F.transform("demos", lambda d: F.element_at(held, d))) if of else texts([])
    key = F.zip_with("words", "form", lambda w, f: F.when(f.startswith(VARIABLE) & F.array_contains(F.col("_known"), w), w).otherwise(f))
    alone = F.when(F.col("log_id").isin(sorted(of)), F.col("log_id")) if of else F.lit(None).cast("long")
    rows = near.withColumn("_known", known).select("domain", "truth", key.alias("words"), line_length(F.col("words")).alias("length"), alone.alias("alone"), "demos", "log_id", "weight")
    return stored(_grouped(rows, "domain", "truth", "words", "length", "alone", "demos"), "rounds-examples")


def _grouped(rows: DataFrame, *keys: str) -> DataFrame:
    return (
        rows.groupBy(*keys).agg(F.min("log_id").alias("log_id"), F.sum("weight").alias("weight"), F.count("*").alias("n")).drop("alone")
        .withColumn("form", form(F.col("words"))).withColumn("labels", words_of(F.col("truth")))
    )


def final_pass(distinct: DataFrame, cfg: Config, labelled: list[Demo], batches: bool = False) -> DataFrame:
    """Every distinct line's prediction beside its truth; marks which lines were labelled."""
    known = [d.id for d in labelled]
    own = distinct.select("log_id", "domain", "truth", "words", F.col("labels").alias("true_labels"), "weight", "form", *(c for c in ("n", "length", "demos") if c in distinct.columns))
    is_known = F.col("log_id").isin(known) if known else F.lit(False)
    asked = answered_batches(own, cfg.model, cfg.context, labelled, 99) if batches else templates(answered(own, cfg.model, cfg.context, labelled, 99))
    return asked.withColumn("labelled", is_known).withColumn("pred", F.when(F.col("labelled"), F.col("truth")).otherwise(F.col("pred")))


def still_open(pred: DataFrame, cut: float) -> DataFrame:
    """Lines whose mean probability is below the cut stay for the next round."""
    return pred.filter(mean_prob(F.col("probs")) < cut)


def variant(cfg: Config, name: str) -> Config:
    """FULL and its ablations."""
    return {
        "FULL": cfg,
        "-SED": replace(cfg, distance="cosine"),
        "-RS": replace(cfg, use_rs=False),
        "-PC": replace(cfg, use_pc=False),
        "-AD": replace(cfg, context=replace(cfg.context, mode="topk")),
        "-AB": replace(cfg, adaptive_budget=False),
    }[name]
