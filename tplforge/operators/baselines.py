"""Baselines: parse tree, few-label tagger, one round, fixed rounds, no examples, random choice."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tplforge.functions.confidence import mean_prob
from tplforge.functions.measures import lines_of
from tplforge.functions.words import SHAPES, classed, classes_of, vector
from tplforge.functions.words import words as words_of
from tplforge.operators.context import Demo
from tplforge.operators.models import Context, ContextTagger, Predictor, ShapeOnly, predict
from tplforge.operators.represent import knn_edges
from tplforge.operators.rounds import Base, Config, Result, _Pattern, diverse, final_pass, mean_vectors, predictions
from tplforge.operators.select import dpp_map, greedy, greedy_local
from tplforge.plans.choose import LOCAL_PATTERNS
from tplforge.session import stored

WILD = "<*>"
#: what a line is worth to the fixed-size baseline when it is covered again
DECAY = 0.5


def masked(words):
    """Words with digits become a wildcard."""
    return F.transform(words, lambda w: F.when(w.rlike("[0-9]"), WILD).otherwise(w))


def mask_group(lines: DataFrame) -> DataFrame:
    """The simplest heuristic: lines equal after masking are one template."""
    return lines.withColumn("pred", F.array_join(masked(F.col("words")), " "))


def mask_count(lines: DataFrame) -> DataFrame:
    """Lines by masked words and truth: the least log_id, and how many (n). The heuristics tell no more of a line."""
    got = lines.groupBy("domain", masked(F.col("words")).alias("words"), "truth").agg(F.min("log_id").alias("log_id"), F.count("*").alias("n"))
    return stored(got.withColumn("labels", words_of(F.col("truth"))), "tree-lines")


class ParseTree:
    """Groups of one leaf: a line joins the group that agrees in the largest share of places, or opens one."""

    def __init__(self, sim: float):
        self.sim, self.groups = sim, []

    def add(self, words: list[str]) -> int:
        best, most = -1, -1.0
        for g, t in enumerate(self.groups):
            same = sum(a == b and a != WILD for a, b in zip(t, words, strict=True)) / max(1, len(words))
            if same > most:
                best, most = g, same
        if best >= 0 and most >= self.sim:
            self.groups[best] = [a if a == b else WILD for a, b in zip(self.groups[best], words, strict=True)]
            return best
        self.groups.append(list(words))
        return len(self.groups) - 1


def parse_tree(lines: DataFrame, depth: int = 4, sim: float = 0.5, fanout: int = 100) -> DataFrame:
    """Fixed-depth tree: by word count, then the first depth-2 words (masked), then by agreement.

    Lines are taken in log_id order. Equal masked lines meet the same group, so only distinct
    masked lines are grouped: a leaf holds patterns, not lines. Below a word count there are at most `fanout`
    leaves, in the order in which their first words were met; later ones share one leaf.
    """
    shown = lines.withColumn("masked", masked(F.col("words")))
    pats = shown.groupBy("domain", "masked").agg(F.min("log_id").alias("first")).withColumn("n", F.size("masked")).withColumn("head", F.array_join(F.slice("masked", 1, max(1, depth - 2)), " "))

    def leaf(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("first")
        tree = ParseTree(sim)
        group = [tree.add(list(w)) for w in pdf.masked]
        return pd.DataFrame({"domain": pdf.domain, "masked": pdf.masked, "pred": [" ".join(tree.groups[g]) for g in group]})

    pats = stored(pats, "tree-patterns")
    met = pats.groupBy("domain", "n", "head").agg(F.min("first").alias("met")).withColumn("k", F.row_number().over(W.partitionBy("domain", "n").orderBy("met"))).filter(F.col("k") <= fanout)
    pats = pats.join(met.select("domain", "n", "head", "k"), ["domain", "n", "head"], "left").withColumn("head", F.when(F.col("k").isNull(), WILD).otherwise(F.col("head"))).drop("k")
    found = pats.groupBy("domain", "n", "head").applyInPandas(leaf, "domain string, masked array<string>, pred string")
    return shown.join(found, ["domain", "masked"]).drop("masked")


def as_typed(pred: DataFrame) -> DataFrame:
    """Wildcards as the majority type of the true labels per predicted group and place, so that untyped methods can be scored."""
    lists = pred.groupBy("domain", "pred", "labels").agg(F.sum(lines_of(pred)).alias("n"))
    place = lists.select("domain", "pred", "n", F.posexplode("labels").alias("pos", "label"))
    top = place.filter(F.col("label").startswith("[")).groupBy("domain", "pred", "pos", "label").agg(F.sum("n").alias("n"))
    best = top.groupBy("domain", "pred", "pos").agg(F.max_by("label", F.struct("n", "label")).alias("label")).groupBy("domain", "pred").agg(F.map_from_entries(F.collect_list(F.struct("pos", "label"))).alias("types"))
    joined = pred.join(best, ["domain", "pred"], "left")
    typed = F.transform(F.split("pred", " "), lambda w, i: F.when(w == WILD, F.coalesce(F.try_element_at("types", i), F.lit(WILD))).otherwise(w))
    return joined.withColumn("group", F.col("pred")).withColumn("pred", F.array_join(typed, " ")).drop("types")


def _pattern_table(lines: DataFrame, base: Base | None = None) -> tuple[DataFrame, DataFrame, dict[int, _Pattern] | None]:
    """Distinct lines, their patterns, and these once more on the driver if they fit it."""
    base = base or Base(lines)
    return base.distinct, base.table, None if base.n > LOCAL_PATTERNS else base.local()


def _demos(pats: dict[int, _Pattern], picks: list[int]) -> list[Demo]:
    return [Demo(i, tuple(pats[i].words), tuple(pats[i].labels)) for i in picks]


def _rows(table: DataFrame, picks: list[int]) -> list[Demo]:
    rows = {r["log_id"]: r for r in table.filter(F.col("log_id").isin(picks)).select("log_id", "words", "labels").collect()} if picks else {}
    return [Demo(i, tuple(rows[i]["words"]), tuple(rows[i]["labels"])) for i in picks]


def diverse_start(lines: DataFrame, k: int, base: Base | None = None) -> tuple[DataFrame, list[Demo]]:
    """Distinct lines and k diverse patterns with their labels."""
    distinct, table, pats = _pattern_table(lines, base)
    if pats is not None:
        return distinct, _demos(pats, diverse(pats, k))
    return distinct, _rows(table, _diverse_ids(table, k))


def _diverse_ids(table: DataFrame, k: int) -> list[int]:
    return [r["id"] for r in dpp_map(mean_vectors(table), k, "log_id", "v").orderBy("rank").collect()]  # k rows


def _hard_picks(open_: DataFrame, cfg: Config, labelled: list[Demo], rnd: int, b: int, neighbours: int, cut: float = 0.3) -> list[int]:
    """A round of multi_fixed where the patterns do not fit the driver."""
    sure = stored(predict(open_, cfg.model, cfg.context, labelled, rnd).select("log_id", mean_prob(F.col("probs")).alias("sure")), "baseline-sure")
    hard = stored(sure.orderBy("sure", "log_id").limit(max(1, (open_.count() + 1) // 2)), "baseline-hard")
    v = mean_vectors(open_.join(hard.select("log_id"), "log_id", "left_semi"))
    near = knn_edges(v, neighbours, "log_id", "v").filter(F.col("cos") >= cut).select("src", "dst")
    own = hard.select(F.col("log_id").alias("src"), F.col("log_id").alias("dst"))
    got = greedy(hard.select("log_id", (1 - F.col("sure")).alias("difficulty")), near.union(own), b, 0.1, decay=DECAY)
    return [r["log_id"] for r in got.orderBy("rank").collect()]  # b rows


def _nearest(words: dict[int, list[str]], m: int, cut: float = 0.3) -> dict[int, set[int]]:
    """Each line and the m others of highest cosine (6 digits) of at least the cut; ties go to the lower id."""
    ids = np.array(sorted(words))
    v = np.array([np.mean([vector(w) for w in words[i]], axis=0) if words[i] else np.zeros(64) for i in ids.tolist()]).reshape(-1, 64)
    n = np.linalg.norm(v, axis=1, keepdims=True)
    v = v / np.where(n > 0, n, 1)
    out = {}
    for k, i in enumerate(ids.tolist()):
        s = np.round(v @ v[k], 6)
        s[k] = -np.inf
        top = np.lexsort((ids, -s))[:m]
        out[i] = {i} | set(ids[top[s[top] >= cut]].tolist())
    return out


def single_round(lines: DataFrame, budget: int, k: int = 5, model: ContextTagger | None = None, base: Base | None = None, compact: bool = False) -> Result:
    """The whole budget on one diverse sample, then k similar examples per line."""
    base = base or Base(lines)
    _, labelled = diverse_start(lines, budget, base)
    cfg = Config(budget=budget, context=Context(mode="topk", k=k), model=model or ContextTagger())
    return Result(labelled, [{"r": 0, "budget": budget, "spent": len(labelled)}], predictions(base, cfg, labelled, compact))


def multi_fixed(lines: DataFrame, budget: int, per_round: int, k: int = 5, neighbours: int = 5, model: ContextTagger | None = None, base: Base | None = None, compact: bool = False) -> Result:
    """Rounds of one size: hard lines (the less sure half) covered by their nearest neighbours.

    A line that is covered already counts half as much each time it is covered again.
    """
    base = base or Base(lines)
    _, table, pats = _pattern_table(lines, base)
    cfg = Config(budget=budget, context=Context(mode="topk", k=k), model=model or ContextTagger())
    labelled, left, trace = [], budget, []
    while pats is None and left > 0:
        b = min(left, per_round)
        picks = _hard_picks(table, cfg, labelled, len(trace), b, neighbours) if labelled else _diverse_ids(table, b)
        if not picks:
            break
        labelled += _rows(table, picks)
        table = stored(table.filter(~F.col("log_id").isin(picks)), "baseline-patterns")
        left -= len(picks)
        trace.append({"r": len(trace), "budget": b, "spent": len(picks)})
    open_ = dict(pats or {})
    while left > 0 and open_:
        b = min(left, per_round)
        if not labelled:
            picks = diverse(open_, b)
        else:
            p = Predictor(cfg.model, cfg.context, labelled, len(trace))
            sure = {i: (sum(a.probs) / len(a.probs) if a.probs else 0.0) for i, x in open_.items() for a in [p.predict(i, x.words)[0]]}
            hard = sorted(open_, key=lambda i: (sure[i], i))[: max(1, (len(open_) + 1) // 2)]
            near = _nearest({i: open_[i].words for i in hard}, neighbours)
            picks = [g[1] for g in greedy_local(near, {i: 1 - sure[i] for i in hard}, b, 0.1, decay=DECAY)]
        labelled += _demos(pats, picks)
        for i in picks:
            open_.pop(i)
        left -= len(picks)
        trace.append({"r": len(trace), "budget": b, "spent": len(picks)})
    return Result(labelled, trace, predictions(base, cfg, labelled, compact))


def zero_shot(lines: DataFrame, misread: int = 0) -> Result:
    distinct = Base(lines).distinct
    return Result([], [], final_pass(distinct, Config(context=Context(mode="none"), model=ShapeOnly(misread=misread)), []))


def random_pick(lines: DataFrame, budget: int, model: ContextTagger | None = None) -> Result:
    distinct = Base(lines).distinct
    rows = distinct.orderBy(F.xxhash64("log_id"), "log_id").limit(budget).select("log_id", "words", "labels").collect()
    labelled = [Demo(r["log_id"], tuple(r["words"]), tuple(r["labels"])) for r in rows]
    return Result(labelled, [], final_pass(distinct, Config(model=model or ContextTagger()), labelled))


def token_tagger(lines: DataFrame, budget: int, base: Base | None = None, compact: bool = False) -> Result:
    """A word classifier on hashed features of shape and neighbours, trained on a diverse sample; stands in for a tuned neural tagger."""
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import FeatureHasher, IndexToString, StringIndexer

    base = base or Base(lines)
    distinct, labelled = diverse_start(lines, budget, base)
    known = [d.id for d in labelled]

    def word_rows(df: DataFrame) -> DataFrame:
        shown = df.withColumn("sh", classed(F.col("words")))
        x = shown.select("log_id", "words", "sh", "labels", F.posexplode("words").alias("pos", "w"))
        at = lambda c, d: F.coalesce(F.try_element_at(c, F.col("pos") + d), F.lit("<none>"))
        before = F.when(F.col("pos") > 0, at("sh", 0)).otherwise("<none>")
        label = F.element_at("labels", F.col("pos") + 1)
        return x.select("log_id", "pos", "w", at("sh", 1).alias("shape"), before.alias("left"), at("sh", 2).alias("right"), F.when(label == F.col("w"), "KEEP").otherwise(label).alias("role"))

    # as many rows as labels: one task, and no pass over the lines
    shown = [(d.id, list(d.words), list(d.labels)) for d in labelled]
    train = word_rows(lines.sparkSession.createDataFrame(shown, "log_id long, words array<string>, labels array<string>").coalesce(1)).persist()
    hasher = FeatureHasher(inputCols=["shape", "left", "right"], outputCol="features", numFeatures=1 << 12)
    index = StringIndexer(inputCol="role", outputCol="label", handleInvalid="skip").fit(train)
    fitted = Pipeline(stages=[hasher, LogisticRegression(maxIter=30, regParam=1e-3)]).fit(index.transform(train))
    # roles follow shapes alone, so they are worked out once per list of shapes
    few = compact and base.compact()
    shaped = (base.classes() if few else distinct).withColumn("sh", classes_of(F.col("form")))
    each = shaped.select("sh").distinct().withColumn("x", F.explode(F.transform("sh", lambda w, i: F.struct(i.alias("pos"), w.alias("shape"), F.when(i > 0, F.get("sh", i - 1)).otherwise("<none>").alias("left"), F.coalesce(F.get("sh", i + 1), F.lit("<none>")).alias("right"))))).select("sh", "x.*")
    tagged = IndexToString(inputCol="prediction", outputCol="role", labels=index.labels).transform(fitted.transform(each))
    roles = stored(tagged.groupBy("sh").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "role"))), lambda v: v["role"]).alias("roles")), "tagger-roles")
    train.unpersist()
    if few and not roles.filter(F.exists(F.zip_with("sh", "roles", lambda s, r: s.isin([n for n, _ in SHAPES]) & (r == "KEEP")), lambda x: x)).isEmpty():
        # a variable word that is kept is told apart from its class
        shaped = distinct.withColumn("sh", classes_of(F.col("form")))
    own = shaped.select("log_id", "domain", "truth", "words", F.col("labels").alias("true_labels"), "weight", "sh", *(c for c in ("n",) if c in shaped.columns)).join(roles, "sh")
    out = own.withColumn("pl", F.zip_with("roles", "words", lambda r, w: F.when(r == "KEEP", w).otherwise(r))).drop("sh", "roles").withColumn("pred", F.array_join("pl", " ")).withColumnRenamed("pl", "labels")
    out = out.withColumn("echo", F.col("words")).withColumn("demos", F.array().cast("array<long>")).withColumn("tokens", F.lit(0).cast("long")).withColumn("labelled", F.col("log_id").isin(known))
    return Result(labelled, [], out.withColumn("pred", F.when(F.col("labelled"), F.col("truth")).otherwise(F.col("pred"))))
