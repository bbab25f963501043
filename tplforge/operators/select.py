"""Choosing lines to label: the set objective and its greedy maximisers, and a diverse start.

`separable`: (1-lam) * covered/u + lam * sum of difficulties (diminishing gains).
`as_printed`: the coverage term counts once per chosen line.
Ties always go to the lower log_id. The denominator u is that of the round's start.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tplforge.schema import PICK
from tplforge.session import stored

_EPS = 1e-12


def objective(chosen: Iterable[int], covers: dict[int, set[int]], c: dict[int, float], lam: float, u: int, form: str = "separable") -> float:
    chosen = list(chosen)
    cov = len(set().union(*(covers.get(i, {i}) for i in chosen))) / u if chosen else 0.0
    return (len(chosen) if form == "as_printed" else 1) * (1 - lam) * cov + lam * sum(c[i] for i in chosen)


def greedy_local(covers: dict[int, set[int]], c: dict[int, float], b: int, lam: float, form: str = "separable", weight: dict[int, int] | None = None, lazy: bool = True, decay: float = 0.0) -> list[tuple[int, int, float, int, float]]:
    """Picks (rank, id, gain, covered so far, difficulty) for lines that fit the driver.

    weight: lines per pattern; coverage then counts lines. lazy: keeps stale gains in a heap
    (only where gains cannot grow). decay: what a line that is covered is still worth when it is
    covered again, as a share of the time before (separable form).
    """
    w = weight or dict.fromkeys(c, 1)
    u = sum(w[i] for i in c) or 1
    size = lambda s: sum(w.get(i, 1) for i in s)
    covered: set[int] = set()
    times: dict[int, int] = {}
    left, out = set(c), []

    def gain(i: int) -> float:
        if decay:
            return (1 - lam) * sum(w.get(j, 1) * decay ** times.get(j, 0) for j in sorted(covers.get(i, {i}))) / u + lam * c[i]
        new = size(covers.get(i, {i}) - covered) / u
        if form == "as_printed":
            k = len(out)
            return (1 - lam) * ((k + 1) * (size(covered) / u + new) - k * size(covered) / u) + lam * c[i]
        return (1 - lam) * new + lam * c[i]

    heap = [(-round(gain(i), 12), i) for i in left] if lazy and form == "separable" else []
    heapq.heapify(heap)
    while left and len(out) < b:
        if heap:
            while True:
                _, i = heapq.heappop(heap)
                g = gain(i)
                if not heap or (-round(g, 12), i) <= heap[0]:
                    break
                heapq.heappush(heap, (-round(g, 12), i))
        else:
            i = min(left, key=lambda j: (-round(gain(j), 12), j))
            g = gain(i)
        left.discard(i)
        covered |= covers.get(i, {i})
        for j in covers.get(i, {i}) if decay else ():
            times[j] = times.get(j, 0) + 1
        out.append((len(out) + 1, i, g, size(covered), c[i]))
    return out


def greedy(cands: DataFrame, edges: DataFrame, b: int, lam: float, form: str = "separable", weight: DataFrame | None = None, decay: float = 0.0, eps: float | None = None, seed: int = 7) -> DataFrame:
    """The distributed form: cands(log_id, difficulty), edges(src, dst).

    weight(dst, w): lines that a covered one counts for. Where cands has a column grp, edges and weights
    are those of groups, whose members stand for the same lines. decay: as in greedy_local. eps: each pick looks only
    at (u/b) ln(1/eps) of the rest, by the hash of seed, pick and id (the sampled form).

    A pick changes only the gains of lines that stand for newly covered ones, so each round joins the
    delta and not all edges. Edges and the state of each pick are stored tables: plans stay small.
    Driver trips: one row per pick.
    """
    spark = cands.sparkSession
    edges = edges.select("src", "dst")
    edges = stored(edges.withColumn("w", F.lit(1)) if weight is None else edges.join(weight.select("dst", "w"), "dst").select("src", "dst", "w"), "greedy-edges")
    cands = cands if "grp" in cands.columns else cands.withColumn("grp", F.col("log_id"))
    fresh = edges.groupBy(F.col("src").alias("grp")).agg(F.sum("w").alias("fresh"))
    state = stored(cands.join(fresh, "grp", "left").select("log_id", "grp", "difficulty", F.coalesce("fresh", F.lit(0)).alias("fresh")), "greedy-state")
    n = state.count()
    u = n if weight is None else weight.agg(F.sum("w")).first()[0] or 1
    covered, picks, done = None, [], 0
    for k in range(min(b, n)):
        mult, base = (k + 1, done) if form == "as_printed" else (1, 0)
        value = F.lit(1 - lam) * (mult * F.col("fresh") + base) / F.lit(float(u)) + F.lit(lam) * F.col("difficulty")
        seen = state if eps is None else state.orderBy(F.xxhash64(F.lit(seed), F.lit(k), "log_id"), "log_id").limit(max(1, math.ceil(n / b * math.log(1 / eps))))
        top = seen.select("log_id", "grp", "difficulty", "fresh", F.round(value, 12).alias("gain")).orderBy(F.desc("gain"), "log_id").first()
        new = edges.filter(F.col("src") == top["grp"]).select("dst", "w").distinct()
        if decay:
            # every line that the pick covers is worth less from now on, by how often it was covered
            seen = new.withColumn("times", F.lit(0)) if covered is None else new.join(covered, "dst", "left").withColumn("times", F.coalesce("times", F.lit(0)))
            new = stored(seen, "greedy-new")
            done += new.filter("times = 0").agg(F.sum("w")).first()[0] or 0
        else:
            done += top["fresh"]
        picks.append((k + 1, top["log_id"], float(top["gain"]), int(done), float(top["difficulty"])))
        if k + 1 == min(b, n):
            break
        if decay:
            lost = new.select("dst", ((1 - decay) * F.pow(F.lit(decay), F.col("times"))).alias("lost"))
            less = edges.join(lost, "dst").groupBy(F.col("src").alias("grp")).agg(F.sum(F.col("w") * F.col("lost")).alias("gone"))
            again = new.select("dst", (F.col("times") + 1).alias("times"))
            covered = again if covered is None else stored(covered.join(again, "dst", "left_anti").union(again), "greedy-covered")
            state = _after(state, top, less)
            continue
        new = stored(new.select("dst") if covered is None else new.select("dst").join(covered, "dst", "left_anti"), "greedy-new")
        less = edges.join(new, "dst", "left_semi").groupBy(F.col("src").alias("grp")).agg(F.sum("w").alias("gone"))
        state = _after(state, top, less)
        covered = new if covered is None else covered.union(new)
    return spark.createDataFrame(picks, PICK)


def _after(state: DataFrame, top, less: DataFrame) -> DataFrame:
    """The candidates after a pick, with what they lose by it."""
    rest = state.filter(F.col("log_id") != top["log_id"]).join(less, "grp", "left")
    return stored(rest.select("log_id", "grp", "difficulty", (F.col("fresh") - F.coalesce("gone", F.lit(0))).alias("fresh")), "greedy-state")


def greedy_sampled(covers: dict[int, set[int]], c: dict[int, float], b: int, lam: float, eps: float = 0.1, seed: int = 7) -> list[tuple[int, int, float, int, float]]:
    """Each pick looks at a random (u/b)ln(1/eps) of the rest; separable objective."""
    rng, u = np.random.default_rng(seed), max(len(c), 1)
    take = max(1, int(np.ceil(u / max(b, 1) * np.log(1 / eps))))
    left, covered, out = sorted(c), set(), []
    while left and len(out) < b:
        look = rng.choice(len(left), min(take, len(left)), replace=False)
        gain = lambda i: (1 - lam) * len(covers.get(i, {i}) - covered) / u + lam * c[i]
        i = min((left[j] for j in look), key=lambda x: (-gain(x), x))
        g = gain(i)
        left.remove(i)
        covered |= covers.get(i, {i})
        out.append((len(out) + 1, i, g, len(covered), c[i]))
    return out


def greedy_sharded(cands: DataFrame, edges: DataFrame, b: int, lam: float, parts: int = 4) -> DataFrame:
    """b picks per shard of lines, then b of those: two levels, weaker bound, no pick-by-pick jobs."""
    u = cands.count()
    rows = cands.join(edges.groupBy(F.col("src").alias("log_id")).agg(F.collect_set("dst").alias("covers")), "log_id", "left").withColumn("shard", F.pmod(F.xxhash64("log_id"), F.lit(parts)))

    def shard(pdf: pd.DataFrame) -> pd.DataFrame:
        covers = {i: set(v) if v is not None else {i} for i, v in zip(pdf.log_id, pdf.covers, strict=True)}
        got = [x[1] for x in greedy_local(covers, dict(zip(pdf.log_id, pdf.difficulty, strict=True)), b, lam)]
        return pdf[pdf.log_id.isin(got)][["log_id", "difficulty", "covers"]]

    short = rows.groupBy("shard").applyInPandas(shard, "log_id long, difficulty double, covers array<long>").collect()  # at most b rows per shard
    c = {r["log_id"]: r["difficulty"] for r in short}
    covers = {r["log_id"]: set(r["covers"] or [r["log_id"]]) for r in short}
    picks, covered = [], set()
    left = set(c)
    while left and len(picks) < b:
        i = min(left, key=lambda x: (-round((1 - lam) * len(covers[x] - covered) / u + lam * c[x], 12), x))
        g = (1 - lam) * len(covers[i] - covered) / u + lam * c[i]
        covered |= covers[i]
        left.discard(i)
        picks.append((len(picks) + 1, int(i), float(g), len(covered), float(c[i])))
    return cands.sparkSession.createDataFrame(picks, PICK)


def top_difficulty(cands: DataFrame, b: int) -> DataFrame:
    """lam = 1: the b hardest."""
    return cands.orderBy(F.desc("difficulty"), "log_id").limit(b)


def dpp_local(ids: list[int], vectors: np.ndarray, k: int, ridge: float = 1e-6) -> list[int]:
    """Greedy maximum of the determinant of the chosen vectors' cosine matrix."""
    n = len(ids)
    if not n:
        return []
    norm = np.linalg.norm(vectors, axis=1, keepdims=True)
    v = vectors / np.where(norm > 0, norm, 1)
    d = (v * v).sum(axis=1) + ridge
    e = np.zeros((min(k, n), n))
    free, out = np.ones(n, bool), []
    order = np.argsort(ids)
    for t in range(min(k, n)):
        best = d[free].max()
        if best < 1e-10:
            out += [j for j in order if free[j]][: min(k, n) - len(out)]
            break
        j = next(int(i) for i in order if free[i] and d[i] >= best - _EPS)
        row = (v @ v[j] + ridge * (np.arange(n) == j) - e[:t].T @ e[:t, j]) / np.sqrt(max(d[j], _EPS))
        e[t] = row
        d = d - row * row
        free[j] = False
        out.append(j)
    return [ids[j] for j in out]


def dpp_map(rows: DataFrame, k: int, id_col: str = "vec_id", vec: str = "embedding", ridge: float = 1e-6) -> DataFrame:
    """The distributed form: one driver trip per pick, each row keeps its own coefficients."""
    spark = rows.sparkSession
    unit = F.sqrt(F.aggregate(F.col("v"), F.lit(0.0), lambda s, x: s + x * x))
    state = rows.select(F.col(id_col).alias("id"), F.transform(F.col(vec), lambda x: x.cast("double")).alias("v")).withColumn("n", unit).withColumn("v", F.transform("v", lambda x: F.when(F.col("n") > 0, x / F.col("n")).otherwise(x)))
    state = state.withColumn("d", F.when(F.col("n") > 0, 1.0).otherwise(0.0) + ridge).withColumn("e", F.array().cast("array<double>")).drop("n")
    state = stored(state, "dpp-state")
    picks = []
    for t in range(min(k, state.count())):
        top = state.orderBy(F.desc(F.round("d", 12)), "id").first()
        if top["d"] < 1e-10:
            rest = state.orderBy("id").limit(k - len(picks)).collect()
            picks += [(len(picks) + i + 1, r["id"]) for i, r in enumerate(rest)]
            break
        picks.append((t + 1, top["id"]))
        pv, pe = F.array(*map(F.lit, top["v"])), F.array(*map(F.lit, top["e"])).cast("array<double>")
        dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
        new = (dot(F.col("v"), pv) - dot(F.col("e"), pe)) / float(np.sqrt(top["d"]))
        rest = state.filter(F.col("id") != top["id"]).withColumn("c", new)
        state = stored(rest.select("id", "v", (F.col("d") - F.col("c") * F.col("c")).alias("d"), F.concat("e", F.array("c")).alias("e")), "dpp-state")
    return spark.createDataFrame(picks, "rank int, id long")
