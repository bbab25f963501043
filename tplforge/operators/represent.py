"""Which lines stand for which: pattern compression, candidate pairs, edges.

Line a stands for line b when their edit distance is at most delta times the
shorter length. Lines with the same residual and length are one pattern. For
similarity that is an equivalence, pairs are found without a cross product: a
pair within the bound either is so short that any pair of its sizes passes, or
shares one of its rarest words (prefix filter on the words' frequency order).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tplforge.functions.distance import sed, sed_arrow, sed_within, sed_words
from tplforge.functions.words import Similarity, classed, classes_of
from tplforge.session import stored


def distinct_lines(lines: DataFrame) -> DataFrame:
    """One row per distinct line: least log_id, its truth, how many there are."""
    keep = [c for c in ("domain", "raw", "truth", "n_words", "labels") if c in lines.columns]
    # grouped as one text: a sort of texts is far cheaper than one of arrays; no word holds a line break
    one = lines.select(F.array_join("words", "\n").alias("_key"), F.size("words").alias("_n"), "log_id", *keep)
    got = one.groupBy("_key", "_n").agg(F.min("log_id").alias("log_id"), F.count("*").alias("weight"), *(F.min_by(c, "log_id").alias(c) for c in keep))
    return got.select(F.when(F.col("_n") == 0, F.array().cast("array<string>")).otherwise(F.split("_key", "\n")).alias("words"), "log_id", "weight", *keep)


def patterns(lines: DataFrame, similarity: str = "classed", residual: str | None = None) -> DataFrame:
    """log_id (least), words (of that line), res, n_words, weight per distinct (residual, length)."""
    arr = F.col(residual or "words")
    key = (classes_of(F.col("form")) if residual is None and "form" in lines.columns else classed(arr)) if similarity == "classed" else arr
    keep = [c for c in ("domain", "truth", "labels") if c in lines.columns]
    return (
        lines.withColumn("key", key)
        .groupBy("key", F.size("words").alias("n_words"))
        .agg(F.min("log_id").alias("log_id"), F.min_by("words", "log_id").alias("words"), F.count("*").alias("weight"), *(F.min_by(c, "log_id").alias(c) for c in keep))
        .withColumnRenamed("key", "res")
    )


def _sides(pats: DataFrame, basis: str) -> DataFrame:
    length = F.col("n_words") if basis == "full" else F.size("res")
    return pats.select("log_id", "res", F.size("res").alias("p"), length.alias("len"))


def _pair(left: DataFrame, right: DataFrame, on: list[str]) -> DataFrame:
    r = right.select(*(F.col(c).alias(c if c in on else f"{c}_b") for c in right.columns))
    joined = left.join(r, on) if on else left.crossJoin(r)
    return joined.filter(F.col("log_id") < F.col("log_id_b"))


def _free_sizes(side: DataFrame, delta: float) -> DataFrame:
    """p, len, n and p_b, len_b: cells of sizes all of whose pairs are within the bound, whatever the words are.

    There are as many cells as there are lengths of lines and of their residuals, not lines.
    """
    cells = side.groupBy("p", "len").agg(F.count("*").alias("n"))
    other = cells.select(F.col("p").alias("p_b"), F.col("len").alias("len_b"), F.col("n").alias("n_b"))
    return cells.crossJoin(other).filter(F.greatest("p", "p_b") <= F.lit(delta) * F.least("len", "len_b"))


def _sharing(side: DataFrame, delta: float) -> DataFrame:
    """Pairs log_id < log_id_b that share a word among the rarest p - need + 1 of each, counting the k-th copy of a word as its own word."""
    numbered = side.select("log_id", "res", "p", "len", F.posexplode("res").alias("pos", "word")).withColumn(
        "copy", F.row_number().over(W.partitionBy("log_id", "word").orderBy("pos"))
    )
    ranked = numbered.join(numbered.groupBy("word", "copy").agg(F.count("*").alias("df")), ["word", "copy"])
    order = F.array_sort(F.collect_list(F.struct("df", "word", "copy")))
    need = F.greatest(F.lit(1), F.ceil(F.col("p") - F.lit(delta) * F.col("len")).cast("int"))
    prefix = ranked.groupBy("log_id", "p", "len").agg(order.alias("ws")).select("log_id", "p", "len", F.explode(F.slice("ws", 1, F.col("p") - need + 1)).alias("x")).select("log_id", "p", "len", "x.word", "x.copy")
    joined = _pair(prefix, prefix, ["word", "copy"]).filter(F.abs(F.col("p") - F.col("p_b")) <= F.lit(delta) * F.least("len", "len_b"))
    return joined.select("log_id", "log_id_b").distinct()


def candidates(pats: DataFrame, delta: float, basis: str = "full") -> DataFrame:
    """Pairs log_id < log_id_b that may be within the bound; loses none (similar words free, equivalence)."""
    side = _sides(pats, basis)
    free_sizes = _free_sizes(side, delta).drop("n", "n_b")
    free = _pair(side.join(free_sizes, ["p", "len"]).drop("len_b").withColumnRenamed("p_b", "want"), side.withColumnRenamed("p", "want").drop("len"), ["want"]).select("log_id", "log_id_b")
    return free.union(_sharing(side, delta)).distinct()


def sizes(pats: DataFrame, delta: float, basis: str = "full") -> DataFrame:
    """src and size: how many patterns each one stands for, itself included (similar words free, equivalence).

    Pairs of cells that fit by their sizes are counted and never written out: near-cliques of short residuals cost
    nothing. Only the other pairs are compared word by word.
    """
    side = _sides(pats, basis)
    free = _free_sizes(side, delta)
    own = side.join(free.groupBy("p", "len").agg(F.sum("n_b").alias("free")), ["p", "len"], "left")
    # a pattern is in its own cell; where that cell is not free, it still stands for itself
    mine = F.col("p") <= F.lit(delta) * F.col("len")
    counted = own.select(F.col("log_id").alias("src"), (F.coalesce("free", F.lit(0)) + F.when(mine, 0).otherwise(1)).alias("n"))
    b = side.select(*(F.col(c).alias(f"{c}_b") for c in side.columns))
    bound = F.lit(delta) * F.least("len", "len_b")
    pairs = _sharing(side, delta).join(side, "log_id").join(b, "log_id_b").filter(F.greatest("p", "p_b") > bound)
    near = pairs.filter(sed(F.col("res"), F.col("res_b")) <= bound)
    compared = near.select(F.explode(F.array("log_id", "log_id_b")).alias("src"), F.lit(1).alias("n"))
    return counted.union(compared).groupBy("src").agg(F.sum("n").alias("size"))


def whole_lines(lines: DataFrame) -> DataFrame:
    """log_id (least), res, text (a word per row) and n_words of every distinct line: patterns() of exact words, with one copy of the words on the way."""
    # grouped as one text: far smaller than an array; no word holds a line break
    one = lines.select(F.array_join("words", "\n").alias("text"), F.size("words").alias("n_words"), "log_id")
    got = one.groupBy("text", "n_words").agg(F.min("log_id").alias("log_id"))
    return got.withColumn("res", F.when(F.col("n_words") == 0, F.array().cast("array<string>")).otherwise(F.split("text", "\n")))


#: counts of grams are kept by this many hash buckets
_BUCKETS = 1 << 18


def _grams(hashes: pd.Series, q: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all runs of q words and the rows that they are of."""
    size = np.array([len(h) for h in hashes], np.int64)
    flat = np.concatenate([*hashes, np.empty(0, np.int64)]).astype(np.int64).view(np.uint64)
    row = np.repeat(np.arange(len(size)), size)
    left = np.repeat(np.cumsum(size), size) - np.arange(len(flat))  # words from here to the end of the line
    g = np.zeros(len(flat), np.uint64)
    for j in range(q):
        g[: len(flat) - j] = g[: len(flat) - j] * np.uint64(0x9E3779B97F4A7C15) + flat[j:]
    g ^= g >> np.uint64(29)
    g *= np.uint64(0xBF58476D1CE4E5B9)
    g ^= g >> np.uint64(32)
    keep = left >= q
    return g[keep], row[keep]


def _sharing_grams(side: DataFrame, delta: float, q: int) -> DataFrame:
    """Pairs log_id < log_id_b of whole, distinct lines that share a run of q words among the q * delta * p + 1 rarest runs of each.

    An edit changes q runs at most, so k edits leave all but q * k of the runs of either line, and two lines within the
    bound share one of the q * k + 1 first runs in any common order. Here that is the count of a run's hash bucket, rare
    ones first. Lines too short for an edit have no other line within the bound. A run whose bucket is its own is left out.
    """
    spark = side.sparkSession
    rows = side.filter(F.floor(F.lit(delta) * F.col("p")) >= 1).select("log_id", "p", F.transform("res", lambda w: F.xxhash64(w)).alias("h"))

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        n = np.zeros(_BUCKETS, np.int64)
        for pdf in batches:
            n += np.bincount((_grams(pdf.h, q)[0] % np.uint64(_BUCKETS)).astype(np.int64), minlength=_BUCKETS)
        at = np.flatnonzero(n)
        yield pd.DataFrame({"bucket": at, "n": n[at]})

    total = np.zeros(_BUCKETS, np.int64)
    for r in rows.mapInPandas(count, "bucket long, n long").groupBy("bucket").agg(F.sum("n").alias("n")).toLocalIterator():  # _BUCKETS rows at most
        total[r["bucket"]] = r["n"]
    held = spark.sparkContext.broadcast(total)

    def prefix(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            g, row = _grams(pdf.h, q)
            n = held.value[(g % np.uint64(_BUCKETS)).astype(np.int64)]
            p = pdf.p.to_numpy()
            # powers of two, so that a bucket's other runs hardly matter; then the hash
            order = np.lexsort((g, np.frexp(n.astype(float))[1], row))
            g, row, n = g[order], row[order], n[order]
            start = np.flatnonzero(np.r_[True, (row[1:] != row[:-1])]) if len(row) else np.empty(0, np.int64)
            place = np.arange(len(row)) - np.repeat(start, np.diff(np.r_[start, len(row)]))
            run = np.flatnonzero(np.r_[True, (row[1:] != row[:-1]) | (g[1:] != g[:-1])]) if len(row) else start
            copy = np.arange(len(row)) - np.repeat(run, np.diff(np.r_[run, len(row)]))
            keep = (place <= q * np.floor(delta * p[row]).astype(np.int64)) & (n > 1)
            yield pd.DataFrame({"g": (g[keep] + copy[keep].astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)).view(np.int64), "log_id": pdf.log_id.to_numpy()[row[keep]], "p": p[row[keep]]})

    # most runs are of one line alone: they are moved once and then dropped
    firsts = rows.mapInPandas(prefix, "g long, log_id long, p int").withColumn("n", F.count("*").over(W.partitionBy("g")))
    firsts = stored(firsts.filter("n > 1").drop("n"), "firsts")
    joined = _pair(firsts, firsts, ["g"]).filter(F.abs(F.col("p") - F.col("p_b")) <= F.lit(delta) * F.least("p", "p_b"))
    return joined.select("log_id", "log_id_b").distinct()


def _code(arr: Column) -> Column:
    """One ASCII character per word by its hash: equal words share it, so codes are at most as far apart as their lines."""
    return F.array_join(F.transform(arr, lambda w: F.char(F.pmod(F.xxhash64(w), F.lit(94)) + 33)), "")


def sizes_whole(lines: DataFrame, delta: float) -> DataFrame:
    """sizes() of whole_lines(lines), for a small delta: runs of words find the pairs, single words would find far too many.

    Pairs are first compared by short codes, natively and only as far as the bound; the words themselves decide on the
    pairs that are left.
    """
    side = stored(lines.select("log_id", "text", F.col("n_words").alias("p")), "whole-lines")
    split = F.split("text", "\n").alias("res")
    q = min(5, int(1 / (2 * delta)))  # the longest runs of which some are left in every line
    pairs = stored(_sharing_grams(side.select("log_id", split, "p"), delta, q), "pairs")
    met = pairs.select(F.explode(F.array("log_id", "log_id_b")).alias("log_id")).distinct()
    texts = stored(side.join(met, "log_id", "left_semi").withColumn("code", _code(split)), "pair-lines")
    b = texts.select(*(F.col(c).alias(f"{c}_b") for c in texts.columns))
    coded = pairs.join(texts.drop("text"), "log_id").join(b.drop("text_b"), "log_id_b").withColumn("most", F.floor(F.lit(delta) * F.least("p", "p_b")).cast("int"))
    close = stored(coded.filter(F.expr("levenshtein(code, code_b, most) >= 0")).select("log_id", "log_id_b", "most"), "close")
    near = close.join(texts.select("log_id", "text"), "log_id").join(b.select("log_id_b", "text_b"), "log_id_b").filter(sed_within()("text", "text_b", "most"))
    found = near.select(F.explode(F.array("log_id", "log_id_b")).alias("src"), F.lit(1).alias("n"))
    return side.select(F.col("log_id").alias("src"), F.lit(1).alias("n")).union(found).groupBy("src").agg(F.sum("n").alias("size"))


def edges(pats: DataFrame, delta: float, basis: str = "full", similarity: str = "exact", tau: float = 0.5, polarity: str = "similar_free", prune: bool = True) -> DataFrame:
    """(src, dst, dist), both directions and each pattern with itself."""
    side = _sides(pats, basis)
    b = side.select(*(F.col(c).alias(f"{c}_b") for c in side.columns))
    native = similarity in ("exact", "classed") and polarity == "similar_free"
    if prune and native:
        pairs = candidates(pats, delta, basis).join(side, "log_id").join(b, "log_id_b")
    else:
        pairs = side.join(b, F.col("log_id") < F.col("log_id_b"))
    bound = F.lit(delta) * F.least("len", "len_b")
    pairs = pairs.filter(F.abs(F.col("p") - F.col("p_b")) <= bound)
    dist = sed(F.col("res"), F.col("res_b")) if native else sed_arrow(similarity, tau, polarity)("res", "res_b")
    found = pairs.withColumn("dist", dist).filter(F.col("dist") <= bound).select(F.col("log_id").alias("src"), F.col("log_id_b").alias("dst"), "dist")
    self_ = pats.select(F.col("log_id").alias("src"), F.col("log_id").alias("dst"), F.lit(0).alias("dist"))
    return found.union(found.select("dst", "src", "dist")).union(self_)


def edges_local(res: dict[int, list[str]], length: dict[int, int], delta: float, sim: Similarity, polarity: str = "similar_free") -> dict[int, set[int]]:
    """The same for a checked, small number of patterns: id -> ids it stands for."""
    alike: dict[tuple, list[int]] = {}
    for i in sorted(res):
        # equal residuals and lengths stand for the same lines
        key = tuple(res[i] if sim.kind == "vector" else [sim.shape(w) if sim.kind == "classed" else w for w in res[i]])
        alike.setdefault((key, length[i], i if polarity != "similar_free" else -1), []).append(i)
    groups = [(res[ids[0]], length[ids[0]], ids) for ids in alike.values()]
    # equal residuals are at distance 0, which fits any bound
    out = {i: set(ids) for *_, ids in groups for i in ids}
    for k, (a, n, ids) in enumerate(groups):
        for b, m, others in groups[k + 1 :]:
            bound = delta * min(n, m)
            if abs(len(a) - len(b)) > bound:
                continue
            # no two lists are farther apart than the longer one is long
            if max(len(a), len(b)) <= bound or sed_words(a, b, sim, polarity, most=int(bound)) <= bound:
                for i in ids:
                    out[i].update(others)
                for j in others:
                    out[j].update(ids)
    return out


def score(edge: DataFrame) -> DataFrame:
    """How many lines each one stands for."""
    return edge.groupBy("src").agg(F.count("*").alias("size"))


def knn_edges(vectors: DataFrame, m: int, id_col: str = "vec_id", vec: str = "embedding", queries: DataFrame | None = None, block: int = 1000) -> DataFrame:
    """The m nearest by cosine (6 digits) for every row, or every query row; ties go to the lower id.

    Both sides are cut into blocks of about `block` rows; a block pair is one matrix product that
    returns m rows per query, so pairs of rows are never written out.
    """

    def blocks(df: DataFrame, name: str) -> DataFrame:
        n = max(1, -(-df.count() // block))
        one = F.struct(F.col(id_col).cast("long").alias("i"), F.transform(vec, lambda x: x.cast("double")).alias("v"))
        return df.groupBy(F.pmod(F.xxhash64(id_col), F.lit(n)).alias("g")).agg(F.collect_list(one).alias(name)).select(name)

    def nearest(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        def matrix(rows):
            v = np.array([r["v"] for r in rows])
            n = np.linalg.norm(v, axis=1, keepdims=True)
            return np.array([r["i"] for r in rows]), v / np.where(n > 0, n, 1)

        for pdf in batches:
            for a, b in zip(pdf.a, pdf.b, strict=True):
                (src, x), (dst, y) = matrix(a), matrix(b)
                s = np.round(x @ y.T, 6)
                s[src[:, None] == dst[None, :]] = -np.inf
                top = np.stack([np.lexsort((dst, -row))[:m] for row in s])
                out = pd.DataFrame({"src": np.repeat(src, top.shape[1]), "dst": dst[top].ravel(), "cos": np.take_along_axis(s, top, 1).ravel()})
                yield out[np.isfinite(out.cos)]

    pairs = blocks(vectors if queries is None else queries, "a").crossJoin(blocks(vectors, "b"))
    found = pairs.repartition(F.xxhash64(F.col("a")[0]["i"], F.col("b")[0]["i"])).mapInPandas(nearest, "src long, dst long, cos double")
    order = W.partitionBy("src").orderBy(F.desc("cos"), "dst")
    return found.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= m)


def centroids(vectors: DataFrame, lists: int, id_col: str, vec: str, sample: int = 20_000, rounds: int = 8) -> np.ndarray:
    """Unit centres of `lists` groups, by rounds of k-means on at most about `sample` rows chosen by the hash of their id."""
    n = vectors.count()
    some = vectors if n <= sample else vectors.filter(F.pmod(F.xxhash64(F.lit("centre"), F.col(id_col)), F.lit(1 << 30)) < int(sample / n * (1 << 30)))
    rows = some.select(F.transform(vec, lambda x: x.cast("double")).alias("v")).orderBy(F.xxhash64(F.lit("order"), F.col(id_col))).limit(2 * sample).collect()
    x = np.array([r["v"] for r in rows]).reshape(len(rows), -1)
    size = np.linalg.norm(x, axis=1, keepdims=True)
    x = x / np.where(size > 0, size, 1)
    c = x[:lists].copy()
    for _ in range(rounds):
        near = (x @ c.T).argmax(axis=1)
        total = np.zeros_like(c)
        np.add.at(total, near, x)
        size = np.linalg.norm(total, axis=1, keepdims=True)
        c = np.where(size > 0, total / np.where(size > 0, size, 1), c)
    return c


def knn_index(vectors: DataFrame, m: int, id_col: str = "vec_id", vec: str = "embedding", queries: DataFrame | None = None, per_list: int = 100, probe: int = 12, piece: int = 4000) -> DataFrame:
    """knn_edges through lists: every row is in the list of its nearest centre, a query looks into the `probe` nearest.

    Approximate: tests hold its recall against knn_edges at 0.9 or more. Centres come from a bounded sample; the rows and the
    queries of a list are worked on in pieces of about `piece`. The work per query falls from all rows to those of a few lists.
    """
    lists = int(min(4096, max(1, vectors.count() // per_list)))
    held = vectors.sparkSession.sparkContext.broadcast(centroids(vectors, lists, id_col, vec))  # at most 4096 centres
    take = min(lists, probe)

    def place(df: DataFrame, k: int) -> DataFrame:
        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in batches:
                if len(pdf):
                    near = np.argsort(-(np.stack(pdf.v) @ held.value.T), axis=1, kind="stable")[:, :k]
                    yield pd.DataFrame({"i": pdf.i, "v": pdf.v, "list": list(near.astype(np.int64))})

        one = df.select(F.col(id_col).cast("long").alias("i"), F.transform(vec, lambda x: x.cast("double")).alias("v"))
        size = F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x))
        unit = one.withColumn("s", size).select("i", F.transform("v", lambda x: F.when(F.col("s") > 0, x / F.col("s")).otherwise(x)).alias("v"))
        return unit.mapInPandas(run, "i long, v array<double>, list array<long>").select("i", "v", F.explode("list").alias("list"))

    base, asked = place(vectors, 1), place(vectors if queries is None else queries, take)
    count = lambda df, name: df.groupBy("list").agg(F.ceil(F.count("*") / piece).alias(name))
    cut = count(base, "rows").join(count(asked, "asks"), "list")
    every = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), F.col(n) - 1))
    deal = lambda n: F.pmod(F.xxhash64("i"), F.col(n))
    base = base.join(cut, "list").withColumn("part", deal("rows")).select("list", "part", every("asks").alias("turn"), "i", "v", F.lit(False).alias("asks"))
    asked = asked.join(cut, "list").withColumn("turn", deal("asks")).select("list", every("rows").alias("part"), "turn", "i", "v", F.lit(True).alias("asks"))

    def nearest(pdf: pd.DataFrame) -> pd.DataFrame:
        q, d = pdf[pdf.asks], pdf[~pdf.asks]
        if not len(q) or not len(d):
            return pd.DataFrame({"src": [], "dst": [], "cos": []})
        dst, y = d.i.to_numpy(), np.stack(d.v)
        out = []
        for at in range(0, len(q), 1000):
            src = q.i.to_numpy()[at : at + 1000]
            s = np.round(np.stack(q.v[at : at + 1000]) @ y.T, 6)
            s[src[:, None] == dst[None, :]] = -np.inf
            top = np.stack([np.lexsort((dst, -row))[:m] for row in s])
            out.append(pd.DataFrame({"src": np.repeat(src, top.shape[1]), "dst": dst[top].ravel(), "cos": np.take_along_axis(s, top, 1).ravel()}))
        got = pd.concat(out)
        return got[np.isfinite(got.cos)]

    found = base.unionByName(asked).groupBy("list", "part", "turn").applyInPandas(nearest, "src long, dst long, cos double")
    order = W.partitionBy("src").orderBy(F.desc("cos"), "dst")
    return found.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= m)


def cosine_edges(vectors: DataFrame, cut: float, id_col: str = "log_id", vec: str = "v", block: int = 1000) -> DataFrame:
    """(src, dst) of all rows with cosine of at least the cut, each with itself; block pairs are matrix products."""
    n = max(1, -(-vectors.count() // block))
    one = F.struct(F.col(id_col).cast("long").alias("i"), F.col(vec).alias("v"))
    cut_up = vectors.groupBy(F.pmod(F.xxhash64(id_col), F.lit(n)).alias("g")).agg(F.collect_list(one).alias("x"))

    def near(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        def matrix(rows):
            v = np.array([r["v"] for r in rows])
            size = np.linalg.norm(v, axis=1, keepdims=True)
            return np.array([r["i"] for r in rows]), v / np.where(size > 0, size, 1)

        for pdf in batches:
            for a, b in zip(pdf.a, pdf.b, strict=True):
                (src, x), (dst, y) = matrix(a), matrix(b)
                i, j = np.nonzero((x @ y.T >= cut) | (src[:, None] == dst[None, :]))
                yield pd.DataFrame({"src": src[i], "dst": dst[j]})

    pairs = cut_up.select(F.col("x").alias("a")).crossJoin(cut_up.select(F.col("x").alias("b")))
    return pairs.repartition(F.xxhash64(F.col("a")[0]["i"], F.col("b")[0]["i"])).mapInPandas(near, "src long, dst long")
