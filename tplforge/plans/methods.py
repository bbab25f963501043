"""Queries of the methods, baselines, measures and workloads, with the SQL that checks them."""

from __future__ import annotations

from collections.abc import Callable
from contextvars import ContextVar
from dataclasses import replace
from functools import reduce, wraps

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tplforge.functions import measures as M
from tplforge.functions.confidence import difficulty, inconsistent, mean_prob
from tplforge.functions.distance import cosine, sed, sed_arrow, sed_fold
from tplforge.functions.words import SHAPES, Similarity, graph, residual_join, tokenize, words
from tplforge.operators import baselines as B
from tplforge.operators import budget as budgets
from tplforge.operators import rounds as R
from tplforge.operators import select as S
from tplforge.operators.context import adaptive_sql, context_frame
from tplforge.operators.models import CANDIDATES, Context, ContextTagger, TruthAnnotator
from tplforge.operators.prompt import INSTRUCTION, attach, build
from tplforge.operators.represent import edges, knn_edges, knn_index, patterns, score, sizes, sizes_whole, whole_lines
from tplforge.plans.choose import choose
from tplforge.sources.corpus import BUDGETS, CORPORA, SCALE, SWEEP_SCALE, TRUTH, corpus, document_lines, plain, query, scaled, table

from tplforge.session import stored

Query = Callable[[SparkSession, str], DataFrame]
_Q: dict[str, Query] = {}
_SQL: dict[str, str] = {}


def register(sql: str | None = None, name: str | None = None):
    def add(f: Query) -> Query:
        _Q[name or f.__name__] = f
        if sql is not None:
            _SQL[name or f.__name__] = sql
        return f

    return add


def lines(spark: SparkSession, sf_dir: str, name: str, spread: bool = False) -> DataFrame:
    return tokenize(corpus(spark, sf_dir, name, spread))


def all_lines(spark: SparkSession, sf_dir: str, names=TRUTH) -> DataFrame:
    return reduce(DataFrame.unionByName, (lines(spark, sf_dir, n) for n in names))


# the checking engine's forms
_WORDS = r"list_filter(string_split_regex({}, '\s+'), lambda x: x <> '')"
_SHAPE = "CASE " + " ".join(f"WHEN regexp_matches(x, '{p}') THEN '{n}'" for n, p in SHAPES) + " ELSE x END"


def _lines_sql(names) -> str:
    return " UNION ALL ".join(f"SELECT '{n}' AS domain, * FROM ({plain(CORPORA[n])})" for n in names)


def _patterns_sql(names) -> str:
    """t(domain, log_id, res): distinct lists of shape classes."""
    return f"""l AS ({_lines_sql(names)}), k AS (SELECT domain, log_id, list_transform({_WORDS.format("raw")}, lambda x: {_SHAPE}) AS res FROM l),
t AS (SELECT domain, res, min(log_id) AS log_id FROM k GROUP BY domain, res)"""


_GLYPHS = "list_aggregate(list_transform({}, lambda x: chr(33 + list_position(d, x)::INT)), 'string_agg', '')"
_PAIRS = f"""p AS (SELECT a.domain, a.log_id AS src, b.log_id AS dst, a.res AS ra, b.res AS rb, list_distinct(list_concat(a.res, b.res)) AS d
 FROM t a JOIN t b ON a.domain = b.domain AND a.log_id < b.log_id),
s AS (SELECT domain, src, dst, len(ra) AS la, len(rb) AS lb, levenshtein({_GLYPHS.format("ra")}, {_GLYPHS.format("rb")}) AS dist FROM p)"""


# ---- corpora and words ------------------------------------------------------------------
for _name in CORPORA:
    if _name in TRUTH:
        register(plain(CORPORA[_name]), f"corpus_{_name}")(lambda spark, sf_dir, n=_name: query(spark, sf_dir, CORPORA[n]))


@register(
    f"""WITH l AS ({_lines_sql(TRUTH)}), w AS (SELECT domain, unnest({_WORDS.format("raw")}) AS w FROM l)
SELECT a.domain, templates, n_lines, n_words FROM (SELECT domain, count(DISTINCT truth) AS templates, count(DISTINCT raw) AS n_lines FROM l GROUP BY 1) a
JOIN (SELECT domain, count(DISTINCT w) AS n_words FROM w GROUP BY 1) b USING (domain)"""
)
def corpus_stats(spark, sf_dir):
    return M.corpus_stats(all_lines(spark, sf_dir))


_DOC_WORDS = f"w AS (SELECT doc_id, unnest({_WORDS.format('text')}) AS w FROM documents)"


def _documents(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "documents").select(F.col("doc_id").alias("log_id"), words(F.col("text")).alias("words"))


@register(f"WITH {_DOC_WORDS} SELECT doc_id AS log_id, count(*) AS n, count(DISTINCT w) AS n_distinct FROM w GROUP BY 1")
def word_graph_degrees(spark, sf_dir):
    e, _ = graph(_documents(spark, sf_dir))
    return e.groupBy("log_id").agg(F.count("*").alias("n"), F.countDistinct("word").alias("n_distinct"))


@register(f"WITH {_DOC_WORDS} SELECT w AS word, count(DISTINCT doc_id) AS df, count(*) AS n FROM w GROUP BY 1")
def vocab_df(spark, sf_dir):
    return graph(_documents(spark, sf_dir))[1].select("word", "df", "n")


@register(
    f"""WITH {_DOC_WORDS}, k AS (SELECT DISTINCT w FROM w JOIN labels USING (doc_id)), u AS (SELECT * FROM w WHERE doc_id NOT IN (SELECT doc_id FROM labels))
SELECT d.doc_id AS log_id, count(u.w) FILTER (WHERE u.w NOT IN (SELECT w FROM k)) AS n_residual FROM documents d LEFT JOIN u USING (doc_id) WHERE d.doc_id NOT IN (SELECT doc_id FROM labels) GROUP BY 1"""
)
def residual_words(spark, sf_dir):
    """Words of unlabelled documents that no labelled document has."""
    docs, known = _documents(spark, sf_dir), table(spark, sf_dir, "labels").select(F.col("doc_id").alias("log_id"))
    vocab = docs.join(known, "log_id", "left_semi").select(F.explode("words").alias("word"))
    return residual_join(docs.join(known, "log_id", "left_anti"), vocab).select("log_id", F.size("residual").alias("n_residual"))


@register(f"WITH {_DOC_WORDS} SELECT count(DISTINCT w) AS words FROM w JOIN labels USING (doc_id)", "words_seen")
def _words_seen(spark, sf_dir):
    """Words that labelled documents identify."""
    known = table(spark, sf_dir, "labels").select(F.col("doc_id").alias("log_id"))
    n = budgets.words_seen(_documents(spark, sf_dir).join(known, "log_id", "left_semi"))
    return spark.createDataFrame([(n,)], "words long")


# ---- distances and representation ----------------------------------------------------------
#: free text: a line stands for those that differ in a tenth of the words
DOC_DELTA = 0.1
_SMALL = ("evt_simple", "evt_rich", "ord_desk", "ledger")


def _pattern_pairs(spark, sf_dir, name) -> DataFrame:
    p = patterns(lines(spark, sf_dir, name)).select("log_id", "res")
    b = p.select(F.col("log_id").alias("dst"), F.col("res").alias("res_b"))
    return p.join(b, F.col("log_id") < F.col("dst")).select(F.lit(name).alias("domain"), F.col("log_id").alias("src"), "dst", "res", "res_b")


@register(f"WITH {_patterns_sql(_SMALL)}, {_PAIRS} SELECT domain, src, dst, dist FROM s")
def sed_exact_pairs(spark, sf_dir):
    out = reduce(DataFrame.unionByName, (_pattern_pairs(spark, sf_dir, n) for n in _SMALL))
    return out.select("domain", "src", "dst", sed(F.col("res"), F.col("res_b")).alias("dist"))


@register(f"WITH {_patterns_sql(('evt_rich',))}, {_PAIRS} SELECT src, dst, dist::INT AS native, dist::INT AS similar_free FROM s")
def sed_variants(spark, sf_dir):
    """The native form of the distance and the recurrence as a fold."""
    p = _pattern_pairs(spark, sf_dir, "evt_rich")
    a, b = F.col("res"), F.col("res_b")
    return p.select("src", "dst", sed(a, b).alias("native"), sed_fold(a, b).alias("similar_free"))


@register()
def sed_as_printed(spark, sf_dir):
    """The other polarity of the substitution cost."""
    p = _pattern_pairs(spark, sf_dir, "evt_rich")
    return p.select("src", "dst", sed_fold(F.col("res"), F.col("res_b"), "as_printed").alias("as_printed"))


@register()
def sed_cosine_pairs(spark, sf_dir):
    return _pattern_pairs(spark, sf_dir, "evt_rich").select("src", "dst", sed_arrow("vector", 0.5)("res", "res_b").alias("dist"))


@register(
    f"""WITH {_patterns_sql(TRUTH)}, {_PAIRS}, e AS (SELECT domain, src, dst FROM s WHERE dist <= 0.5 * least(la, lb)),
f AS (SELECT domain, src, dst FROM e UNION ALL SELECT domain, dst, src FROM e UNION ALL SELECT domain, log_id, log_id FROM t)
SELECT domain, src, count(*) AS size FROM f GROUP BY 1, 2"""
)
def represent_sizes(spark, sf_dir):
    """Pairs that fit by their sizes alone are counted by cells of sizes and not written out."""
    parts = [sizes(patterns(lines(spark, sf_dir, n)), 0.5).select(F.lit(n).alias("domain"), "src", "size") for n in TRUTH]
    return reduce(DataFrame.unionByName, parts)


_FEW_GLYPHS = "list_aggregate(list_transform({}, lambda x: chr(list_position(d, x)::INT)), 'string_agg', '')"  # passages of under 64 words


@register(
    f"""WITH t AS (SELECT {_WORDS.format("text")} AS res, min(item_id) AS log_id FROM benchmark GROUP BY 1),
p AS (SELECT a.log_id AS src, b.log_id AS dst, a.res AS ra, b.res AS rb, list_distinct(list_concat(a.res, b.res)) AS d FROM t a JOIN t b ON a.log_id < b.log_id),
e AS (SELECT src, dst FROM p WHERE levenshtein({_FEW_GLYPHS.format("ra")}, {_FEW_GLYPHS.format("rb")}) <= 0.7 * least(len(ra), len(rb))),
f AS (SELECT src FROM e UNION ALL SELECT dst FROM e UNION ALL SELECT log_id FROM t) SELECT src, count(*) AS size FROM f GROUP BY 1"""
)
def repr_bench_lines(spark, sf_dir):
    """Edges of free text, exact words: the rarest-word filter instead of all pairs."""
    return score(edges(patterns(lines(spark, sf_dir, "bench_lines"), "exact"), 0.7))


@register()
def repr_documents_lines(spark, sf_dir):
    """How many lines each distinct line of documents stands for: near copies among free text of any length."""
    return sizes_whole(whole_lines(tokenize(document_lines(spark, sf_dir)).filter("n_words > 0")), DOC_DELTA)


@register()
def repr_chat_lines(spark, sf_dir):
    return sizes_whole(whole_lines(lines(spark, sf_dir, "chat_lines")), DOC_DELTA)


_EMB = """q AS (SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings WHERE vec_id % 50 = 0), c AS (SELECT q.vec_id AS src, e.vec_id AS dst, round(list_cosine_similarity(q.v, e.embedding::DOUBLE[]), 6) AS cos FROM q JOIN embeddings e ON q.vec_id <> e.vec_id)"""


@register(f"WITH {_EMB}, r AS (SELECT *, row_number() OVER (PARTITION BY src ORDER BY cos DESC, dst) AS rank FROM c) SELECT src, dst, cos, rank FROM r WHERE rank <= 5")
def emb_cosine_topk(spark, sf_dir):
    """Queries are the rows whose id is divisible by 50, against all rows."""
    e = table(spark, sf_dir, "embeddings")
    return knn_edges(e, 5, queries=e.filter(F.col("vec_id") % 50 == 0))


@register(
    """WITH c AS (SELECT a.vec_id AS src, b.vec_id AS dst, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS cos FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id),
r AS (SELECT *, row_number() OVER (PARTITION BY src ORDER BY cos DESC, dst) AS rank FROM c) SELECT dst, count(*) AS size FROM r WHERE rank <= 5 GROUP BY 1"""
)
def emb_knn_coverage(spark, sf_dir):
    return knn_edges(table(spark, sf_dir, "embeddings"), 5).groupBy("dst").agg(F.count("*").alias("size"))


@register("SELECT a.vec_id AS src, b.vec_id AS dst, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS cos FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def emb_line_cosine(spark, sf_dir):
    """Cosine of two vectors in built-in functions, for each row and the next."""
    e = table(spark, sf_dir, "embeddings")
    b = e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("vec_id").alias("dst"), F.col("embedding").alias("other"))
    return e.join(b, "vec_id").select(F.col("vec_id").alias("src"), "dst", F.round(cosine(F.col("embedding"), F.col("other")), 6).alias("cos"))


@register()
def emb_knn_index(spark, sf_dir):
    """The same neighbours through an index: every row is in a list, a query looks into the nearest lists."""
    e = table(spark, sf_dir, "embeddings")
    return knn_index(e, 5, queries=e.filter(F.col("vec_id") % 50 == 0))


@register()
def dpp_pick(spark, sf_dir):
    return S.dpp_map(table(spark, sf_dir, "embeddings"), 12)


# ---- confidence ------------------------------------------------------------------------------
def answers(spark, sf_dir) -> DataFrame:
    """Answers made by arithmetic on event ids: every 10th loses a word, every 15th leaves a variable."""
    d = lines(spark, sf_dir, "evt_simple")
    probs = F.transform("words", lambda w, i: ((F.col("log_id") * 7 + i * 13) % 100) / F.lit(100.0))
    echo = F.when(F.col("log_id") % 10 == 0, F.slice("words", 1, F.size("words") - 1)).otherwise(F.col("words"))
    labels = F.when(F.col("log_id") % 15 == 0, F.transform("labels", lambda x, i: F.when(i == 4, F.element_at("words", 5)).otherwise(x))).otherwise(F.col("labels"))
    return d.select("log_id", "words", F.col("labels").alias("true_labels"), echo.alias("echo"), labels.alias("labels"), probs.alias("probs"))


_ANSWERS = f"""l AS ({plain(CORPORA["evt_simple"])}), a AS (SELECT log_id, {_WORDS.format("raw")} AS words FROM l),
b AS (SELECT log_id, list_sum(list_transform(range(0, len(words)), lambda i: ((log_id * 7 + i * 13) % 100) / 100.0)) / len(words) AS p, CASE WHEN log_id % 10 = 0 THEN 1 ELSE 0 END AS flag FROM a)"""


@register(f"WITH {_ANSWERS} SELECT log_id, round(p, 6) AS p FROM b", "mean_prob")
def _mean_prob(spark, sf_dir):
    return answers(spark, sf_dir).select("log_id", F.round(mean_prob(F.col("probs")), 6).alias("p"))


@register(f"WITH {_ANSWERS} SELECT log_id, flag FROM b", "consistency_flag")
def _flag(spark, sf_dir):
    cand = F.array(*map(F.lit, CANDIDATES))
    return answers(spark, sf_dir).select("log_id", inconsistent(F.col("words"), F.col("echo"), F.col("labels"), cand).alias("flag"))


@register(f"WITH {_ANSWERS}, g AS (SELECT unnest([0.2, 0.5, 0.8]) AS a) SELECT log_id, a, round(a * (1 - p) + (1 - a) * flag, 6) AS c FROM b, g", "difficulty")
def _difficulty(spark, sf_dir):
    x = answers(spark, sf_dir).select("log_id", mean_prob(F.col("probs")).alias("p"), inconsistent(F.col("words"), F.col("echo"), F.col("labels")).alias("flag"))
    c = F.array(*(F.struct(F.lit(a).alias("a"), F.round(difficulty(F.col("p"), F.col("flag"), a), 6).alias("c")) for a in (0.2, 0.5, 0.8)))
    return x.select("log_id", F.inline(c))


@register(f"WITH {_ANSWERS} SELECT log_id, round(0.5 * (1 - p) + 0.5 * flag, 6) AS difficulty FROM b ORDER BY 2 DESC, 1 LIMIT 50")
def top_difficulty(spark, sf_dir):
    """lam = 1: the budget goes to the hardest lines."""
    x = answers(spark, sf_dir)
    c = x.select("log_id", F.round(difficulty(mean_prob(F.col("probs")), inconsistent(F.col("words"), F.col("echo"), F.col("labels"))), 6).alias("difficulty"))
    return S.top_difficulty(c, 50)


@register(f"WITH {_ANSWERS} SELECT log_id FROM b WHERE p < 0.5")
def still_open(spark, sf_dir):
    """Lines that the generic framework keeps for the next round: those the model is not sure of."""
    return R.still_open(answers(spark, sf_dir), 0.5).select("log_id")


@register(f"WITH {_ANSWERS} SELECT count(*) FILTER (WHERE log_id % 10 = 0) AS gen_errors, count(*) FILTER (WHERE log_id % 15 = 0) AS word_errors FROM b", "error_counts")
def _errors(spark, sf_dir):
    return M.errors(answers(spark, sf_dir), keys=())


# ---- selection -------------------------------------------------------------------------------
def _candidates(spark, sf_dir, name="ord_desk") -> tuple[DataFrame, DataFrame]:
    pats = stored(patterns(lines(spark, sf_dir, name)), "candidates")
    c = pats.select("log_id", (F.pmod(F.col("log_id") * 7, F.lit(100)) / F.lit(100.0)).alias("difficulty"))
    return c, edges(pats, 0.5).select("src", "dst")


@register(
    f"""WITH {_patterns_sql(("ord_desk",))}, {_PAIRS}, e AS (SELECT src, dst FROM s WHERE dist <= 0.5 * least(la, lb)),
f AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e UNION ALL SELECT log_id, log_id FROM t)
SELECT src AS log_id, count(*) AS covered FROM f GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 1"""
)
def coverage_greedy_first(spark, sf_dir):
    c, e = _candidates(spark, sf_dir)
    return S.greedy(c, e, 1, 0.0).select("log_id", "covered")


def _greedy_query(form: str, lam: float):
    def run(spark, sf_dir):
        c, e = _candidates(spark, sf_dir)
        return S.greedy(c, e, 4, lam, form)

    return run




def _greedy_sql(form: str, lam: float, b: int, name: str = "ord_desk", result: str | None = None) -> str:
    """The picks unrolled: x<k> is what the first k picks cover, g<k> the gains after them, p<k> the k-th pick."""
    u = "(SELECT count(*) FROM t)"
    parts = [
        f"{_patterns_sql((name,))}, {_PAIRS}, e AS (SELECT src, dst FROM s WHERE dist <= 0.5 * least(la, lb))",
        "f AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e UNION ALL SELECT log_id, log_id FROM t)",
        "c AS (SELECT log_id, (log_id * 7 % 100) / 100.0::DOUBLE AS difficulty FROM t)",
        "x0 AS (SELECT NULL::BIGINT AS dst WHERE false)",
    ]
    for k in range(b):
        gone = " UNION ALL ".join(f"SELECT log_id FROM p{i}" for i in range(1, k + 1)) or "SELECT NULL::BIGINT WHERE false"
        times, base = (k + 1, f"(SELECT count(*) FROM x{k})") if form == "as_printed" else (1, "0")
        value = f"round({1 - lam}::DOUBLE * ({times} * count(f.dst) + {base}) / {u}::DOUBLE + {lam}::DOUBLE * any_value(difficulty), 12)"
        parts.append(f"g{k} AS (SELECT c.log_id, any_value(difficulty) AS difficulty, {value} AS gain FROM c LEFT JOIN f ON f.src = c.log_id AND f.dst NOT IN (SELECT dst FROM x{k}) WHERE c.log_id NOT IN (SELECT log_id FROM ({gone}) WHERE log_id IS NOT NULL) GROUP BY 1)")
        parts.append(f"p{k + 1} AS (SELECT * FROM g{k} ORDER BY gain DESC, log_id LIMIT 1)")
        parts.append(f"x{k + 1} AS (SELECT dst FROM x{k} UNION SELECT dst FROM f JOIN p{k + 1} ON src = log_id)")
    rows = " UNION ALL ".join(f"SELECT {k}::INT AS rank, log_id, gain, (SELECT count(*) FROM x{k})::INT AS covered, difficulty FROM p{k}" for k in range(1, b + 1))
    return f"WITH {', '.join(parts)} {result or rows}"


for _key, _form, _lam in (("greedy_separable", "separable", 0.5), ("greedy_as_printed", "as_printed", 0.5), ("greedy_coverage_only", "separable", 0.0)):
    register(_greedy_sql(_form, _lam, 4), _key)(_greedy_query(_form, _lam))


@register(_greedy_sql("separable", 0.0, 4, result="SELECT round((SELECT count(*) FROM x4) / (SELECT count(*) FROM t)::DOUBLE, 9) AS coverage"))
def coverage_of_picks(spark, sf_dir):
    """Share of the patterns that four picks stand for."""
    c, e = _candidates(spark, sf_dir)
    return M.coverage(S.greedy(c, e, 4, 0.0), e, c.count()).select(F.round("coverage", 9).alias("coverage"))


@register(_greedy_sql("separable", 0.5, 5))
def greedy_lazy(spark, sf_dir):
    """Stale gains in a heap on the driver, where the number of patterns was checked; the same picks from stored tables beyond."""
    c, e = _candidates(spark, sf_dir)
    if choose(c.count())["greedy"].choice == "distributed":
        return S.greedy(c, e, 5, 0.5)
    cover: dict[int, set[int]] = {}
    for r in e.toLocalIterator():  # at most the square of the checked number
        cover.setdefault(r["src"], set()).add(r["dst"])
    got = S.greedy_local(cover, {r["log_id"]: r["difficulty"] for r in c.collect()}, 5, 0.5)
    return spark.createDataFrame([(k, i, round(g, 12), n, d) for k, i, g, n, d in got], "rank int, log_id long, gain double, covered int, difficulty double")


@register()
def greedy_sampled(spark, sf_dir):
    return S.greedy(*_candidates(spark, sf_dir), 10, 0.5, eps=0.1)


@register()
def greedy_sharded(spark, sf_dir):
    return S.greedy_sharded(*_candidates(spark, sf_dir), 10, 0.5)


_MONTHS = """m AS (SELECT cast(extract(year FROM first) * 12 + extract(month FROM first) AS INT) AS m, count(*) AS fresh FROM (SELECT o_custkey, min(o_orderdate) AS first FROM {orders} GROUP BY 1) GROUP BY 1),
w AS (SELECT cast(row_number() OVER (ORDER BY m) AS INT) AS r, cast(sum(fresh) OVER (ORDER BY m) AS INT) AS seen FROM m)"""
_BUDGET_STEP = """least(z.left_over, CASE WHEN w.r = 2 THEN 25 ELSE greatest(1, cast(floor(z.budget * least(2.0, greatest(0.0, 1 - (z.seen - z.prev) / cast(z.seen AS DOUBLE))) + 1e-9) AS INT)) END)"""
_BUDGET_SQL = f"""WITH RECURSIVE {_MONTHS}, z AS (
 SELECT 1 AS r, 50 AS budget, 150 AS left_over, seen, 0 AS prev FROM w WHERE r = 1
 UNION ALL SELECT w.r, {_BUDGET_STEP}, z.left_over - {_BUDGET_STEP}, w.seen, z.seen FROM z JOIN w ON w.r = z.r + 1 WHERE z.left_over > 0
) SELECT r, budget FROM z"""


@register(plain(_BUDGET_SQL))
def adaptive_budget(spark, sf_dir):
    """Budgets of 200 over months as rounds; customers seen so far stand for words identified."""
    rows = query(spark, sf_dir, f"WITH {_MONTHS} SELECT r, seen FROM w ORDER BY r").collect()  # one row per month
    out = budgets.trace([r["seen"] for r in rows], 200, (50, 25))
    return spark.createDataFrame([(i + 1, b) for i, b in enumerate(out)], "r int, budget int")


@register(plain(_BUDGET_SQL), "op_recursive")
def _recursive(spark, sf_dir):
    return query(spark, sf_dir, _BUDGET_SQL)


# ---- contexts, prompts, cost --------------------------------------------------------------------
def _demos(spark, sf_dir, name="ord_desk", k=20):
    return B.diverse_start(lines(spark, sf_dir, name), k)[1]


@register()
def context_adaptive(spark, sf_dir):
    return context_frame(lines(spark, sf_dir, "ord_desk"), _demos(spark, sf_dir))


@register()
def context_as_printed(spark, sf_dir):
    return context_frame(lines(spark, sf_dir, "ord_desk"), _demos(spark, sf_dir), cover="as_printed")


@register()
def context_topk(spark, sf_dir):
    return context_frame(lines(spark, sf_dir, "ord_desk"), _demos(spark, sf_dir), mode="topk", k=5)


@register()
def context_by_joins(spark, sf_dir):
    d = lines(spark, sf_dir, "evt_simple")
    demos = spark.createDataFrame([(x.id, list(x.words)) for x in _demos(spark, sf_dir, "evt_simple", 5)], "log_id long, words array<string>")
    return adaptive_sql(d, demos, 4)


_PROMPT_LENGTH = f"""length('{INSTRUCTION}') + 1 + length('Line: ') + length(raw) + length('
Words: ') + length(regexp_replace(raw, '\\s+', ' | ', 'g')) + length('
Template:')"""


@register(f"WITH l AS ({_lines_sql(TRUTH)}) SELECT domain, log_id, cast(ceil(({_PROMPT_LENGTH}) / 4.0) AS BIGINT) AS tokens FROM l")
def prompt_tokens(spark, sf_dir):
    d = all_lines(spark, sf_dir)
    none = F.array().cast("array<struct<raw:string,template:string>>")
    return d.select("domain", "log_id", M.tokens(build(F.col("raw"), none)).alias("tokens"))


@register(
    f"""WITH l AS ({_lines_sql(("evt_simple",))}), d AS (SELECT string_agg('Line: ' || raw || chr(10) || 'Template: ' || truth || chr(10), '' ORDER BY log_id) AS shown FROM (SELECT * FROM l ORDER BY log_id LIMIT 3))
SELECT log_id, md5('{INSTRUCTION}' || chr(10) || shown || 'Line: ' || raw || chr(10) || 'Words: ' || regexp_replace(raw, '\\s+', ' | ', 'g') || chr(10) || 'Template:') AS prompt FROM l, d"""
)
def prompt_with_demos(spark, sf_dir):
    """Whole prompts with three examples (those of the least ids), as digests."""
    d = lines(spark, sf_dir, "evt_simple")
    labelled = TruthAnnotator(d).label([r["log_id"] for r in d.orderBy("log_id").limit(3).collect()])
    shown = spark.createDataFrame([(x.id, " ".join(x.words), " ".join(x.labels)) for x in labelled], "log_id long, raw string, template string")
    context = d.select("log_id", F.array(*(F.lit(x.id) for x in labelled)).alias("demos"))
    return attach(context, d, shown).select("log_id", F.md5("prompt").alias("prompt"))


@register(f"WITH l AS ({_lines_sql(TRUTH)}), t AS (SELECT domain, cast(ceil(({_PROMPT_LENGTH}) / 4.0) AS BIGINT) AS tokens FROM l) SELECT domain, sum(tokens)::BIGINT AS tokens, round(sum(tokens) * 3.6e-6, 6) AS usd, round(avg(tokens) * 3.6e-6, 10) AS usd_per_line FROM t GROUP BY 1", "api_cost")
def _api_cost(spark, sf_dir):
    out = M.api_cost(prompt_tokens(spark, sf_dir), keys=("domain",))
    return out.select("domain", "tokens", F.round("usd", 6).alias("usd"), F.round("usd_per_line", 10).alias("usd_per_line"))


# ---- accuracy measures on the masking heuristic ------------------------------------------------------
def _masked(spark, sf_dir) -> DataFrame:
    d = all_lines(spark, sf_dir)
    truth = F.regexp_replace("truth", r"\[[A-Z]+\]", B.WILD)
    return B.mask_group(d).select("domain", F.lit("mask").alias("method"), "log_id", truth.alias("truth"), "pred")


_MASKED = f"""l AS ({_lines_sql(TRUTH)}), m AS (SELECT domain, log_id, regexp_replace(truth, '\\[[A-Z]+\\]', '<*>', 'g') AS truth,
 list_aggregate(list_transform({_WORDS.format("raw")}, lambda x: CASE WHEN regexp_matches(x, '[0-9]') THEN '<*>' ELSE x END), 'string_agg', ' ') AS pred FROM l)"""


def _rate_sql(by: str, name: str) -> str:
    return f"WITH {_MASKED}, g AS (SELECT domain, {by}, min((truth = pred)::INT) AS ok FROM m GROUP BY 1, 2) SELECT domain, 'mask' AS method, round(avg(ok), 9) AS {name} FROM g GROUP BY 1"


@register(f"WITH {_MASKED} SELECT domain, 'mask' AS method, round(avg((truth = pred)::INT), 9) AS mla FROM m GROUP BY 1", "mla")
def _mla(spark, sf_dir):
    return M.mla(_masked(spark, sf_dir)).withColumn("mla", F.round("mla", 9))


@register(_rate_sql("pred", "pta"), "pta")
def _pta(spark, sf_dir):
    return M.pta(_masked(spark, sf_dir)).withColumn("pta", F.round("pta", 9))


@register(_rate_sql("truth", "rta"), "rta")
def _rta(spark, sf_dir):
    return M.rta(_masked(spark, sf_dir)).withColumn("rta", F.round("rta", 9))


@register(f"WITH {_MASKED} SELECT domain, pred, count(*) AS n FROM m GROUP BY 1, 2")
def parse_tree_masked(spark, sf_dir):
    return _masked(spark, sf_dir).groupBy("domain", "pred").agg(F.count("*").alias("n"))


# ---- methods -----------------------------------------------------------------------------------
#: words per thousand that the stand-in model makes up a type for while no example shows them
MISREAD = 500


def config(name: str, scale: int = SCALE) -> R.Config:
    total, start = scaled(name, scale)
    fixed = max(1, (10 if BUDGETS[name][0] == 50 else 40) // scale)
    return R.Config(budget=total, start=start, fixed=fixed, model=ContextTagger(misread=MISREAD))


#: distinct lines and patterns of the corpora of one workload, while it runs
_BASES: ContextVar[dict | None] = ContextVar("bases", default=None)


def _base(spark, sf_dir, name: str) -> tuple[DataFrame, R.Base]:
    held = _BASES.get()
    if held is None:
        held = {}
    if (sf_dir, name) not in held:
        d = lines(spark, sf_dir, name, True)
        held[sf_dir, name] = d, R.Base(d)
    return held[sf_dir, name]


def workload(f: Query) -> Query:
    """Runs over one corpus share its distinct lines and patterns."""

    @wraps(f)
    def run(*args, **kwargs):
        token = _BASES.set({})
        try:
            return f(*args, **kwargs)
        finally:
            _BASES.reset(token)

    return run


def method(spark, sf_dir, name: str, which: str, cfg: R.Config | None = None) -> DataFrame:
    """Predictions of one method on one corpus: distinct lines, or n lines with one prediction."""
    cfg = cfg or config(name)
    d, base = (lines(spark, sf_dir, name, True), None) if which in ("PT", "ZERO", "RANDOM") else _base(spark, sf_dir, name)
    if which == "PT":
        p = B.as_typed(B.parse_tree(B.mask_count(d)))
        out = p.select("n", "log_id", "domain", "truth", "pred", "words", F.col("labels").alias("true_labels"), F.col("words").alias("echo"), "labels", F.array().cast("array<long>").alias("demos"), F.lit(0).cast("long").alias("tokens"), F.lit(False).alias("labelled"))
    elif which == "FT":
        out = B.token_tagger(d, cfg.budget, base, True).predictions
    elif which == "S1":
        out = B.single_round(d, cfg.budget, model=cfg.model, base=base, compact=True).predictions
    elif which == "MF":
        out = B.multi_fixed(d, cfg.budget, cfg.fixed, model=cfg.model, base=base, compact=True).predictions
    elif which == "ZERO":
        out = B.zero_shot(d, misread=MISREAD).predictions
    elif which == "RANDOM":
        out = B.random_pick(d, cfg.budget, model=cfg.model).predictions
    else:
        out = R.run(d, R.variant(cfg, which), base=base, compact=True).predictions
    return out.withColumn("method", F.lit(which)).select("domain", "method", "log_id", "truth", "pred", "words", "echo", "labels", "true_labels", "demos", "tokens", "labelled", M.lines_of(out).cast("long").alias("n"))


POPULATIONS = ("all", "unlabelled")


def scored(pred: DataFrame, keys=M.KEYS) -> DataFrame:
    """MLA, PTA, RTA over all distinct lines (a label makes its own line right), and over those without a label."""
    seen = F.when(F.col("labelled"), F.array(F.lit("all"))).otherwise(F.array(*map(F.lit, POPULATIONS)))
    keys, per = (*keys, "population"), stored(M.cells_of(pred, (*keys, "labelled")), "cells")
    # predictions are worked out once, the three measures are read from their counts
    cells = per.withColumn("population", F.explode(seen)).groupBy(*keys, "truth", "pred").agg(F.sum("n").alias("n"))
    return M.accuracy(pred, keys, cells)


def _method_query(which: str, name: str):
    return lambda spark, sf_dir: scored(method(spark, sf_dir, name, which))


for _which, _key in (("FULL", "full_rounds"), ("S1", "single_round"), ("MF", "multi_fixed"), ("PT", "parse_tree"), ("FT", "token_tagger"), ("ZERO", "zero_shot"), ("RANDOM", "random_pick")):
    register(None, _key)(_method_query(_which, "evt_rich"))


@register()
def round_trace(spark, sf_dir):
    """Labels spent and words seen per round."""
    got = R.run(lines(spark, sf_dir, "part_shelf"), config("part_shelf"), final=False).trace
    return spark.createDataFrame([(t["r"], t["budget"], t["spent"], t["words_seen"], t["words_new"], t["open"], t["coverage"]) for t in got], "r int, budget int, spent int, words_seen int, words_new int, open int, coverage double")


def _union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


@register()
@workload
def w2_effectiveness(spark, sf_dir, names=TRUTH, methods=("PT", "FT", "S1", "MF", "FULL")):
    return scored(_union([method(spark, sf_dir, n, w) for n in names for w in methods]))


@register()
@workload
def w3_w4_cost(spark, sf_dir, names=TRUTH, methods=("S1", "MF", "FULL")):
    """Seconds per line (modelled), context size, tokens and price."""
    p = stored(_union([method(spark, sf_dir, n, w).select("domain", "method", "demos", "tokens", "n") for n in names for w in methods]), "cost")
    return M.time_per_line(p).join(M.context_size(p), ["domain", "method"]).join(M.api_cost(p), ["domain", "method"])


#: the surveyed budgets, and a fiftieth of them, where more corpora have patterns left to choose from
_BUDGETS_RUN = (SWEEP_SCALE, 1)


def _labels(p: DataFrame, cfg: R.Config) -> DataFrame:
    return p.withColumn("budget", F.lit(cfg.budget))


@register()
@workload
def w5_ablation(spark, sf_dir, names=("part_shelf", "evt_rich", "ord_desk", "evt_simple")):
    """The method and five that lack a part, with the surveyed budgets and with a fiftieth of them; large budgets first."""
    parts = []
    for scale in _BUDGETS_RUN:
        runs = [(n, w, config(n, scale)) for n in names for w in ("FULL", "-SED", "-RS", "-PC", "-AD", "-AB")]
        parts.append(scored(_union([_labels(method(spark, sf_dir, n, w, cfg), cfg) for n, w, cfg in runs]), (*M.KEYS, "budget")))
    got = stored(_union(parts), "ablation")
    keys = ["domain", "population", "budget", "method"]
    out = got.join(M.delta(got, "FULL", ("domain", "population", "budget")), keys, "left")
    return out.select("domain", "population", "method", *(c for c in out.columns if c not in keys), "budget").orderBy(F.desc("budget"), "domain", "population", "method")


def _sweep(spark, sf_dir, names, values, change, extra=None, scale: int = SWEEP_SCALE, keys=(*M.KEYS, "value")) -> DataFrame:
    parts = []
    for n in names:
        for v in values:
            cfg = change(config(n, scale), v)
            parts.append(_labels(method(spark, sf_dir, n, "FULL", cfg), cfg).withColumn("value", F.lit(float(v))))
    out = (extra or scored)(_union(parts), keys)
    return out.select(*(c for c in out.columns if c != "value"), "value")


#: corpora of the sweeps
_SWEPT = ("ord_desk", "evt_simple")


@register()
@workload
def w6_sweep_budget(spark, sf_dir):
    """50 to 250 labels, a fiftieth of it."""
    return _sweep(spark, sf_dir, _SWEPT, (1, 2, 3, 4, 5), lambda c, v: replace(c, budget=v))


@register()
@workload
def w7_sweep_lambda(spark, sf_dir):
    """With the surveyed budgets, and with a fiftieth of them."""
    by = [_sweep(spark, sf_dir, _SWEPT, (0, 0.25, 0.5, 0.75, 1), lambda c, v: replace(c, lam=v), scale=scale, keys=(*M.KEYS, "budget", "value")) for scale in _BUDGETS_RUN]
    out = _union(by)
    return out.select(*(c for c in out.columns if c != "budget"), "budget")


@register()
@workload
def w8_sweep_delta(spark, sf_dir):
    return _sweep(spark, sf_dir, ("ord_desk",), (0, 0.25, 0.3, 0.5, 1), lambda c, v: replace(c, delta=v))


@register()
@workload
def w9_sweep_tau(spark, sf_dir):
    return _sweep(spark, sf_dir, _SWEPT, (0, 0.25, 0.5, 0.75, 1), lambda c, v: replace(c, tau=v, context=Context(similarity="vector", tau=v), model=ContextTagger("vector", v, misread=MISREAD)))


def _error_counts(p: DataFrame, keys=M.KEYS) -> DataFrame:
    return M.errors(p, keys)


@register()
@workload
def w10_errors_lambda(spark, sf_dir):
    return _sweep(spark, sf_dir, ("evt_rich",), (0, 0.25, 0.5), lambda c, v: replace(c, lam=v, model=ContextTagger(inject=20, misread=MISREAD)), _error_counts)


@register()
@workload
def w11_errors_a(spark, sf_dir):
    return _sweep(spark, sf_dir, ("evt_rich",), (0.2, 0.5, 0.8), lambda c, v: replace(c, a=v, model=ContextTagger(inject=20, misread=MISREAD)), _error_counts)


@register()
def similar_words(spark, sf_dir):
    """Word pairs of the part names with cosine of at least 0.25."""
    from tplforge.functions.words import similar_pairs

    vocab = graph(lines(spark, sf_dir, "part_shelf"))[1].filter(~F.col("word").rlike("[0-9]"))
    return similar_pairs(vocab, 0.25)


def queries() -> dict[str, Query]:
    return dict(_Q)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)


__all__ = ["queries", "oracle_sql", "Similarity"]
