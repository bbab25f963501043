"""Substring deduplication by relative Lempel-Ziv parsing.

A document is parsed against all text that comes before it (smaller doc_id, or
earlier in the document): a factor is a run of words copied from one place of
an earlier text. The parse goes from left to right: where a copy begins, the match
that reaches furthest becomes the factor, and the parse goes on behind it. Factors of
at least `window` words are the duplicate spans; what they cover is removed.

The reference is indexed in blocks, dealt by hash, that hold *seeds*: in every
window the k-gram with the least hash. Equal windows have equal seeds, so a
document meets all blocks that could hold a copy of it, and only those. The
windows that one seed stands for form a run; its *context* is the hash of all
words the run touches.
  1. A seed found once in the corpus has no copies: most seeds end here.
  2. Equal contexts are equal runs: all but the earliest match as they stand.
  3. Where one seed has several contexts, copies reach over some windows of a run
     and not over others - the boundaries of factors. There the windows of the
     earliest run of each context are looked up one by one.
Each document joins its matches along their diagonals (consecutive in the document and
in the source) and parses itself by them. The outcome is exact: windows are compared
by 128 bits of hash, and a window that crosses from one factor into the next was looked
up like any other.

Counts are reduced before they are shuffled and occurrences are only ever joined,
never gathered by seed, so a passage in a third of all documents has no one task.
What a task holds at a time is one document's matches, of which there are no more than
it has windows.

Null and empty texts have no words and stay as they are. Very long texts are parsed whole.
Of equal spans the one of the least doc_id, then of the first place, stays. doc_id is meant to be
unique; rows that repeat one are parsed as one document would be that holds either
text, and each keeps its own row. Rows without a doc_id are neither cut nor a source. An empty
table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tplforge.llm.common import FIRST, SECOND, byte_slices, delete, fresh_names, hash_words, mix, raw_bytes, scratch, stored, stored_at, texts

WINDOW = 20
GRAM = 8


def _runs(h: np.ndarray, counts: np.ndarray, window: int, gram: int):
    """Runs of windows with one seed: seed hash, context hash, text number, first window, number of windows."""
    n = len(h)
    if n < window:
        return [np.empty(0, t) for t in (np.uint64, np.uint64, np.int64, np.int64, np.int64)]
    doc = np.repeat(np.arange(len(counts)), counts)
    first = np.cumsum(counts) - counts
    sums = FIRST.prefix(h)
    grams = FIRST.windows(sums, gram)
    width = window - gram + 1
    views = np.lib.stride_tricks.sliding_window_view(np.append(grams, np.uint64(0)) if len(grams) < n - gram + 1 else grams, width)
    seed_at = np.arange(n - window + 1) + views[: n - window + 1].argmin(axis=1)
    ok = doc[: n - window + 1] == doc[window - 1 :]
    w = np.flatnonzero(ok)
    if not len(w):
        return _runs(np.empty(0, np.uint64), counts, window, gram)
    p = seed_at[w]
    cut = np.flatnonzero(np.append(True, (p[1:] != p[:-1]) | (w[1:] != w[:-1] + 1)))
    a, last = w[cut], w[np.append(cut[1:], len(w)) - 1]
    s = p[cut]
    context = FIRST.ranges(sums, a, last + window)
    context = mix(context + ((s - a) * 64 + (last - a)).astype(np.uint64))
    return grams[s], context, doc[a], a - first[doc[a]], last - a + 1


def seeds(docs: DataFrame, window: int, gram: int) -> DataFrame:
    """seed, context, doc_id, start, n of every run of every text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in byte_slices(batches, "text"):
            seed, context, doc, start, n = _runs(*hash_words(raw_bytes(b, "text")), window, gram)
            ids = b.column("doc_id").take(pa.array(doc))
            yield pa.record_batch(
                [pa.array(seed.view(np.int64)), pa.array(context.view(np.int64)), ids, pa.array(start.astype(np.int32)), pa.array(n.astype(np.int32))],
                names=["seed", "context", "doc_id", "start", "n"],
            )

    return docs.filter("text IS NOT NULL").mapInArrow(run, "seed long, context long, doc_id long, start int, n int")


def _windows(docs: DataFrame, checks: DataFrame, window: int) -> DataFrame:
    """wa, wb, doc_id, start: hashes of the windows of the runs in checks(doc_id, start, n)."""
    listed = checks.groupBy("doc_id").agg(F.collect_list(F.struct("start", "n")).alias("runs"))
    joined = docs.join(listed, "doc_id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in byte_slices(batches, "text"):
            h, counts = hash_words(raw_bytes(b, "text"))
            first = np.cumsum(counts) - counts
            runs = b.column("runs")
            flat = runs.flatten()
            lens = np.diff(runs.offsets.to_numpy())
            of = np.repeat(np.arange(b.num_rows), lens)
            start = flat.field("start").to_numpy(zero_copy_only=False).astype(np.int64)
            n = flat.field("n").to_numpy(zero_copy_only=False).astype(np.int64)
            of, each = np.repeat(of, n), np.repeat(start, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            inside = each + window <= counts[of]
            of, each = of[inside], each[inside]
            at = first[of] + each
            wa, wb = (r.ranges(r.prefix(h), at, at + window) for r in (FIRST, SECOND))
            yield pa.record_batch(
                [pa.array(wa.view(np.int64)), pa.array(wb.view(np.int64)), b.column("doc_id").take(pa.array(of)), pa.array(each.astype(np.int32))],
                names=["wa", "wb", "doc_id", "start"],
            )

    return joined.select("doc_id", "text", "runs").mapInArrow(run, "wa long, wb long, doc_id long, start int")


def matches(docs: DataFrame, window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """doc_id, start, n, src_id, src_start: windows start..start+n-1 copy those from src_start of the earlier text."""
    spark, docs = docs.sparkSession, docs.filter("doc_id IS NOT NULL")
    root = scratch(spark, "substring")
    all_seeds = seeds(docs, window, gram)
    # counts are stored before they are joined: both sides of each join are then plain exchanges, which
    # adaptive execution splits where a seed or window is hot
    shared = stored_at(all_seeds.groupBy("seed").agg(F.count("*").alias("times")).filter("times > 1").select("seed"), f"{root}/shared")
    found = stored_at(all_seeds.join(shared, "seed"), f"{root}/seeds")
    by_context = found.groupBy("seed", "context").agg(F.min(F.struct("doc_id", "start", "n")).alias("src"), F.count("*").alias("times"))
    by_context = stored_at(by_context, f"{root}/contexts")
    copied = by_context.filter("times > 1").select("seed", "context", F.col("src.doc_id").alias("src_id"), F.col("src.start").alias("src_start"))
    whole = found.join(copied, ["seed", "context"]).filter("doc_id <> src_id OR start <> src_start").select("doc_id", "start", "n", "src_id", "src_start")
    # a seed with several contexts: their windows one by one
    several = stored_at(by_context.groupBy("seed").agg(F.count("*").alias("contexts")).filter("contexts > 1").select("seed"), f"{root}/several")
    checks = by_context.join(several, "seed").select("src.doc_id", "src.start", "src.n")
    windows = stored_at(_windows(docs, checks, window), f"{root}/windows")
    earliest = windows.groupBy("wa", "wb").agg(F.min(F.struct("doc_id", "start")).alias("src"), F.count("*").alias("times")).filter("times > 1")
    earliest = stored_at(earliest.select("wa", "wb", F.col("src.doc_id").alias("src_id"), F.col("src.start").alias("src_start")), f"{root}/earliest")
    single = windows.join(earliest, ["wa", "wb"]).filter("doc_id <> src_id OR start <> src_start").select("doc_id", "start", F.lit(1).alias("n"), "src_id", "src_start")
    out = stored(whole.unionByName(single), "substring-matches")
    delete(spark, root)
    return out


def parse(start: np.ndarray, n: np.ndarray, src: np.ndarray, src_start: np.ndarray, window: int) -> list[tuple[int, int, int, int]]:
    """The greedy factors of one document, from its matches (n windows each): start, length in words, source, its start."""
    # matches on one diagonal that touch or overlap are one
    order = np.lexsort((start, src_start - start, src))
    start, end, src, shift = start[order], (start + n)[order], src[order], (src_start - start)[order]
    reach = end.copy()
    new = np.ones(len(start), bool)
    lines = np.append(np.flatnonzero((src[1:] != src[:-1]) | (shift[1:] != shift[:-1])) + 1, len(start))
    at = 0
    for to in lines.tolist():
        np.maximum.accumulate(end[at:to], out=reach[at:to])
        new[at + 1 : to] = start[at + 1 : to] > reach[at : to - 1]
        at = to
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(start)) - 1
    begin, stop, src, shift = start[first], reach[last], src[first], shift[first]
    # from left to right: of the matches that cover the next copied window, the one that reaches furthest
    out, at, here, best = [], 0, 0, None
    order = np.lexsort((shift, src, -stop, begin)).tolist()
    while True:
        while at < len(order) and begin[order[at]] <= here:
            i = order[at]
            at += 1
            if best is None or (stop[i], -src[i], -shift[i]) > (stop[best], -src[best], -shift[best]):
                best = i
        if best is not None and stop[best] > here:
            out.append((int(here), int(stop[best] - here + window - 1), int(src[best]), int(here + shift[best])))
            here = int(stop[best])
        elif at < len(order):
            here = int(begin[order[at]])
        else:
            return out


def dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """doc_id, text, kept_text (kept words joined by one space), n_words, n_removed, factors of every row."""
    docs = texts(docs, id_col, text_col)
    runs = matches(docs, window, gram)
    listed = runs.groupBy("doc_id").agg(F.collect_list(F.struct("start", "n", "src_id", "src_start")).alias("runs"))
    joined = docs.join(listed, "doc_id", "left").select("doc_id", "text", "runs")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in byte_slices(batches, "text"):
            kept, total, removed, factors = [], [], [], []
            runs = b.column("runs")
            for i, text in enumerate(raw_bytes(b, "text")):
                words = text.split()
                total.append(len(words))
                found = runs[i].values
                if found is None or not len(found):
                    kept.append(b" ".join(words).decode())
                    removed.append(0)
                    factors.append([])
                    continue
                parsed = parse(*(found.field(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("start", "n", "src_id", "src_start")), window)
                left, at = [], 0
                for s, m, _, _ in parsed:
                    left += words[at:s]
                    at = max(at, s + m)
                left += words[at:]
                kept.append(b" ".join(left).decode())
                removed.append(len(words) - len(left))
                factors.append([{"start": s, "length": m, "src_id": d, "src_start": t} for s, m, d, t in parsed])
            yield pa.record_batch(
                [b.column("doc_id"), b.column("text"), pa.array(kept, pa.string()), pa.array(total, pa.int64()), pa.array(removed, pa.int64()), pa.array(factors, _FACTORS)],
                names=["doc_id", "text", "kept_text", "n_words", "n_removed", "factors"],
            )

    return joined.mapInArrow(run, "doc_id long, text string, kept_text string, n_words long, n_removed long, factors array<struct<start int, length int, src_id long, src_start int>>")


_FACTORS = pa.list_(pa.struct([("start", pa.int32()), ("length", pa.int32()), ("src_id", pa.int64()), ("src_start", pa.int32())]))


def contract(docs: DataFrame) -> DataFrame:
    return dedup(docs).select("doc_id", "n_words", "n_removed", F.sha2(F.col("kept_text"), 256).alias("kept_sha256"))


#: the contract by all windows; doc_id is unique there
ORACLE = r"""
WITH l AS (SELECT doc_id, list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0d]+'), lambda x: x <> '') AS ws FROM documents),
w AS (SELECT doc_id, unnest(ws) AS w, generate_subscripts(ws, 1) AS pos FROM l),
s AS (SELECT doc_id, pos, sha256(string_agg(w, ' ') OVER v) AS h, count(*) OVER v AS n FROM w WINDOW v AS (PARTITION BY doc_id ORDER BY pos ROWS BETWEEN CURRENT ROW AND 19 FOLLOWING)),
f AS (SELECT doc_id, pos, row_number() OVER (PARTITION BY h ORDER BY doc_id, pos) > 1 AS again FROM s WHERE n = 20),
g AS (SELECT w.doc_id, w.pos, w.w, coalesce(max(f.again::INT) OVER (PARTITION BY w.doc_id ORDER BY w.pos ROWS BETWEEN 19 PRECEDING AND CURRENT ROW), 0) AS gone FROM w LEFT JOIN f USING (doc_id, pos)),
k AS (SELECT doc_id, count(*) AS n_words, sum(gone)::BIGINT AS n_removed, string_agg(w, ' ' ORDER BY pos) FILTER (WHERE gone = 0) AS kept FROM g GROUP BY 1)
SELECT l.doc_id, coalesce(n_words, 0) AS n_words, coalesce(n_removed, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM l LEFT JOIN k USING (doc_id)
"""


def cut_repeats(docs: DataFrame) -> DataFrame:
    """docs with repeated spans cut out; documents that are nothing but repeats go. doc_id is taken as unique.

    Where docs has a column n_chars, it is counted anew for what was cut.
    """
    key, left = fresh_names(docs, "cut_id", "cut_text")
    cut = dedup(docs).filter("n_removed > 0").select(F.col("doc_id").alias(key), F.col("kept_text").alias(left))
    joined = docs.join(cut, docs["doc_id"] == F.col(key), "left").filter(F.col(key).isNull() | (F.col(left) != ""))
    new = {"text": F.coalesce(F.col(left), docs["text"])}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.when(F.col(key).isNull(), docs["n_chars"]).otherwise(F.length(left)).cast(docs.schema["n_chars"].dataType)
    return joined.select(*(new.get(c, docs[c]).alias(c) for c in docs.columns))


def brute_force(rows: list[tuple[int, str | None]], window: int = WINDOW) -> list[tuple[int, int, int, str]]:
    """What contract() has to return, by a dictionary of all windows (for tests)."""
    out, seen = [], set()
    for doc_id, text in sorted(rows, key=lambda r: r[0]):
        words = (text or "").encode().split()
        gone = [False] * len(words)
        for i in range(len(words) - window + 1):
            w = tuple(words[i : i + window])
            if w in seen:
                gone[i : i + window] = [True] * window
            seen.add(w)
        kept = b" ".join(w for w, g in zip(words, gone, strict=True) if not g)
        out.append((doc_id, len(words), sum(gone), hashlib.sha256(kept).hexdigest()))
    return out
