"""Near copies: texts whose sets of word shingles have a Jaccard similarity of at least a bound.

Two sources of candidate pairs, one exact check. SimHash fingerprints of the sets
are joined by the trie of `simhash`, which links close copies cheaply; texts at the
bound itself differ in too many bits for it. What it leaves is found by an exact
join. Texts with equal sets become one row first. All sets are put in one order,
common shingles last; two sets within the bound then share a shingle among the first
n - ceil(bound * n) + 1 of each (prefix filter), and the first one they share leaves
room for enough others (position filter). What is common is guessed from a sample:
the guess decides how large buckets get, never what is found.

One sort by shingle drops all shingles that a single text has, and pairs neighbours by
size. What is left is sorted again in some orders of chance, one for each class of
shingles, so that a text of a large group meets a few others by chance and not the same
ones everywhere; with the trie's links these pairs join most of a group of copies. Then the
buckets that still hold several components give all pairs between different ones. So a
group costs rows and not pairs. Candidates are compared by bit vectors before anything else: a bit is
the parity of how many shingles fall on it, so two vectors differ in no more places
than the sets have shingles that are not shared. The rest is compared by whole sets,
made again from the texts for the documents that need it.

Texts without words have the empty set and are one group.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tplforge.llm.common import FIRST, byte_slices, delete, hash_words, mix, raw_bytes, scratch, stored, stored_at, texts
from tplforge.llm.components import components

#: one document in so many is looked at for common shingles
SAMPLE = 64
#: common shingles that are held, at most
COMMON = 50_000
#: slots of the filter of documents to compare, in words of 32 bits
FILTER = 1 << 19
#: bits of a set's parity vector, a power of 2
PARITY = 2048
#: bits of the vector that buckets compare pairs by, a power of 2 below PARITY
FOLDED = 512
#: orders of chance in which the texts of a bucket are paired with the next
ORDERS = 8
#: pairs of a bucket made at a time
BLOCK = 1 << 16
#: bytes of texts whose shingles are worked on at a time
STEP_BYTES = 1 << 20
BITS = 64
_EPS = 1e-9


def shingle_sets(raw: list[bytes], k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Text number and hash of each text's distinct k-word shingles (A-Z as a-z), by text and hash; sizes.

    A text of fewer words has its whole sequence as its only shingle.
    """
    h, counts = hash_words(raw, lower=True)
    n = len(raw)
    doc = np.repeat(np.arange(n), counts)
    sums, first = FIRST.prefix(h), np.cumsum(counts) - counts
    wins = FIRST.windows(sums, k)
    at = np.flatnonzero(doc[: len(wins)] == doc[k - 1 :]) if len(wins) else np.empty(0, np.int64)
    short = np.flatnonzero((counts > 0) & (counts < k))
    hs = np.concatenate([wins[at], mix(FIRST.ranges(sums, first[short], first[short] + counts[short]) + counts[short].astype(np.uint64))])
    ds = np.concatenate([doc[at], short])
    order = np.lexsort((hs, ds))
    hs, ds = hs[order], ds[order]
    new = np.ones(len(hs), bool)
    new[1:] = (hs[1:] != hs[:-1]) | (ds[1:] != ds[:-1])
    hs, ds = hs[new], ds[new]
    return ds, hs, np.bincount(ds, minlength=n)


def _reduce(values: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Sums of consecutive runs of the given sizes (along the first axis); 0 for empty runs."""
    out = np.zeros((len(sizes), *values.shape[1:]), values.dtype)
    some = np.flatnonzero(sizes)
    if len(some):
        out[some] = np.add.reduceat(values, (np.cumsum(sizes) - sizes)[some], axis=0, dtype=values.dtype)
    return out


def set_fingerprints(hs: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """SimHash of each set: a bit is 1 where more than half of its hashes have it."""
    bits = np.unpackbits(hs.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    on = np.zeros((len(sizes), BITS), bool)
    some = np.flatnonzero(sizes)
    if len(some):
        on[some] = np.add.reduceat(bits, (np.cumsum(sizes) - sizes)[some], axis=0, dtype=np.int32) * 2 > sizes[some, None]
    return np.packbits(on, axis=1, bitorder="little").view("<u8").ravel()


def _lists(sizes: np.ndarray, values: np.ndarray) -> pa.Array:
    ends = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(values))


def _common(docs: DataFrame, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Shingles seen more than once in a sample of documents, and how often; sorted by shingle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in byte_slices(batches, "text", STEP_BYTES):
            yield pa.record_batch([pa.array(shingle_sets(raw_bytes(b, "text"), k)[1].view(np.int64))], names=["h"])

    some = docs.filter(F.pmod(F.xxhash64("doc_id"), F.lit(SAMPLE)) == 0).mapInArrow(run, "h long")
    rows = some.groupBy("h").count().filter("count > 1").orderBy(F.desc("count"), "h").limit(COMMON).collect()
    h, n = np.array([r["h"] for r in rows], np.int64).view(np.uint64), np.array([r["count"] for r in rows], np.int64)
    order = np.argsort(h)
    return h[order], n[order]


def _prefixes(docs: DataFrame, k: int, bound: float) -> DataFrame:
    """doc_id, key (the whole set's hash), n, fp, the set's first shingles in the common order, and its parities."""
    held = docs.sparkSession.sparkContext.broadcast(_common(docs, k))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, seen = held.value
        for b in byte_slices(batches, "text", STEP_BYTES):
            ds, hs, n = shingle_sets(raw_bytes(b, "text"), k)
            key = _reduce(mix(hs ^ np.uint64(0x165667B19E3779F9)), n)
            odd = np.bincount(ds * PARITY + (hs & np.uint64(PARITY - 1)).astype(np.int64), minlength=len(n) * PARITY).reshape(-1, PARITY) & 1
            odd = np.packbits(odd.astype(bool), axis=1)
            low = np.bitwise_xor.reduce(odd.reshape(len(n), PARITY // FOLDED, FOLDED // 8), axis=1)
            fp = set_fingerprints(hs, n)
            freq = np.zeros(len(hs), np.int64)
            if len(known):
                at = np.minimum(np.searchsorted(known, hs), len(known) - 1)
                freq = np.where(known[at] == hs, seen[at], 0)
            order = np.lexsort((hs, freq, ds))
            size = np.where(n > 0, n - np.ceil(bound * n - _EPS).astype(np.int64) + 1, 0)
            rank = np.arange(len(hs)) - np.repeat(np.cumsum(n) - n, n)
            first = hs[order][rank < np.repeat(size, n)]
            yield pa.record_batch(
                [b.column("doc_id"), pa.array(key.view(np.int64)), pa.array(n.astype(np.int32)), pa.array(fp.view(np.int64)), _lists(size, first.view(np.int64)), pa.array([x.tobytes() for x in odd], pa.binary()), pa.array([x.tobytes() for x in low], pa.binary())],
                names=["doc_id", "key", "n", "fp", "first", "odd", "low"],
            )

    return docs.mapInArrow(run, "doc_id long, key long, n int, fp long, first array<long>, odd binary, low binary")


def _open(n: str, pos: str, n_b: str, pos_b: str, bound: float):
    """What sizes and positions say of a pair that shares a shingle at these places of its prefixes."""
    small, large = F.least(n, n_b), F.greatest(n, n_b)
    room = F.least(F.col(n) - F.col(pos), F.col(n_b) - F.col(pos_b))
    return (small >= bound * large - _EPS) & (room * (1 + bound) >= bound * (small + large) - _EPS)


def _shared(one: DataFrame) -> DataFrame:
    """h, rep, n, pos of the prefix shingles that several sets have, each with the next larger set that has it."""
    rows = one.select("rep", "n", F.posexplode("first").alias("pos", "h"))
    by = W.partitionBy("h").orderBy("n", "rep")
    with_next = rows.withColumn("next", F.lead(F.struct("rep", "n", "pos")).over(by)).withColumn("last", F.lag("rep").over(by))
    return with_next.filter("next IS NOT NULL OR last IS NOT NULL").select("h", "rep", "n", "pos", "next")


def _beside(shared: DataFrame, bound: float) -> DataFrame:
    """Pairs (a, b) of neighbours in a bucket: by size, and in the order of chance that the bucket's shingle has."""
    by_chance = W.partitionBy("h").orderBy(F.xxhash64(F.pmod("h", F.lit(ORDERS)), "rep"), "rep")
    chance = shared.select("h", "rep", "n", "pos").withColumn("next", F.lead(F.struct("rep", "n", "pos")).over(by_chance))
    pairs = shared.select("rep", "n", "pos", "next").union(chance.select("rep", "n", "pos", "next")).filter("next IS NOT NULL")
    pairs = pairs.select("rep", "n", "pos", F.col("next.rep").alias("rep_b"), F.col("next.n").alias("n_b"), F.col("next.pos").alias("pos_b"))
    return pairs.filter(_open("n", "pos", "n_b", "pos_b", bound)).select(F.least("rep", "rep_b").alias("a"), F.greatest("rep", "rep_b").alias("b"))


def _bucket_pairs(n: np.ndarray, pos: np.ndarray, rep: np.ndarray, comp: np.ndarray, odd: np.ndarray, bound: float) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs of one bucket, of different components, that sizes, positions and parities leave open."""
    order = np.lexsort((rep, comp))
    n, pos, rep, comp, odd = n[order], pos[order], rep[order], comp[order], odd[order]
    m = len(n)
    start = np.searchsorted(comp, comp, side="right")
    count = m - start
    upto = np.cumsum(count)
    at = 0
    while at < m:
        to = max(at + 1, int(np.searchsorted(upto, (upto[at - 1] if at else 0) + BLOCK, side="right")))
        c = count[at:to]
        x = np.repeat(np.arange(at, to), c)
        y = start[x] + np.arange(c.sum()) - np.repeat(np.cumsum(c) - c, c)
        room = np.minimum(n[x] - pos[x], n[y] - pos[y])
        both, small, large = n[x] + n[y], np.minimum(n[x], n[y]), np.maximum(n[x], n[y])
        ok = np.flatnonzero((small >= bound * large - _EPS) & (room * (1 + bound) >= bound * both - _EPS))
        x, y, both = x[ok], y[ok], both[ok]
        ok = np.bitwise_count(odd[x] ^ odd[y]).sum(axis=1, dtype=np.int64) * (1 + bound) <= both * (1 - bound) + _EPS * both
        if ok.any():
            x, y = x[ok], y[ok]
            yield np.minimum(rep[x], rep[y]), np.maximum(rep[x], rep[y])
        at = to


def _between(rows: DataFrame, bound: float) -> DataFrame:
    """rows(h, rep, n, pos, comp, odd) -> distinct pairs (a, b) of different components that share a shingle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, held = None, []

        def pairs():
            columns = [np.concatenate(x) for x in zip(*held, strict=True)]
            if len(columns[0]) > 1:
                yield from _bucket_pairs(*columns, bound)

        def out(found):
            return pa.record_batch([pa.array(np.concatenate(x)) for x in zip(*found, strict=True)], names=["a", "b"])

        found, size = [], 0
        for batch in batches:
            if not batch.num_rows:
                continue
            h, *rest = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("h", "n", "pos", "rep", "comp"))
            rest.append(np.frombuffer(b"".join(batch.column("odd").to_pylist()), np.uint64).reshape(batch.num_rows, -1))
            cut = [0, *(np.flatnonzero(h[1:] != h[:-1]) + 1).tolist(), len(h)]
            for lo, hi in zip(cut, cut[1:], strict=False):
                if held and h[lo] != key:
                    for p in pairs():
                        found.append(p)
                        size += len(p[0])
                        if size > BLOCK:
                            yield out(found)
                            found, size = [], 0
                    held = []
                key = h[lo]
                held.append([x[lo:hi] for x in rest])
        if held:
            for p in pairs():
                found.append(p)
                size += len(p[0])
                if size > BLOCK:
                    yield out(found)
                    found, size = [], 0
        if found:
            yield out(found)

    return rows.select("h", "n", "pos", "rep", "comp", "odd").repartition("h").sortWithinPartitions("h").mapInArrow(run, "a long, b long").distinct()


def _possible(pairs: DataFrame, one: DataFrame, bound: float) -> DataFrame:
    """The pairs whose parities do not rule them out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            x, y = (np.frombuffer(b"".join(b.column(c).to_pylist()), np.uint64).reshape(b.num_rows, -1) for c in ("odd_a", "odd_b"))
            both = b.column("n_a").to_numpy().astype(np.int64) + b.column("n_b").to_numpy()
            ok = np.bitwise_count(x ^ y).sum(axis=1, dtype=np.int64) * (1 + bound) <= both * (1 - bound) + _EPS * both
            yield b.select(["a", "b"]).filter(pa.array(ok))

    side = lambda c: one.select(F.col("rep").alias(c), F.col("n").alias(f"n_{c}"), F.col("odd").alias(f"odd_{c}"))
    return pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "n_a", "n_b", "odd_a", "odd_b").mapInArrow(run, "a long, b long").distinct()


def _similar(docs: DataFrame, pairs: DataFrame, one: DataFrame, k: int, bound: float, name: str) -> DataFrame:
    """The pairs (a, b) whose whole sets are within the bound."""
    pairs = stored_at(_possible(pairs, one, bound), f"{name}-pairs")
    nodes = pairs.select(F.explode(F.array("a", "b")).alias("doc_id"))
    slot = F.pmod(F.xxhash64("doc_id"), F.lit(FILTER * 32))
    bits = np.zeros(FILTER, np.int64)
    for r in nodes.select(slot.alias("s")).groupBy(F.expr("s div 32").alias("at")).agg(F.expr("bit_or(shiftleft(1L, cast(s % 32 as int)))").alias("v")).toLocalIterator():  # at most FILTER rows
        bits[r["at"]] = r["v"]
    held = docs.sparkSession.sparkContext.broadcast(bits)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            s = batch.column("slot").to_numpy(zero_copy_only=False)
            wanted = batch.filter(pa.array((held.value[s // 32] >> (s % 32)) & 1 == 1)) if len(s) else batch
            for b in byte_slices([wanted], "text", STEP_BYTES):
                _, hs, n = shingle_sets(raw_bytes(b, "text"), k)
                yield pa.record_batch([b.column("doc_id"), _lists(n, hs.view(np.int64))], names=["doc_id", "s"])

    sets = docs.filter("doc_id IS NOT NULL").select("doc_id", "text", slot.alias("slot")).mapInArrow(run, "doc_id long, s array<long>")
    sets = stored_at(sets.join(nodes.distinct(), "doc_id", "left_semi"), f"{name}-sets")
    both = pairs.join(sets.select(F.col("doc_id").alias("a"), F.col("s").alias("sa")), "a").join(sets.select(F.col("doc_id").alias("b"), F.col("s").alias("sb")), "b")
    common = F.size(F.array_intersect("sa", "sb"))
    return stored_at(both.filter(common / (F.size("sa") + F.size("sb") - common) >= bound).select("a", "b"), f"{name}-links")


def similar_components(docs: DataFrame, k: int, bound: float, budget: int) -> DataFrame:
    """doc_id and component_id (the least doc_id that similar pairs lead to) of every row of docs(doc_id, text).

    budget: bits within which the trie links fingerprints. Rows that repeat a doc_id are taken as texts of one document
    (their links are its links); rows without one have no component and are left out. The result is a stored table; what
    it was made from is deleted.
    """
    from tplforge.llm.simhash import near_links

    spark, docs = docs.sparkSession, texts(docs)
    root = scratch(spark, "similar")
    seen = stored_at(_prefixes(docs, k, bound).filter("doc_id IS NOT NULL"), f"{root}/prefixes")
    one = stored_at(seen.groupBy("key").agg(F.min_by(F.struct("n", "fp", "first", "odd", "low"), "doc_id").alias("x"), F.min("doc_id").alias("rep")).select("key", "rep", "x.n", "x.fp", "x.first", "x.odd", "x.low"), f"{root}/distinct")
    # close copies by their fingerprints: the trie's links, and sets of one fingerprint
    fps = stored_at(one.groupBy("fp").agg(F.min("rep").alias("rep")), f"{root}/fingerprints")
    same = one.select("fp", F.col("rep").alias("b")).join(fps.withColumnRenamed("rep", "a"), "fp").filter("a <> b").select("a", "b")
    tried = near_links(fps, budget).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    # what the fingerprints miss, by shared shingles
    shared = stored_at(_shared(one), f"{root}/shared")
    beside = _beside(shared, bound)
    links = _similar(docs, tried.union(same).union(beside).distinct(), one, k, bound, f"{root}/near")
    label = components(links, "similar-first").select(F.col("node").alias("rep"), "label")
    low = one.select("rep", F.col("low").alias("odd"))
    named = shared.select("h", "rep", "n", "pos").join(low, "rep").join(label, "rep", "left").withColumn("comp", F.coalesce("label", "rep"))
    # buckets of one component have no pairs left
    several = stored_at(named.groupBy("h").agg(F.min("comp").alias("least"), F.max("comp").alias("most")).filter("least < most").select("h"), f"{root}/several")
    links = links.union(_similar(docs, _between(named.join(several, "h"), bound), one, k, bound, f"{root}/rest"))
    found = components(links, "similar-components")
    of = one.join(found.withColumnRenamed("node", "rep"), "rep", "left").select("key", F.coalesce("label", "rep").alias("component_id"))
    out = stored(seen.select("doc_id", "key").join(of, "key").select("doc_id", "component_id"), "similar")
    delete(spark, root)
    return out
