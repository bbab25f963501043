"""SimHash near-duplicates by a self-join of binary tries.

Fingerprints that are equal become one row first, so groups of exact copies
have no weight. Two fingerprints that differ in at most k bits agree in one of
k+1 blocks of bits. Rotated so that a block comes first, the fingerprints with
the same value of it are one subtree of a binary trie, at whose root no
difference has been spent yet; such subtrees are what tasks work on. Within one,
node pairs are traversed together, the differing bits of their paths add up, and
a pair is dropped as soon as they exceed the budget. The budget deepens from 0:
what small budgets link need not be compared again, because a pair of nodes whose
leaves all belong to one component is dropped too. Only the links of a spanning
forest leave a task: copies and near copies are never expanded into all pairs.

A subtree of many fingerprints is dealt by its next trie bits into nodes, and every pair
of nodes whose bits differ within the budget is work of its own (`SUBTREE` fingerprints
at a node, about): no task holds a hot subtree. A subtree is held as a sorted array of
8-byte numbers, its nodes as ranges of that array, and the pairs of a level are worked on
together, in blocks of bounded size.

Texts without words (null, empty, blank) have fingerprint zero and link like
any other. Rows that repeat a doc_id are kept, each with its own fingerprint. Rows without
a doc_id are kept and link to none but those of equal fingerprint; a component's id is the least doc_id of
the others. Fingerprints that tie are one. Texts of any length are whole sequences of shingles. An empty
table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tplforge.llm.common import byte_slices, fresh_names, raw_bytes, stored, texts
from tplforge.llm.components import components
from tplforge.llm.similar_texts import similar_components

BITS = 64
SHINGLE = 4
LINK_BITS = 4
#: what the pipeline's stage calls a near copy; SHINGLE and LINK_BITS bind the op10 query
STAGE_SHINGLE = 5
STAGE_SIMILARITY = 0.8
SEED = 42
#: node pairs worked on at a time
BLOCK = 1 << 18
#: subtrees up to this size are compared leaf by leaf
LEAVES = 8
#: fingerprints at a node that a task takes on, and trie bits by which a larger subtree is dealt, at most
SUBTREE, SPLIT_BITS = 1 << 16, 12
_LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))


def shingle_hashes(text: bytes, k: int = SHINGLE) -> list[int]:
    """XXH64 of the k-word shingles of a lower-cased text; of the whole sequence if it has fewer words."""
    words = text.translate(_LOWER).split()
    if not words:
        return []
    line = b" ".join(words)
    if len(words) <= k:
        return [xxhash.xxh64_intdigest(line, SEED)]
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    starts = [0, *ends[:-k].tolist()]
    digest = xxhash.xxh64_intdigest
    return [digest(line[a:b], SEED) for a, b in zip(starts, (ends[k - 1 :] - 1).tolist(), strict=True)]


def fingerprints(raw: list[bytes], k: int = SHINGLE) -> np.ndarray:
    """A bit is 1 where more than half of a text's shingle hashes have it."""
    out = np.zeros(len(raw), np.uint64)
    for i, t in enumerate(raw):
        h = shingle_hashes(t, k)
        if not h:
            continue
        bits = np.unpackbits(np.array(h, "<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        on = bits.sum(axis=0, dtype=np.int64) * 2 > len(h)
        out[i] = np.packbits(on, bitorder="little").view("<u8")[0]
    return out


def fingerprint_table(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = SHINGLE) -> DataFrame:
    """doc_id and fp (the 64 bits as a signed long) of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in byte_slices(batches, "text"):
            yield pa.record_batch([b.column("doc_id"), pa.array(fingerprints(raw_bytes(b, "text"), k).view(np.int64))], names=["doc_id", "fp"])

    return texts(docs, id_col, text_col).mapInArrow(run, "doc_id long, fp long")


class Forest:
    """Components of leaves 0..n-1, relabelled as links arrive in bulk."""

    def __init__(self, n: int):
        self.label = np.arange(n)

    def link(self, a: np.ndarray, b: np.ndarray) -> None:
        while True:
            la, lb = self.label[a], self.label[b]
            differ = la != lb
            if not differ.any():
                return
            a, b, la, lb = a[differ], b[differ], la[differ], lb[differ]
            up = np.arange(len(self.label))
            np.minimum.at(up, np.maximum(la, lb), np.minimum(la, lb))
            while True:
                further = up[up]
                if (further == up).all():
                    break
                up = further
            self.label = up[self.label]


def _popcount(x: np.ndarray) -> np.ndarray:
    return np.bitwise_count(x).astype(np.int64)


def _traverse(keys: np.ndarray, budget: int, forest: Forest, top: tuple[int, np.ndarray]) -> None:
    """Link all leaf pairs within the budget, save those already in one component.

    top: the bit to begin with, and a node pair: its two ranges of keys and the bits they differ in above.
    """
    stack = [top]
    while stack:
        bit, pairs = stack.pop()
        if len(pairs) > BLOCK:
            stack += [(bit, pairs[i : i + BLOCK]) for i in range(0, len(pairs), BLOCK)]
            continue
        a0, a1, b0, b1, _ = pairs.T
        # drop pairs of nodes that lie in one component already
        low = np.concatenate([[0], np.cumsum(forest.label[1:] != forest.label[:-1])])
        whole = (low[a1 - 1] == low[a0]) & (low[b1 - 1] == low[b0]) & (forest.label[a0] == forest.label[b0])
        pairs = pairs[~whole]
        if not len(pairs):
            continue
        a0, a1, b0, b1, _ = pairs.T
        small = ((a1 - a0 <= LEAVES) & (b1 - b0 <= LEAVES)) | (bit < 0)
        if small.any():
            _leaves(keys, budget, forest, pairs[small])
            pairs = pairs[~small]
        if not len(pairs):
            continue
        a0, a1, b0, b1, d = pairs.T
        # within a node all higher bits are equal: its split is where this bit turns 1
        am, bm = _split(keys, a0, a1, bit), _split(keys, b0, b1, bit)
        same = (a0 == b0) & (a1 == b1)
        nxt = [
            np.stack([a0, am, b0, bm, d], 1),
            np.stack([am, a1, bm, b1, d], 1),
            np.stack([a0, am, bm, b1, d + 1], 1),
            np.stack([am, a1, b0, bm, d + 1], 1)[~same],
        ]
        p = np.concatenate(nxt)
        p = p[(p[:, 0] < p[:, 1]) & (p[:, 2] < p[:, 3]) & (p[:, 4] <= budget)]
        if len(p):
            stack.append((bit - 1, p))


def _split(keys: np.ndarray, lo: np.ndarray, hi: np.ndarray, bit: int) -> np.ndarray:
    top = (keys[lo] >> np.uint64(bit)) | np.uint64(1)
    return np.clip(np.searchsorted(keys, top << np.uint64(bit)), lo, hi)


def _leaves(keys: np.ndarray, budget: int, forest: Forest, pairs: np.ndarray) -> None:
    a0, a1, b0, b1, _ = pairs.T
    na, nb = a1 - a0, b1 - b0
    for at in range(0, len(pairs), BLOCK // 16):
        s = slice(at, at + BLOCK // 16)
        n = na[s] * nb[s]
        of = np.repeat(np.arange(len(n)), n)
        j = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        x, y = a0[s][of] + j // nb[s][of], b0[s][of] + j % nb[s][of]
        ok = (x < y) | (y < x)
        x, y = x[ok], y[ok]
        near = _popcount(keys[x] ^ keys[y]) <= budget
        if near.any():
            forest.link(x[near], y[near])


def trie_components(fp: np.ndarray, budget: int, split: int = 0) -> np.ndarray:
    """For distinct fingerprints: the place of the least member of each one's component.

    split: the fingerprints are those of one or two nodes that many bits below the root; of two nodes, only pairs
    between them are compared.
    """
    order = np.argsort(fp)
    keys = fp[order]
    n, forest = len(fp), Forest(len(fp))
    mid, apart = n, 0
    if split:
        node = keys >> np.uint64(BITS - split)
        if node[0] != node[-1]:
            mid, apart = int(np.searchsorted(node, node[-1])), int(np.bitwise_count(node[0] ^ node[-1]))
    if n <= 64:
        x, y = np.triu_indices(n, 1)
        near = (_popcount(keys[x] ^ keys[y]) <= budget) & ((mid == n) | ((x < mid) & (y >= mid)))
        forest.link(x[near], y[near])
    else:
        pair = np.array([[0, n, 0, n, 0]] if mid == n else [[0, mid, mid, n, apart]])
        for b in range(max(1, apart), budget + 1):
            _traverse(keys, b, forest, (BITS - 1 - split, pair))
    root = np.empty(n, np.int64)
    root[order] = order[forest.label]
    return root


def blocks_of(n: int) -> list[tuple[int, int]]:
    """(shift, width) of n blocks of bits."""
    edge = [BITS * i // n for i in range(n + 1)]
    return [(a, b - a) for a, b in zip(edge, edge[1:], strict=False)]


def _rotate(x: np.ndarray, by: int) -> np.ndarray:
    """Bits by.. of x come to the lowest places, those below go to the top."""
    return x if not by else (x >> np.uint64(by)) | (x << np.uint64(BITS - by))


def _dealt(fps: DataFrame, budget: int, limit: int) -> DataFrame:
    """block, value, split, lo, hi, fp, rep: fingerprints once per subtree and per pair of its nodes that they belong to."""
    parts = blocks_of(budget + 1)
    turned = lambda by: f"shiftrightunsigned(fp, {by}) | shiftleft(fp, {BITS - by})" if by % BITS else "fp"
    places = F.array(*(F.struct(F.lit(i).alias("block"), F.expr(f"shiftrightunsigned(fp, {s}) & {(1 << w) - 1}L").alias("value"), F.expr(turned(s + w)).alias("turned")) for i, (s, w) in enumerate(parts)))
    keyed = fps.select("fp", "rep", F.explode(places).alias("k")).select("k.block", "k.value", "k.turned", "fp", "rep")
    bits = F.least(F.lit(SPLIT_BITS), F.ceil(F.log2(F.col("count") / limit))).cast("int")
    large = keyed.groupBy("block", "value").count().filter(F.col("count") > limit).select("block", "value", bits.alias("split"))
    placed = keyed.join(large, ["block", "value"], "left").withColumn("split", F.coalesce("split", F.lit(0)))
    # shifting by 64 is shifting by 0: a subtree in one piece has node 0
    node = F.when(F.col("split") == 0, F.lit(0).cast("long")).otherwise(F.expr(f"shiftrightunsigned(turned, {BITS} - split)"))
    others = F.expr(f"filter(sequence(0L, shiftleft(1L, split) - 1), x -> bit_count(x ^ node) <= {budget})")
    pairs = placed.withColumn("node", node).select("block", "value", "split", "node", "fp", "rep", F.explode(others).alias("other"))
    return pairs.select("block", "value", "split", F.least("node", "other").alias("lo"), F.greatest("node", "other").alias("hi"), "fp", "rep")


def near_links(fps: DataFrame, budget: int = LINK_BITS, limit: int | None = None) -> DataFrame:
    """fps(fp, rep), fp distinct -> links (a, b) of reps that keep the components of all pairs within the budget.

    limit: fingerprints of a subtree beyond which it is dealt by its next trie bits. fps is read twice.
    """
    parts = blocks_of(budget + 1)
    key_names = ["block", "value", "lo", "hi"]
    dealt = _dealt(fps, budget, limit or SUBTREE).repartition(*key_names).sortWithinPartitions(*key_names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []
        key, split = None, 0

        def linked():
            fp, rep = (np.concatenate(x) for x in zip(*held, strict=True))
            # the block that is shared comes last after the turn: what differs is decided first
            root = trie_components(_rotate(fp.view(np.uint64), sum(parts[key[0]])), budget, split)
            own = np.flatnonzero(root != np.arange(len(root)))
            return pa.record_batch([pa.array(rep[own]), pa.array(rep[root[own]])], names=["a", "b"])

        for b in batches:
            if not b.num_rows:
                continue
            keys = np.stack([b.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in key_names], axis=1)
            splits, fp, rep = (b.column(c).to_numpy(zero_copy_only=False) for c in ("split", "fp", "rep"))
            cut = [0, *(np.flatnonzero((keys[1:] != keys[:-1]).any(axis=1)) + 1).tolist(), len(fp)]
            for lo, hi in zip(cut, cut[1:], strict=False):
                now = tuple(keys[lo].tolist())
                if key is not None and now != key:
                    if sum(len(x[0]) for x in held) > 1:
                        yield linked()
                    held = []
                key, split = now, int(splits[lo])
                held.append((fp[lo:hi], rep[lo:hi]))
        if key is not None and sum(len(x[0]) for x in held) > 1:
            yield linked()

    return dealt.mapInArrow(run, "a long, b long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", budget: int = LINK_BITS, shingle: int = SHINGLE) -> DataFrame:
    """doc_id, fp and component_id (the least doc_id that links lead to) of every row."""
    seen = stored(fingerprint_table(docs, id_col, text_col, shingle), "simhash")
    fps = stored(seen.groupBy("fp").agg(F.min("doc_id").alias("rep")), "simhash-distinct")
    links = near_links(fps.filter("rep IS NOT NULL"), budget)
    found = components(links, "simhash-components")
    # a doc_id may repeat with different texts: its fingerprints then have one rep, and the link of equal reps is implied
    named = fps.join(found.withColumnRenamed("node", "rep"), "rep", "left").select("fp", F.coalesce("label", "rep").alias("component_id"))
    return seen.join(named, "fp")


def contract(docs: DataFrame) -> DataFrame:
    return near_duplicates(docs).select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, shingle: int = STAGE_SHINGLE, similarity: float = STAGE_SIMILARITY, budget: int = LINK_BITS) -> DataFrame:
    """docs with the document of the least doc_id of each component of near copies.

    Near copies share that much of their shingles. The trie's links are candidates for it; at 0.8 fingerprints
    differ in about 10 of 64 bits and often in more, and blocks of a budget that misses none are too short to
    divide the rows, so an exact join completes them (`similar_texts`). Rows without a doc_id stay as they are,
    and so do all rows of a doc_id that stays.
    """
    gone = similar_components(docs, shingle, similarity, budget).filter("doc_id <> component_id")
    key = fresh_names(docs, "kept")[0]
    return docs.join(gone.select(F.col("doc_id").alias(key)).distinct(), docs["doc_id"] == F.col(key), "left_anti")
