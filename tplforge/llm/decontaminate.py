"""Benchmark decontamination by pigeonhole edit matching.

An item of m characters that occurs in a document with at most e edits leaves
one of any e+1 pieces of it untouched. Each item is cut into e+1 pieces; one
automaton over all pieces of a block of items finds exact piece hits in whole
texts; around each hit, Myers' bit-parallel distance verifies the item.

Texts and items are compared in lower case, with runs of white space as one
space. Items of any number are worked through in blocks whose size is bounded
(`block_chars`), each against all documents. An item's budget is the whole part of `share` of its
characters, so items of under 20 are matched without edits at the default; empty and null items match nothing.
Null and empty documents contain nothing. Very long documents are searched whole.
Rows and items that repeat are judged alike, each on its own; rows without a doc_id too (`drop_contaminated`,
which names documents by it, keeps them). Of several places of an item the least distance counts.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tplforge.llm.common import byte_slices, fresh_names, texts

EDIT_SHARE = 0.05
BLOCK_CHARS = 8 << 20
SCHEMA = "doc_id long, items array<long>, edits array<int>"


def normal(text: str) -> str:
    return " ".join(text.lower().split())


def budget(length: int, share: float = EDIT_SHARE) -> int:
    return int(length * share)


def pieces(item: str, edits: int) -> list[tuple[int, str]]:
    """edits+1 pieces of nearly equal length with their places."""
    n = edits + 1
    edge = [len(item) * i // n for i in range(n + 1)]
    return [(a, item[a:b]) for a, b in zip(edge, edge[1:], strict=False) if a < b]


def myers(pattern: str, text: str, most: int) -> int | None:
    """Least edit distance between pattern and any substring of text, if at most `most`."""
    masks: dict[str, int] = {}
    for i, c in enumerate(pattern):
        masks[c] = masks.get(c, 0) | 1 << i
    m = len(pattern)
    top, full = 1 << (m - 1), (1 << m) - 1
    up, down, score, best = full, 0, m, m
    for c in text:
        eq = masks.get(c, 0)
        diagonal = (((eq & up) + up) ^ up) | eq | down
        plus, minus = down | ~(diagonal | up) & full, up & diagonal
        if plus & top:
            score += 1
        elif minus & top:
            score -= 1
            if score < best:
                best = score
                if not best:
                    break
        plus, minus = (plus << 1) & full, (minus << 1) & full
        up, down = minus | ~(eq | down | plus) & full, plus & (eq | down)
    return best if best <= most else None


class Matcher:
    """The pieces of a block of items in one automaton."""

    def __init__(self, items: list[tuple[int, str]], share: float = EDIT_SHARE):
        import ahocorasick

        self.items = {i: normal(t) for i, t in items}
        self.edits = {i: budget(len(t), share) for i, t in self.items.items()}
        places = defaultdict(list)
        for i, t in self.items.items():
            for at, piece in pieces(t, self.edits[i]):
                places[piece].append((i, at))
        self.automaton = ahocorasick.Automaton()
        for piece, where in places.items():
            self.automaton.add_word(piece, (len(piece), where))
        if places:
            self.automaton.make_automaton()
        self.any = bool(places)

    def find(self, text: str) -> dict[int, int]:
        """item -> edits, for every item within its budget somewhere in text."""
        if not self.any or not text:
            return {}
        text = normal(text)
        hits = defaultdict(set)
        for end, (n, where) in self.automaton.iter(text):
            for i, at in where:
                hits[i].add(end + 1 - n - at)
        out = {}
        for i, starts in hits.items():
            item, e = self.items[i], self.edits[i]
            if any(s >= 0 and text.startswith(item, s) for s in starts):
                out[i] = 0
                continue
            if not e:
                continue
            best, reach = None, -1
            spans: list[list[int]] = []
            for s in sorted(starts):
                a, b = max(0, s - e), s + len(item) + e
                if spans and a <= reach:
                    spans[-1][1] = b
                else:
                    spans.append([a, b])
                reach = b
            for a, b in spans:
                d = myers(item, text[a:b], e)
                if d is not None and (best is None or d < best):
                    best = d
            if best is not None:
                out[i] = best
        return out


def item_blocks(items: DataFrame, id_col: str, text_col: str, block_chars: int) -> Iterator[list[tuple[int, str]]]:
    block, size = [], 0
    for r in items.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).cast("string").alias("t")).filter("i IS NOT NULL AND t IS NOT NULL").toLocalIterator():
        if block and size + len(r["t"]) > block_chars:
            yield block
            block, size = [], 0
        block.append((r["i"], r["t"]))
        size += len(r["t"])
    if block:
        yield block


def find_items(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_id: str = "item_id", item_text: str = "text", share: float = EDIT_SHARE, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """doc_id, items (ids found, ascending) and edits (of each) for every row of docs in which something was found."""
    docs = texts(docs, id_col, text_col).filter("text IS NOT NULL")
    sc = docs.sparkSession.sparkContext
    parts = []
    for block in item_blocks(items, item_id, item_text, block_chars):
        held = sc.broadcast(block)  # at most block_chars characters, or one item

        def run(batches: Iterator[pa.RecordBatch], held=held) -> Iterator[pa.RecordBatch]:
            matcher = Matcher(held.value, share)
            for b in byte_slices(batches, "text"):
                found = [matcher.find(t) for t in b.column("text").to_pylist()]
                at = [i for i, f in enumerate(found) if f]
                yield pa.record_batch(
                    [
                        b.column("doc_id").take(pa.array(np.array(at, np.int64))),
                        pa.array([sorted(found[i]) for i in at], pa.list_(pa.int64())),
                        pa.array([[found[i][k] for k in sorted(found[i])] for i in at], pa.list_(pa.int32())),
                    ],
                    names=["doc_id", "items", "edits"],
                )

        parts.append(docs.mapInArrow(run, SCHEMA))
    if not parts:
        return docs.sparkSession.createDataFrame([], SCHEMA)
    return reduce(DataFrame.unionByName, parts)


def contract(docs: DataFrame, items: DataFrame) -> DataFrame:
    """One row for every document with at least one item: doc_id, item_ids, least_edits."""
    found = find_items(docs, items)
    pairs = found.select("doc_id", F.explode(F.arrays_zip("items", "edits")).alias("x"))
    return pairs.groupBy("doc_id").agg(F.array_sort(F.collect_set("x.items")).alias("item_ids"), F.min("x.edits").alias("least_edits"))


def drop_contaminated(docs: DataFrame, items: DataFrame) -> DataFrame:
    """docs without those in which an item was found; every row of such a doc_id goes."""
    key = fresh_names(docs, "found")[0]
    found = find_items(docs, items).select(F.col("doc_id").alias(key)).distinct()
    return docs.join(found, docs["doc_id"] == F.col(key), "left_anti")
