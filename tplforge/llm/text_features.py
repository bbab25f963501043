"""Counts over whole texts that quality rules and labellers vote on (one pass, Arrow batches)."""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from tplforge.llm.common import FIRST, byte_slices, hash_words, mix, texts

COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_letters", "n_upper", "n_exclaim", "n_echo_words")
SCHEMA = "doc_id long, " + ", ".join(f"{c} long" for c in COUNTS)
_SYMBOLS = re.compile(rb"[#*$%&|<>]")
_SPACE = b" \t\n\x0b\x0c\r"
#: bytes that continue a UTF-8 character
_CONTINUE = bytes(range(0x80, 0xC0))
_UPPER = bytes(range(65, 91))
_LOWER = bytes(range(97, 123))
_ALL = bytes(range(256))


def repeat_words(h: np.ndarray, counts: np.ndarray, k: int = 5) -> np.ndarray:
    """Words of each text that lie in a k-word window found twice or more in that text."""
    n = len(h)
    doc = np.repeat(np.arange(len(counts)), counts)
    out = np.zeros(len(counts), np.int64)
    if n < k:
        return out
    key = FIRST.windows(FIRST.prefix(h), k)
    inside = doc[: n - k + 1] == doc[k - 1 :]
    start = np.flatnonzero(inside)
    key = mix(key[start] + mix(doc[start].astype(np.uint64) + np.uint64(1)))
    order = np.argsort(key, kind="stable")
    s = key[order]
    same = np.zeros(len(s), bool)
    if len(s) > 1:
        eq = s[1:] == s[:-1]
        same[1:] |= eq
        same[:-1] |= eq
    hit = start[order[same]]
    edge = np.zeros(n + 1, np.int64)
    np.add.at(edge, hit, 1)
    np.add.at(edge, hit + k, -1)
    covered = np.cumsum(edge[:n]) > 0
    return np.bincount(doc[covered], minlength=len(counts)).astype(np.int64)


def echo_words(h: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Words equal to the word before them."""
    doc = np.repeat(np.arange(len(counts)), counts)
    if len(h) < 2:
        return np.zeros(len(counts), np.int64)
    same = (h[1:] == h[:-1]) & (doc[1:] == doc[:-1])
    return np.bincount(doc[1:][same], minlength=len(counts)).astype(np.int64)


def dup_lines(text: bytes) -> int:
    """Lines with a word that equal an earlier line."""
    lines = [x for x in text.split(b"\n") if x.strip(_SPACE)]
    return len(lines) - len(set(lines))


def count_features(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and COUNTS of every row; null and empty texts count 0 throughout."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in byte_slices(batches, "text"):
            raw = [x or b"" for x in b.column("text").cast(pa.binary()).to_pylist()]
            h, counts = hash_words(raw)
            cols = [
                counts,
                [len(t.translate(None, _SPACE + _CONTINUE)) for t in raw],
                [len(_SYMBOLS.findall(t)) for t in raw],
                [dup_lines(t) for t in raw],
                repeat_words(h, counts),
                [len(t) - len(t.translate(None, _UPPER + _LOWER)) for t in raw],
                [len(t) - len(t.translate(None, _UPPER)) for t in raw],
                [t.count(b"!") for t in raw],
                echo_words(h, counts),
            ]
            yield pa.record_batch([b.column("doc_id"), *(pa.array(c, pa.int64()) for c in cols)], names=["doc_id", *COUNTS])

    return texts(docs, id_col, text_col).mapInArrow(run, SCHEMA)
