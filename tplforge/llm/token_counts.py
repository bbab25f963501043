"""Token counts: lengths of encoded texts, without the encodings.

A byte-level BPE never merges across the change from a non-space to a space, whatever
space it is, so a text may be cut in front of every run of white space. Long texts
are cut there, short pieces met before are looked up, and only new pieces go to
the tokenizer, in batches balanced by bytes. What is remembered is bounded in
bytes. (Four control characters that some engines count as white space and others
do not are never cut at.)

Null and empty texts have 0 bytes and 0 tokens. Every row is kept, repeated
doc_ids and rows without one included; equal texts have equal counts. A piece without
any white space is encoded as it is, however long, and not remembered. An empty table gives an
empty result.
"""

from __future__ import annotations

import os
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tplforge.llm.common import byte_slices, texts

BATCH_BYTES = 1 << 20
#: pieces of at most SHORT characters are remembered, in MEMO_BYTES bytes, at ENTRY_BYTES beside the characters
SHORT, MEMO_BYTES, ENTRY_BYTES = 64, 96 << 20, 160
SCHEMA = "doc_id long, n_bytes long, n_tokens long"
#: white space of the tokenizer's patterns, and characters that only other engines take for it (fixed values)
_SPACES, _DOUBTFUL = r"\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000", r"\x1c-\x1f"
_PIECES = re.compile(f"[{_SPACES}]*[^{_SPACES}]+|[{_SPACES}]+")
_CUTS = re.compile(f"(?<=[^{_SPACES}{_DOUBTFUL}])(?=[{_SPACES}])")
_HAS_DOUBTFUL = re.compile(f"[{_DOUBTFUL}]")
_loaded: dict[str, object] = {}


def _tokenizer(path: str):
    if path not in _loaded:
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        if not os.path.exists(path):
            import public_tokenizers

            path_here = public_tokenizers.path(path)
        else:
            path_here = path
        tk = Tokenizer.from_file(path_here)
        tk.no_truncation()
        tk.no_padding()
        _loaded[path] = tk
    return _loaded[path]


class PieceCounts:
    """Short piece -> number of tokens; new pieces are encoded in batches of about BATCH_BYTES."""

    def __init__(self, tokenizer):
        self.tk, self.known, self.held = tokenizer, {}, 0

    def encode(self, pieces: list[str]) -> list[int]:
        out, batch, size = [], [], 0
        for p in [*pieces, None]:
            if batch and (p is None or size + len(p) > BATCH_BYTES // 4):  # a character has 4 bytes at most
                out += [len(e) for e in self.tk.encode_batch_fast(batch, add_special_tokens=False)]
                batch, size = [], 0
            if p is not None:
                batch.append(p)
                size += len(p)
        return out

    def count(self, texts: list[str]) -> list[int]:
        if self.held > MEMO_BYTES:
            self.known.clear()
            self.held = 0
        cut = [(_CUTS.split if _HAS_DOUBTFUL.search(t) else _PIECES.findall)(t) for t in texts]
        new = list({p for pieces in cut for p in pieces if p not in self.known})
        now = dict(zip(new, self.encode(new), strict=True))
        keep = {p: n for p, n in now.items() if len(p) <= SHORT}
        self.known.update(keep)
        self.held += sum(map(len, keep)) * 4 + len(keep) * ENTRY_BYTES
        now = {p: n for p, n in now.items() if len(p) > SHORT}
        if not now:
            look = self.known.__getitem__
            return [sum(map(look, pieces)) for pieces in cut]
        return [sum(self.known[p] if p in self.known else now[p] for p in pieces) for pieces in cut]


def count_tokens(docs: DataFrame, tokenizer: str = "byte_bpe_50k.json", id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_tokens of every row; `tokenizer` is a path or a name the tokenizer package resolves."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = PieceCounts(_tokenizer(tokenizer))
        for b in byte_slices(batches, "text"):
            found = [t or "" for t in b.column("text").to_pylist()]
            yield pa.record_batch(
                [b.column("doc_id"), pa.array([len(t.encode()) for t in found], pa.int64()), pa.array(counter.count(found), pa.int64())],
                names=["doc_id", "n_bytes", "n_tokens"],
            )

    return texts(docs, id_col, text_col).mapInArrow(run, SCHEMA)


def contract(docs: DataFrame, limit: int = 512) -> DataFrame:
    return count_tokens(docs).withColumn("over_limit", F.col("n_tokens") > limit)
