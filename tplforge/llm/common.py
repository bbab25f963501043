"""Helpers shared by the training-data operators.

Everything that runs on executors works on Arrow batches cut into slices of a
bounded number of bytes, so that memory does not follow the number of rows in
a batch or the length of its texts (one row is the smallest slice).
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SLICE_BYTES = 4 << 20
#: entries after which a per-process memo starts anew
MEMO_ENTRIES = 400_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


_made: set[str] = set()


def scratch(spark: SparkSession, name: str) -> str:
    """A new path in the folder that driver and executors share (spark.checkpoint.dir).

    Where the setting is missing, a session on one machine uses its warehouse; a cluster has to name a folder,
    because one that is local to a machine would lose rows.
    """
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        root = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_scratch"
    path = f"{root.rstrip('/')}/{name}-{uuid.uuid4().hex}"
    _made.add(path)
    return path


def stored(df: DataFrame, name: str) -> DataFrame:
    """Write df to the shared folder and read it back: cuts lineage, survives lost executors."""
    return stored_at(df, scratch(df.sparkSession, name))


def stored_at(df: DataFrame, path: str) -> DataFrame:
    """df written to a path and read back."""
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def delete(spark: SparkSession, *paths: str) -> None:
    """Remove stored tables, or folders of them, that nothing reads any more."""
    for path in paths:
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)
        _made.discard(path)


def forget(spark: SparkSession) -> None:
    """Remove everything that this process has stored: for when no result is read any more."""
    delete(spark, *list(_made))


def fresh_names(df: DataFrame, *wanted: str) -> list[str]:
    """Column names like the wanted ones that df does not have (whatever their case)."""
    taken = {c.lower() for c in df.columns}
    out = []
    for name in wanted:
        while name.lower() in taken:
            name = f"_{name}"
        taken.add(name.lower())
        out.append(name)
    return out


def texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The two columns an operator reads, under fixed names, so that other columns cannot clash."""
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))


def byte_slices(batches: Iterator[pa.RecordBatch], column: str, limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut batches so that a slice holds at most `limit` bytes of `column`, or one row."""
    for batch in batches:
        n = batch.num_rows
        if not n:
            continue
        size = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
        upto = np.cumsum(size, dtype=np.int64)
        at = 0
        while at < n:
            base = upto[at - 1] if at else 0
            end = max(at + 1, int(np.searchsorted(upto, base + limit, side="right")))
            yield batch.slice(at, end - at)
            at = end


def raw_bytes(batch: pa.RecordBatch, column: str) -> list[bytes]:
    """UTF-8 of each text, null as empty."""
    return [b or b"" for b in batch.column(column).cast(pa.binary()).to_pylist()]


_BLANK = np.zeros(256, bool)
_BLANK[[9, 10, 11, 12, 13, 32]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
#: the lowest n bytes of a number
_LOWEST = np.array([(1 << (8 * i)) - 1 for i in range(8)] + [(1 << 64) - 1], np.uint64)
#: words of more bytes are hashed one by one
_LONG = 512


def hash_words(texts: list[bytes], lower: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of the words of all texts one after another, and the number of words in each.

    Words are what \\x20 and \\x09-\\x0D separate. All are hashed together, eight bytes at a time.
    lower: A-Z count as a-z.
    """
    n = len(texts)
    joined = b" ".join(texts) + b" " * 9
    buf = np.frombuffer(joined, np.uint8)
    if lower:
        buf = _LOWER[buf]
        joined = buf.tobytes()
    edge = np.flatnonzero(np.diff(_BLANK[buf].view(np.int8), prepend=np.int8(1)))
    start, size = edge[0::2], edge[1::2] - edge[0::2]
    counts = np.bincount(np.searchsorted(np.cumsum(np.fromiter(map(len, texts), np.int64, n) + 1), start, side="right"), minlength=n)
    eight = np.ndarray((len(buf) - 7,), "<u8", joined, 0, (1,))
    h = mix((eight[start] & _LOWEST[np.minimum(size, 8)]) + size.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    for i in np.flatnonzero(size > _LONG).tolist():
        h[i] = xxhash.xxh64_intdigest(joined[start[i] : start[i] + size[i]])
    more, at = np.flatnonzero((size > 8) & (size <= _LONG)), 8
    while len(more):
        h[more] = mix(h[more] * np.uint64(0xD6E8FEB86659FD93) + (eight[start[more] + at] & _LOWEST[np.minimum(size[more] - at, 8)]))
        at += 8
        more = more[size[more] > at]
    return h, counts


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser of a 64-bit generator: spreads sums of products over all bits."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Rolling:
    """Hashes of word ranges as a polynomial modulo 2**64 over prefix sums."""

    def __init__(self, base: int):
        self.base = base | 1
        self.inverse = pow(self.base, -1, 1 << 64)
        self.up = np.ones(1, np.uint64)
        self.down = np.ones(1, np.uint64)

    def _powers(self, n: int) -> None:
        if len(self.up) < n:
            n = max(n, 2 * len(self.up))
            up, down = np.full(n, self.base, np.uint64), np.full(n, self.inverse, np.uint64)
            up[0] = down[0] = 1
            self.up, self.down = np.cumprod(up, dtype=np.uint64), np.cumprod(down, dtype=np.uint64)

    def prefix(self, h: np.ndarray) -> np.ndarray:
        self._powers(len(h) + 1)
        out = np.zeros(len(h) + 1, np.uint64)
        np.cumsum(h * self.up[: len(h)], out=out[1:])
        return out

    def ranges(self, prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix((prefix[end] - prefix[start]) * self.down[start])

    def windows(self, prefix: np.ndarray, k: int) -> np.ndarray:
        n = len(prefix) - k
        if n <= 0:
            return np.empty(0, np.uint64)
        return mix((prefix[k:] - prefix[:n]) * self.down[:n])


FIRST, SECOND = Rolling(0x9E3779B97F4A7C15), Rolling(0xD6E8FEB86659FD93)
