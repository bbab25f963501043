"""Words of lines: tokenising, the word-line graph, shape classes, hashed vectors, residuals."""

from __future__ import annotations

import math
import re
import zlib
from functools import lru_cache

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: (class, pattern): the first that fits a whole word names its shape. Used on both sides, so kept portable.
SHAPES = (
    ("<date>", r"^[0-9]{4}-[0-9]{2}-[0-9]{2}$"),
    ("<int>", r"^[0-9]+$"),
    ("<dec>", r"^-?[0-9]+[.][0-9]+$"),
    ("<addr>", r"^([0-9]{1,3}[.]){3}[0-9]{1,3}(:[0-9]+)?$"),
    ("<addr>", r"^[A-Za-z0-9-]+([.][A-Za-z0-9-]+)+:[0-9]+$"),
    ("<url>", r"^(https?://|/).*$"),
    ("<hex>", r"^0x[0-9A-Fa-f]+$"),
    ("<id>", r"^[A-Za-z]+#?[0-9][A-Za-z0-9#-]*$"),
)
_COMPILED = tuple((n, re.compile(p)) for n, p in SHAPES)
#: every class asks for a digit or a slash
_MAY_VARY = re.compile("[0-9/]")
DIM = 64


def words(raw: Column) -> Column:
    """Words between white space; none for null and blank lines."""
    return F.filter(F.split(F.coalesce(raw, F.lit("")), r"\s+"), lambda w: w != "")


def tokenize(df: DataFrame, raw: str = "raw") -> DataFrame:
    """Adds words, n_words and, where there is a truth, labels."""
    out = df.withColumn("words", words(F.col(raw))).withColumn("n_words", F.size("words"))
    return out.withColumn("labels", words(F.col("truth"))) if "truth" in df.columns else out


def graph(df: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Edges (log_id, pos, word_id, word) and vocabulary (word_id, word, df, n) of tokenised lines."""
    edges = df.select("log_id", F.posexplode("words").alias("pos", "word")).withColumn("word_id", F.xxhash64("word"))
    vocab = edges.groupBy("word_id", "word").agg(F.countDistinct("log_id").alias("df"), F.count("*").alias("n"))
    return edges, vocab


def shape(word: Column) -> Column:
    """The shape class of a word with variable content; any other word stands for itself."""
    out = F.when(~word.rlike("[0-9/]"), word)  # every class asks for a digit or a slash
    for name, pattern in SHAPES:
        out = out.when(word.rlike(pattern), name)
    return out.otherwise(word)


def classed(arr: Column) -> Column:
    return F.transform(arr, shape)


def residual(arr: Column, known: Column) -> Column:
    """Words that are not among the identified ones, in order."""
    return F.filter(arr, lambda w: ~F.array_contains(known, w))


def residual_join(df: DataFrame, known: DataFrame) -> DataFrame:
    """residual for a vocabulary of any size, known(word): an anti-join on exploded words."""
    left = df.select("log_id", F.posexplode("words").alias("pos", "word")).join(known.select("word").distinct(), "word", "left_anti")
    kept = left.groupBy("log_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "word"))), lambda x: x["word"]).alias("residual"))
    return df.join(kept, "log_id", "left").withColumn("residual", F.coalesce("residual", F.array().cast("array<string>")))


#: share of a variable word's vector that its shape class makes up; two words of one class then have a cosine of about its square
CLASS_SHARE = 0.9


def _hashed(grams: list[str]) -> np.ndarray:
    v = np.zeros(DIM)
    for g in grams:
        h = zlib.crc32(g.encode())
        v[h % DIM] += 1.0 if h >> 16 & 1 else -1.0
    n = math.sqrt(v @ v)
    return v / n if n else v


def shape_of(word: str) -> str:
    """shape() for one word outside Spark."""
    if word.isdigit() and word.isascii():
        return "<int>"
    return next((n for n, p in _COMPILED if p.match(word)), word) if _MAY_VARY.search(word) else word


def vector(word: str) -> np.ndarray:
    """Signed hashed character 3-grams (and the word), unit length; the stand-in for word embeddings.

    Words of a shape class (numbers, dates, addresses) lie near each other, as they do in trained embeddings.
    """
    marked = f"<{word}>"
    own = _hashed([marked, *(marked[i : i + 3] for i in range(max(1, len(marked) - 2)))])
    kind = shape_of(word)
    if kind == word:
        return own
    both = CLASS_SHARE * _hashed([f"{kind}/{i}" for i in range(12)]) + math.sqrt(1 - CLASS_SHARE**2) * own
    n = math.sqrt(both @ both)
    return both / n if n else both


def vectors(many: list[str]) -> np.ndarray:
    """vector() of many words at once, digit by digit the same."""
    if not many:
        return np.zeros((0, DIM))
    row, code = _ascii_grams(many)
    more_row, more = [], []
    for k, w in enumerate(many):
        if not w.isascii() or not w:
            marked = f"<{w}>"
            own = [marked, *(marked[i : i + 3] for i in range(max(1, len(marked) - 2)))]
            more += [zlib.crc32(g.encode()) for g in own]
            more_row += [k] * len(own)
    row, h = np.r_[row, np.array(more_row, np.int64)], np.r_[code, np.array(more, np.int64)]
    v = np.bincount(row * DIM + h % DIM, np.where(h >> 16 & 1, 1.0, -1.0), len(many) * DIM).reshape(-1, DIM)
    n = np.sqrt((v * v).sum(axis=1, keepdims=True))  # sums of whole numbers, exact in any order
    v = v / np.where(n > 0, n, 1)
    for kind, at in _kinds(many).items():
        both = CLASS_SHARE * _kind_vector(kind) + math.sqrt(1 - CLASS_SHARE**2) * v[at]
        n = np.array([math.sqrt(b @ b) for b in both])[:, None]
        v[at] = both / np.where(n > 0, n, 1)
    return v


#: of the checksum, by the byte that leaves it
_CRC = np.array([zlib.crc32(bytes([b ^ 255])) ^ 0xFF000000 for b in range(256)], np.uint32)


def _ascii_grams(many: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Places and checksums of the marked ASCII words and of their 3-grams."""
    at = [k for k, w in enumerate(many) if w and w.isascii()]
    marked = [f"<{many[k]}>".encode() for k in at]
    whole = np.array([zlib.crc32(m) for m in marked], np.int64)
    size = np.array([len(m) for m in marked], np.int64)
    b = np.frombuffer(b"".join(marked) + b"\0\0", np.uint8).astype(np.uint32)
    n = len(b) - 2
    c = np.full(n, 0xFFFFFFFF, np.uint32)
    for j in range(3):
        c = _CRC[(c ^ b[j : j + n]) & np.uint32(255)] ^ (c >> np.uint32(8))
    inside = np.repeat(np.cumsum(size), size) - np.arange(n) >= 3  # three bytes of one word
    rows = np.array(at, np.int64)
    return np.r_[rows, np.repeat(rows, size)[inside]], np.r_[whole, (c ^ np.uint32(0xFFFFFFFF))[inside].astype(np.int64)]


def _kinds(many: list[str]) -> dict[str, list[int]]:
    out: dict[str, list[int]] = {}
    for k, w in enumerate(many):
        if (kind := shape_of(w)) != w:
            out.setdefault(kind, []).append(k)
    return out


@lru_cache(maxsize=64)
def _kind_vector(kind: str) -> np.ndarray:
    return _hashed([f"{kind}/{i}" for i in range(12)])


#: begins the form of a variable word; no word holds it, since words end at white space
VARIABLE = "\n"


def form(arr: Column) -> Column:
    """Constant words as they are; variable ones as their class and the place where the line has that word first.

    Lines of one form differ in nothing but the letters of their variable words.
    """
    mark = lambda w, s: F.concat(F.lit(VARIABLE), s, F.lit("="), F.array_position(arr, w).cast("string"))
    return F.zip_with(arr, classed(arr), lambda w, s: F.when(s == w, w).otherwise(mark(w, s)))


def classes_of(forms: Column) -> Column:
    """classed() of the words that have these forms."""
    return F.transform(forms, lambda f: F.when(f.startswith(VARIABLE), F.substring_index(F.substring(f, 2, 64), "=", 1)).otherwise(f))


class Similarity:
    """Word similarity on executors and driver: exact, classed (same shape or string) or vector (cosine >= tau)."""

    def __init__(self, kind: str = "classed", tau: float = 0.5):
        self.kind, self.tau = kind, tau
        self._shape, self._vec = {}, {}

    def shape(self, w: str) -> str:
        if (s := self._shape.get(w)) is None:
            if len(self._shape) > 200_000:
                self._shape.clear()
            s = self._shape[w] = w[1 : w.rindex("=")] if w[:1] == VARIABLE else shape_of(w)
        return s

    def vec(self, w: str) -> np.ndarray:
        if (v := self._vec.get(w)) is None:
            v = self._vec[w] = vector(w)
        return v

    def learn(self, many) -> None:
        """Vectors of many words at once; forgets the earlier ones when they are many."""
        if len(self._vec) > 50_000:
            self._vec.clear()
        new = [w for w in dict.fromkeys(many) if w not in self._vec]
        self._vec.update(zip(new, vectors(new), strict=True))

    def score(self, a: str, b: str) -> float:
        if a == b:
            return 1.0
        if self.kind == "exact":
            return -1.0
        if self.kind == "classed":
            return 0.9 if self.shape(a) == self.shape(b) else -1.0
        return float(self.vec(a) @ self.vec(b))

    def same(self, a: str, b: str) -> bool:
        return self.score(a, b) >= (self.tau if self.kind == "vector" else 0)


def similar_pairs(vocab: DataFrame, tau: float, block: int = 2000) -> DataFrame:
    """Word pairs (a < b) with cosine >= tau: the vocabulary in blocks against all words."""
    from pyspark.sql.functions import pandas_udf

    @pandas_udf("array<double>")
    def vec(s):
        return s.map(lambda w: vector(w).tolist())

    v = vocab.select("word", vec("word").alias("v"))
    n = max(1, math.ceil(vocab.count() / block))
    left = v.withColumn("g", F.pmod(F.xxhash64("word"), F.lit(n)))
    right = v.select(F.col("word").alias("word_b"), F.col("v").alias("v_b")).withColumn("g", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long"))))
    dot = F.aggregate(F.zip_with("v", "v_b", lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    return left.join(right, "g").filter(F.col("word") < F.col("word_b")).withColumn("cos", dot).filter(F.col("cos") >= tau).select("word", "word_b", "cos")
