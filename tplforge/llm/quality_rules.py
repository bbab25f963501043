"""Quality rules as weak supervision.

Every rule may accept, reject or abstain; expectation-maximisation over the
votes of all documents estimates how far each rule can be trusted, and the
posterior probability of good quality decides, instead of asking that a
document pass all rules. Two hard limits stay in front: too few words, and too
many words in repeated 5-word windows.

Null and empty texts have no words and fail the hard limit. Very long texts are counted
whole. Rows with the same doc_id are judged one by one, rows without a doc_id too (`keep_good`, which names
documents by it, keeps those). Documents of the same votes have the same posterior, and one at the threshold itself
is kept. An empty table gives an empty result. Columns of other names play no part.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tplforge.llm.common import fresh_names, stored
from tplforge.llm.text_features import count_features
from tplforge.llm.weak_labels import Voter, posteriors


def rules() -> list[Voter]:
    c = F.col
    words = F.greatest(c("n_words"), F.lit(1))
    symbols, letters = c("n_symbols") / words, F.greatest(c("n_letters"), F.lit(1))
    upper, repeat = c("n_upper") / letters, c("n_repeat_words") / words
    length, echo = c("word_chars") / words, c("n_echo_words") / words
    return [
        Voter("symbols", symbols > 0.25, symbols < 0.05),
        Voter("symbol_chars", c("n_symbols") > 0.06 * c("word_chars"), c("n_symbols") < 0.02 * c("word_chars")),
        Voter("capitals", (upper > 0.4) & (letters >= 20), (upper < 0.15) & (letters >= 20)),
        Voter("exclaim", c("n_exclaim") > 0.2 * words, c("n_exclaim") < 0.05 * words),
        # a line at head and foot of a short text repeats as well; what fills a text repeats in place
        Voter("repeats", (repeat > 0.15) & (echo > 0.03), (repeat < 0.02) & (c("n_words") >= 30)),
        Voter("echo", echo > 0.1, (echo < 0.03) & (c("n_words") >= 30)),
        Voter("dup_lines", c("n_dup_lines") >= 4, F.lit(False)),
        Voter("word_length", (length > 25) | (length < 1.5), (length >= 2.5) & (length <= 12)),
    ]


def judge(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.5) -> DataFrame:
    """Counts, base_failed, p_good (posterior) and kept for every row."""
    scored = posteriors(stored(count_features(docs, id_col, text_col), "quality-rules"), rules())
    n = F.col("n_words")
    failed = (n < 10) | (100 * F.col("n_repeat_words") > 20 * n)
    return scored.withColumn("base_failed", failed).withColumn("kept", ~failed & (F.col("p_good") >= threshold))


def contract(docs: DataFrame) -> DataFrame:
    return judge(docs).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", F.round("p_good", 6).alias("p_good"))


def keep_good(docs: DataFrame) -> DataFrame:
    """docs without the rejected ones. A doc_id that repeats goes if one of its rows is rejected."""
    key = fresh_names(docs, "bad")[0]
    bad = judge(docs).filter(~F.col("kept")).select(F.col("doc_id").alias(key)).distinct()
    return docs.join(bad, docs["doc_id"] == F.col(key), "left_anti")
