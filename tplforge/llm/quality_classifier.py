"""Quality classifier from weak labels.

Overlapping heuristic labellers vote on every document; expectation-maximisation
over the vote patterns of the whole corpus estimates how accurate each labeller
is; the posteriors of a bounded, documented sample (`fit_rows`) then train a
hashed linear scorer, which scores every document. Human labels are used for
evaluation only.

Null and empty texts get a score like any text without words (the labellers
reject them). Rows with one doc_id are scored one by one, rows without a doc_id too.
Equal texts have equal scores; of the sample, ties of the hash fall on one side
together. Texts of any length are scored whole; a scored text's memory follows its
length. An empty table gives an empty result. Columns of other names play no part.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tplforge.llm.common import stored, texts
from tplforge.llm.hashed_linear import fit, predict, sample_features, sample_rows
from tplforge.llm.quality_rules import rules
from tplforge.llm.text_features import count_features
from tplforge.llm.weak_labels import Voter, posteriors

FIT_ROWS = 6000
#: words count little beside shapes: quality here is a matter of form, and long texts have many words
WORD_GAIN = 0.05


def labellers() -> list[Voter]:
    """The quality rules and one that rejects texts without words."""
    return [*rules(), Voter("words", F.col("n_words") < 3, F.col("n_words") >= 30)]


def score(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", fit_rows: int = FIT_ROWS, threshold: float = 0.5) -> DataFrame:
    """doc_id, weak_label (posterior of the labellers), score (of the linear scorer) and keep."""
    docs = texts(docs, id_col, text_col)
    weak = posteriors(stored(count_features(docs), "quality-labels"), labellers(), "weak_label").select("doc_id", "weak_label")
    chosen = sample_rows(weak, "doc_id", fit_rows)
    rows = docs.join(F.broadcast(chosen), "doc_id").limit(2 * fit_rows)  # the sample's bound holds the size of chosen
    sparse, target = sample_features(rows, [1 - F.col("weak_label"), F.col("weak_label")], WORD_GAIN)
    model = fit(sparse, target, word_gain=WORD_GAIN)
    # a doc_id's rows differ in text, so the scores are not joined to labels: every row is scored by its text
    scored = predict(docs, model, ["p_bad", "score"])
    return scored.select("doc_id", "n_words", F.round("score", 9).alias("score"), (F.col("score") >= threshold).alias("keep"))
