"""Growing logs: windows, repeats, late lines, known words per domain, labelling batches.

Every stream here has a batch twin over the same rows (plans.relational op_tumble,
op_slide, op_session); drained with availableNow the two agree on rows that were not late.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from tplforge.functions.words import classed, words

WATERMARK = "10 minutes"


def render(events: DataFrame) -> DataFrame:
    """Lines of the simple event corpus with their time."""
    amount = F.col("value").cast("decimal(18,2)").cast("string")
    raw = F.concat(F.col("event_type"), F.lit(" event from user "), F.col("user_id").cast("string"), F.lit(" amount "), amount)
    return events.select(F.col("event_id").alias("log_id"), "ts", "user_id", "event_type", raw.alias("raw")).withColumn("words", words(F.col("raw")))


def once(stream: DataFrame, watermark: str = WATERMARK) -> DataFrame:
    """Repeats of an id go, as long as both fall within the watermark."""
    return stream.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["log_id"])


def tumbling(stream: DataFrame, by: str = "event_type", size: str = "1 hour", watermark: str = WATERMARK) -> DataFrame:
    return stream.withWatermark("ts", watermark).groupBy(F.window("ts", size).alias("w"), by).agg(F.count("*").alias("n"))


def sliding(stream: DataFrame, by: str = "event_type", size: str = "1 hour", slide: str = "15 minutes", watermark: str = WATERMARK) -> DataFrame:
    return stream.withWatermark("ts", watermark).groupBy(F.window("ts", size, slide).alias("w"), by).agg(F.count("*").alias("n"))


def sessions(stream: DataFrame, by: str = "user_id", gap: str = "30 minutes", watermark: str = WATERMARK) -> DataFrame:
    return stream.withWatermark("ts", watermark).groupBy(F.session_window("ts", gap).alias("w"), by).agg(F.count("*").alias("n"))


def patterns(stream: DataFrame, size: str = "1 hour", watermark: str = WATERMARK) -> DataFrame:
    """Lines per shape pattern and window: what a round would call its patterns."""
    key = F.array_join(classed(F.col("words")), " ").alias("pattern")
    return stream.withWatermark("ts", watermark).groupBy(F.window("ts", size).alias("w"), key).agg(F.count("*").alias("n"), F.min("log_id").alias("log_id"))


def with_labels(stream: DataFrame, labelled: DataFrame) -> DataFrame:
    """Each line with the template of its pattern, if one is labelled; labelled(pattern, template) is bounded by the budget."""
    return stream.withColumn("pattern", F.array_join(classed(F.col("words")), " ")).join(F.broadcast(labelled), "pattern", "left")


def confirmed(predictions: DataFrame, truths: DataFrame, bound: str = "1 hour", watermark: str = WATERMARK) -> DataFrame:
    """Predictions with the truth that arrives within `bound`; both sides have a time and a log_id."""
    p = predictions.withWatermark("ts", watermark).alias("p")
    t = truths.select(F.col("log_id").alias("t_id"), F.col("ts").alias("t_ts"), "truth").withWatermark("t_ts", watermark).alias("t")
    return p.join(t, F.expr(f"log_id = t_id AND t_ts >= ts AND t_ts <= ts + INTERVAL {bound}"))


class NewWords(StatefulProcessor):
    """Per key: words met so far; emits, per micro-batch, the lines that bring new ones."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.known = handle.getMapState("known", "word string", "n long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        out = []
        for pdf in rows:
            for i, ws in zip(pdf.log_id, pdf.words, strict=True):
                fresh = [w for w in dict.fromkeys(ws) if not self.known.containsKey((w,))]
                for w in fresh:
                    self.known.updateValue((w,), (1,))
                if fresh:
                    out.append((key[0], int(i), len(fresh)))
        yield pd.DataFrame(out, columns=["event_type", "log_id", "fresh"])

    def close(self) -> None:
        pass


class HardLines(StatefulProcessor):
    """Per key: lines with a word never met before wait in a list; a timer in event time releases the first `budget` of them."""

    def __init__(self, budget: int, wait_ms: int):
        self.budget, self.wait = budget, wait_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.known = handle.getMapState("known", "word string", "n long")
        self.hard = handle.getListState("hard", "log_id long, fresh long")
        self.due = handle.getValueState("due", "at long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        for pdf in rows:
            for i, ws in zip(pdf.log_id, pdf.words, strict=True):
                fresh = [w for w in dict.fromkeys(ws) if not self.known.containsKey((w,))]
                for w in fresh:
                    self.known.updateValue((w,), (1,))
                if fresh:
                    self.hard.appendValue((int(i), len(fresh)))
        if not self.due.exists():
            at = max(0, timerValues.getCurrentWatermarkInMs()) + self.wait
            self.due.update((at,))
            self.handle.registerTimer(at)
        yield pd.DataFrame({"event_type": pd.Series([], dtype=str), "log_id": pd.Series([], dtype="int64"), "fresh": pd.Series([], dtype="int64")})

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:
        waiting = sorted(self.hard.get(), key=lambda r: (-r[1], r[0]))
        self.hard.clear()
        for r in waiting[self.budget :]:
            self.hard.appendValue(r)
        self.due.clear()
        yield pd.DataFrame([(key[0], r[0], r[1]) for r in waiting[: self.budget]], columns=["event_type", "log_id", "fresh"])

    def close(self) -> None:
        pass


def label_requests(stream: DataFrame, budget: int, wait_ms: int = 60_000, by: str = "event_type", watermark: str = WATERMARK) -> DataFrame:
    """The hardest lines of each key, at most `budget` each time that the watermark passes the wait. Needs the RocksDB state store."""
    return stream.withWatermark("ts", watermark).groupBy(by).transformWithStateInPandas(HardLines(budget, wait_ms), "event_type string, log_id long, fresh long", "Append", "EventTime")


def late_rows(query) -> int:
    """Rows that a query has dropped because they came behind the watermark."""
    return sum(op.get("numRowsDroppedByWatermark", 0) for p in query.recentProgress for op in p["stateOperators"])


def new_words(stream: DataFrame, by: str = "event_type") -> DataFrame:
    """Needs the RocksDB state store."""
    return stream.groupBy(by).transformWithStateInPandas(NewWords(), "event_type string, log_id long, fresh long", "Append", "None")


def label_batches(stream: DataFrame, budget: int, take: Callable[[DataFrame, int], None], checkpoint: str):
    """Every micro-batch hands its patterns to `take`, which selects within the budget."""
    return stream.writeStream.foreachBatch(lambda df, i: take(df, budget)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def drain(df: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Run to the end of what is there and return the memory sink (tests)."""
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination(120)
    q.stop()
    return df.sparkSession.table(name)
