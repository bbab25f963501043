"""Decisions that the query optimiser cannot make, with the figures they rest on."""

from __future__ import annotations

from dataclasses import dataclass

#: patterns up to which the rounds' bookkeeping stays with the driver
LOCAL_PATTERNS = 2_000
#: patterns up to which pair distances are computed there as well
LOCAL_PAIRS = 600
#: classes of lines (by form, truth and length) up to which their predictions are worked out there
LOCAL_CLASSES = 10_000
#: labelled words up to which the labelled vocabulary is broadcast
BROADCAST_WORDS = 1_000_000


@dataclass(frozen=True)
class Decision:
    what: str
    choice: str
    because: str

    def __str__(self) -> str:
        return f"{self.what}: {self.choice} ({self.because})"


def choose(patterns: int, labelled_words: int = 0, similarity: str = "classed", polarity: str = "similar_free") -> dict[str, Decision]:
    native = similarity in ("exact", "classed") and polarity == "similar_free"
    return {
        "distance": Decision("distance", "native" if native else "arrow", f"{similarity}, {polarity}"),
        "pairs": Decision("pairs", "driver" if patterns <= LOCAL_PAIRS else "pruned join" if native else "size-bounded join", f"{patterns} patterns"),
        "greedy": Decision("greedy", "driver" if patterns <= LOCAL_PATTERNS else "distributed", f"{patterns} patterns"),
        "context": Decision("context", "broadcast" if labelled_words <= BROADCAST_WORDS else "join", f"{labelled_words} labelled words"),
    }
