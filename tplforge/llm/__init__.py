"""Training-data operators: filtering, deduplication, scoring, mixing."""
