"""Connected components of a distributed edge table.

Labels sink along edges and along pointers to the labels of labels, so paths
halve each round. Every round is written to the shared folder: no lineage
grows, and nothing but the number of changed labels reaches the driver. Hubs
cost nothing special: neighbours are reduced before they are shuffled, and the
joins are plain equi-joins that adaptive execution may split.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tplforge.llm.common import delete, scratch, stored_at


def components(edges: DataFrame, name: str = "components") -> DataFrame:
    """edges(a, b) of longs, either direction -> (node, label): label is the least node that can be reached."""
    spark = edges.sparkSession
    root = scratch(spark, name)
    both = edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).filter("a <> b").distinct()
    both = stored_at(both, f"{root}/edges")
    labels = stored_at(both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.col("node")).alias("label")), f"{root}/0")
    turn = 0
    while True:
        near = both.join(labels.select(F.col("node").alias("b"), "label"), "b").groupBy(F.col("a").alias("node")).agg(F.min("label").alias("near"))
        sunk = labels.join(near, "node", "left").select("node", F.col("label").alias("old"), F.least("label", F.coalesce("near", "label")).alias("label"))
        of = labels.select(F.col("node").alias("label"), F.col("label").alias("further"))
        jumped = stored_at(sunk.join(of, "label", "left").select("node", "old", F.least("label", F.coalesce("further", "label")).alias("label")), f"{root}/{turn + 1}")
        changed = jumped.filter("label <> old").limit(1).count()
        labels = jumped.select("node", "label")
        delete(spark, f"{root}/{turn}")
        turn += 1
        if not changed:
            delete(spark, f"{root}/edges")
            return labels
