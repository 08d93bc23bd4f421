"""Similarity graphs: survivors of an insert-in-order reference set, and connected components.

Inserting items one by one and keeping an item when nothing kept is similar to it gives the lexicographically first maximal
independent set of the graph. Rounds find the same set in parallel: an undecided node without an undecided smaller neighbour is kept, and its
neighbours go. Each round is joins over edges and a table in the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from refinery.operators.storage import materialize, remove


def first_independent_set(edges: DataFrame) -> DataFrame:
    """edges: a, b with a before b in the order. Returns node, kept, by (the first kept neighbour that blocks it)."""
    edges = materialize(edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a < b").distinct(), "edges")
    decided = None
    left = edges
    while not left.isEmpty():
        blocked = left.select(F.col("b").alias("node")).distinct()
        kept = left.select(F.col("a").alias("node")).distinct().join(blocked, "node", "left_anti")
        gone = left.join(kept.withColumnRenamed("node", "a"), "a").groupBy(F.col("b").alias("node")).agg(F.min("a").alias("by"))
        now = materialize(kept.select("node", F.lit(True).alias("kept"), F.lit(None).cast(edges.schema["a"].dataType).alias("by")).unionByName(gone.select("node", F.lit(False).alias("kept"), "by")), "decided")
        decided = now if decided is None else decided.unionByName(now)
        done = now.select("node")
        rest = left.join(done.withColumnRenamed("node", "a"), "a", "left_anti").join(done.withColumnRenamed("node", "b"), "b", "left_anti")
        after = materialize(rest, "left")
        # nodes whose every neighbour went are kept
        free = left.select(F.col("a").alias("node")).unionByName(left.select(F.col("b").alias("node"))).distinct().join(done, "node", "left_anti").join(after.select(F.col("a").alias("node")).unionByName(after.select(F.col("b").alias("node"))), "node", "left_anti")
        decided = decided.unionByName(materialize(free.select("node", F.lit(True).alias("kept"), F.lit(None).cast(edges.schema["a"].dataType).alias("by")), "free"))
        left = after
    if decided is None:
        return edges.select(F.col("a").alias("node"), F.lit(True).alias("kept"), F.col("a").alias("by"))
    # name the least kept neighbour, whatever the round in which it blocked
    kept = decided.where("kept").select(F.col("node").alias("a"))
    by = edges.join(kept, "a").groupBy(F.col("b").alias("node")).agg(F.min("a").alias("first"))
    return decided.join(by, "node", "left").select("node", "kept", F.when(~F.col("kept"), F.col("first")).alias("by"))


def components(edges: DataFrame) -> DataFrame:
    """node, label (least node of its component), by least labels of neighbours and label jumping."""
    both = edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct()
    both = materialize(both, "both")
    labels = materialize(both.groupBy(F.col("a").alias("node")).agg(F.least(F.col("node"), F.min("b")).alias("label")), "labels")
    while True:
        near = both.join(labels.withColumnRenamed("node", "b"), "b").groupBy(F.col("a").alias("node")).agg(F.min("label").alias("near"))
        step = labels.join(near, "node").select("node", "label", F.least("label", "near").alias("new"))
        jump = step.select(F.col("node").alias("new"), F.col("new").alias("far"))
        moved = step.join(jump, "new", "left").select("node", "label", F.least("new", F.coalesce("far", "new")).alias("next"))
        moved = materialize(moved.select("node", F.col("next").alias("label"), (F.col("next") < F.col("label")).alias("changed")), "labels")
        remove(labels)
        labels = moved.select("node", "label")
        if moved.where("changed").isEmpty():
            remove(both)
            return labels
