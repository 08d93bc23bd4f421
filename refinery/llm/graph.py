"""Connected components of an edge table, in DataFrame joins; no link or label reaches the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from refinery.llm.common import drop_stage, stage


def components(edges: DataFrame) -> DataFrame:
    """edges: a, b (any orderable type). Returns node, label: the least node of its component.

    Each round takes the least label among a node and its neighbours, then the label of that label, so paths shorten
    by half at least and the rounds grow with the logarithm of the longest path. A round's labels are written to the
    shared folder. The centre of a star, or the label of a large group, is a hot key in the two joins that carry labels: both
    sides are plain exchanges under nothing that needs a key's rows together, so the adaptive planner splits it over tasks; the
    sums by node combine before they are shuffled. An empty edge table gives an empty result.
    """
    both = edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct()
    both = stage(both, "edges")
    labels = stage(both.groupBy(F.col("a").alias("node")).agg(F.least(F.col("node"), F.min("b")).alias("label")), "labels")
    while True:
        near = both.hint("merge").join(labels.withColumnRenamed("node", "b"), "b").groupBy(F.col("a").alias("node")).agg(F.min("label").alias("near"))
        step = stage(labels.join(near, "node").select("node", "label", F.least("label", "near").alias("new")), "step")
        jump = step.select(F.col("node").alias("new"), F.col("new").alias("far"))
        least = F.least("new", F.coalesce("far", "new"))
        moved = stage(step.hint("merge").join(jump, "new", "left").select("node", least.alias("label"), (least < F.col("label")).alias("changed")), "labels")
        drop_stage(labels)
        drop_stage(step)
        labels = moved.select("node", "label")
        if moved.where("changed").isEmpty():
            drop_stage(both)
            return labels


def merge_labels(labels: DataFrame | None, edges: DataFrame) -> DataFrame:
    """Labels (node, label) after edges (a, b) have joined more nodes; labels may be None. Only the edges between different labels
    are followed."""
    if labels is None:
        return components(edges)
    name = lambda side: labels.select(F.col("node").alias(side), F.col("label").alias(f"{side}_label"))
    named = edges.hint("merge").join(name("a"), "a", "left").hint("merge").join(name("b"), "b", "left")
    named = named.select(F.coalesce("a_label", "a").alias("a"), F.coalesce("b_label", "b").alias("b")).where("a <> b").distinct()
    fresh = components(named)
    moved = labels.hint("merge").join(fresh.select(F.col("node").alias("label"), F.col("label").alias("new")), "label", "left").select("node", F.coalesce("new", "label").alias("label"))
    others = fresh.join(labels.select("node").hint("merge"), "node", "left_anti")
    return stage(moved.unionByName(others), "labels")
