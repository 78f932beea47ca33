"""Connected components of an edge table, by labels that halve their way down."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import shared

MOST_ROUNDS = 60


def components(edges: DataFrame) -> DataFrame:
    """(id, component) of every end of the edges (a, b); a component is its smallest id.

    Each round takes the smallest label among a node's neighbours and then the
    label of that label.  Rounds are written to the shared folder and their
    number grows with the logarithm of a component's width.  Nothing but the
    count of changes reaches the driver.
    """
    spark = edges.sparkSession
    both = edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a != b").distinct()
    both = shared.written(both, "edges")
    labels = shared.written(both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("label")).withColumnRenamed("a", "id"), "labels")
    for _ in range(MOST_ROUNDS):
        near = both.join(labels, both.b == labels.id).groupBy("a").agg(F.min("label").alias("near"))
        step = labels.join(near, labels.id == near.a).select("id", "label", F.least("label", "near").alias("next"))
        step = shared.written(step, "steps")
        jump = step.select(F.col("id").alias("next"), F.col("next").alias("further"))
        done = step.join(jump, "next", "left").select("id", F.least("next", F.coalesce("further", "next")).alias("label"), (F.least("next", F.coalesce("further", "next")) != F.col("label")).alias("changed"))
        done = shared.written(done, "labels")
        labels = done.select("id", "label")
        if not done.where("changed").limit(1).collect():
            break
    else:
        raise RuntimeError("components did not settle")
    return labels.select("id", F.col("label").alias("component"))
