"""Connected components of a graph of links, as tables: nothing of the graph is collected."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hamcover.llm.common import discard, written


def components(links: DataFrame) -> DataFrame:
    """links: a, b. Returns id, label: the least id of its component, for all ids in links.

    Each round takes the least label among a node and its neighbours, then twice the label's label, so chains
    halve; rounds end when no label changes, so their number grows with the logarithm of the longest chain. Each writes two tables and deletes those of the round before. Labels are aggregated before they are shuffled, so a node with many links costs
    one row for each task.
    """
    both = written(links.select("a", "b").union(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b"), "links")
    table = labels = written(both.groupBy(F.col("a").alias("id")).agg(F.min("b").alias("least")).select("id", F.least("id", "least").alias("label")), "labels")
    while True:
        near = both.join(labels, F.col("b") == F.col("id")).groupBy("a").agg(F.min("label").alias("least"))
        step = labels.join(near, F.col("id") == F.col("a")).select("id", F.least("label", "least").alias("label"), F.col("label").alias("was"))
        shorter = first = written(step, "labels")
        for _ in range(2):
            target = shorter.select(F.col("id").alias("t"), F.col("label").alias("to"))
            shorter = shorter.join(target, F.col("label") == F.col("t"), "left").select("id", F.least("label", F.coalesce("to", "label")).alias("label"), "was")
        shorter = written(shorter, "labels")
        discard(table, first)
        changed = shorter.where("label <> was").limit(1).count()
        table, labels = shorter, shorter.select("id", "label")
        if not changed:
            discard(both)
            return labels
