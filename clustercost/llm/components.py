"""Connected components of a link table by smallest labels and pointer jumping."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .exchange import checkpointed


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """``node, class`` for all ends of ``links(a, b)``; class is the component's smallest node.

    Each round gives a node the smallest label around it and then its label's label, so
    labels travel twice as far each time; rounds end when no label changes.
    """
    both = checkpointed(links.select(F.col("a").alias("node"), F.col("b").alias("near")).unionByName(links.select(F.col("b").alias("node"), F.col("a").alias("near"))).distinct())
    labels = checkpointed(both.groupBy("node").agg(F.min("near").alias("low")).select("node", F.least("node", "low").alias("class")))
    for _ in range(most_rounds):
        around = both.join(labels.select(F.col("node").alias("near"), F.col("class").alias("c")), "near").groupBy("node").agg(F.min("c").alias("c"))
        lower = labels.join(around, "node").select("node", F.least("class", "c").alias("next"), F.col("class").alias("old"))
        jump = labels.select(F.col("node").alias("next"), F.col("class").alias("far"))
        moved = checkpointed(lower.join(jump, "next", "left").select("node", F.coalesce(F.least("next", "far"), "next").alias("class"), "old"))
        labels = moved.select("node", "class")
        if moved.where(F.col("class") != F.col("old")).isEmpty():
            return labels
    raise RuntimeError("labels still change after the allowed rounds")
