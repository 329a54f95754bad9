"""Graph helpers over ``pairs(u, v)`` with ``u < v``."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..lineage import checkpointed


def symmetrize(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """Distinct undirected pairs without self-loops from a directed link table."""
    return links.where(F.col(a) != F.col(b)).select(F.least(a, b).cast("bigint").alias("u"), F.greatest(a, b).cast("bigint").alias("v")).distinct()


def both_ways(pairs: DataFrame) -> DataFrame:
    """``id, near``: each pair from both ends, in one scan."""
    ends = F.explode(F.array(F.struct(F.col("u").alias("id"), F.col("v").alias("near")), F.struct(F.col("v").alias("id"), F.col("u").alias("near")))).alias("e")
    return pairs.select(ends).select("e.id", "e.near")


def degrees(ids: DataFrame, pairs: DataFrame) -> DataFrame:
    """``id, degree`` for all nodes, isolated ones with 0."""
    counted = both_ways(pairs).groupBy("id").agg(F.count("*").alias("degree"))
    return ids.select("id").join(counted, "id", "left").select("id", F.coalesce("degree", F.lit(0)).cast("bigint").alias("degree"))


def profile(ids: DataFrame, pairs: DataFrame) -> DataFrame:
    """One row ``n, m, avg_degree, max_degree, isolated``."""
    return degrees(ids, pairs).agg(
        F.count("*").alias("n"),
        F.expr("CAST(sum(degree) DIV 2 AS BIGINT)").alias("m"),
        F.round(F.avg("degree"), 6).alias("avg_degree"),
        F.max("degree").alias("max_degree"),
        F.count_if(F.col("degree") == 0).alias("isolated"),
    )


def induced(pairs: DataFrame, ids: DataFrame) -> DataFrame:
    """Pairs with both ends in ``ids``."""
    return pairs.join(ids.select(F.col("id").alias("u")), "u", "left_semi").join(ids.select(F.col("id").alias("v")), "v", "left_semi").select("u", "v")


def triangles(pairs: DataFrame) -> DataFrame:
    """``a, b, c`` with a < b < c and all three pairs positive."""
    first = pairs.select(F.col("u").alias("a"), F.col("v").alias("b"))
    second = pairs.select(F.col("u").alias("b"), F.col("v").alias("c"))
    return first.join(second, "b").join(pairs.select(F.col("u").alias("a"), F.col("v").alias("c")), ["a", "c"], "left_semi").select("a", "b", "c")


def bad_triangles(pairs: DataFrame) -> DataFrame:
    """``center, a, b``: center near to both ends a < b, which are not near to each other."""
    ways = both_ways(pairs)
    left, right = ways.select(F.col("id").alias("center"), F.col("near").alias("a")), ways.select(F.col("id").alias("center"), F.col("near").alias("b"))
    return left.join(right, "center").where("a < b").join(pairs.select(F.col("u").alias("a"), F.col("v").alias("b")), ["a", "b"], "left_anti").select("center", "a", "b")


def components(ids: DataFrame, pairs: DataFrame, most_rounds: int = 60) -> DataFrame:
    """``id, component`` (its smallest id): smallest labels around, then pointer jumping."""
    ways = checkpointed(both_ways(pairs))
    labels = checkpointed(ids.select("id", F.col("id").alias("component")))
    for _ in range(most_rounds):
        around = ways.join(labels.select(F.col("id").alias("near"), F.col("component").alias("c")), "near").groupBy("id").agg(F.min("c").alias("c"))
        lower = labels.join(around, "id", "left").select("id", F.col("component").alias("old"), F.least("component", F.coalesce("c", "component")).alias("next"))
        jump = labels.select(F.col("id").alias("next"), F.col("component").alias("far"))
        moved = checkpointed(lower.join(jump, "next", "left").select("id", "old", F.least("next", F.coalesce("far", "next")).alias("component")))
        labels = moved.select("id", "component")
        if moved.where("component <> old").isEmpty():
            return labels
    raise RuntimeError("components still change after the allowed rounds")
