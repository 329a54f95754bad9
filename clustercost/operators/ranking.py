"""Random rank orders by hashed keys."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def rank_key(seed: Column | str, node: Column | str = "id") -> Column:
    """``md5(seed ':' id)``; smaller keys come earlier, ties by id."""
    seed = F.lit(seed) if isinstance(seed, str) else seed
    node = F.col(node) if isinstance(node, str) else node
    return F.md5(F.concat(seed, F.lit(":"), node.cast("string")))


def with_rank_key(nodes: DataFrame, seed: str) -> DataFrame:
    return nodes.withColumn("key", rank_key(seed))


def ranked_trials(ids: DataFrame, trials: DataFrame) -> DataFrame:
    """``trial, id, key`` for each trial's seed; ``trials`` is a small parameter table."""
    return ids.select("id").crossJoin(F.broadcast(trials.select("trial", "seed"))).select("trial", "id", rank_key(F.col("seed")).alias("key"))


def places(ranked: DataFrame, *by: str) -> DataFrame:
    """``ranked`` with ``place`` from 0 in (key, id) order, per group of ``by``, without a single-task window.

    Keys are uniform, so their first bits cut the order into even cells: cells are counted, the few
    counts are summed up to offsets, and rows are numbered within their cell.
    """
    parts = int(ranked.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    width = max(1, 65536 // max(1, min(parts * 4, 4096)))
    cut = ranked.withColumn("cell", F.floor(F.conv(F.substring("key", 1, 4), 16, 10).cast("int") / width).cast("int"))
    counts = cut.groupBy(*by, "cell").agg(F.count("*").alias("n"))
    earlier = Window.partitionBy(*by).orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)  # at most 4,096 rows a group
    offsets = counts.select(*by, "cell", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("before"))
    local = F.row_number().over(Window.partitionBy(*by, "cell").orderBy("key", "id")) - 1
    numbered = cut.withColumn("local", local).join(offsets, [*by, "cell"])
    return numbered.select(*ranked.columns, (F.col("before") + F.col("local")).cast("bigint").alias("place"))


def dense_rank_order(nodes: DataFrame, seed: str) -> DataFrame:
    """``rank`` from 1 in the order of the seed."""
    return places(with_rank_key(nodes, seed)).withColumn("rank", F.col("place") + 1).drop("place")
