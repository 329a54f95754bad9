"""Anchored lookups: the budgeted pivot with the search restricted to the earliest-ranked nodes.

Anchors are closed under earlier rank, so they settle among themselves; every other node
folds its anchors in rank order, by windows and sums, however many there are.  It ends with a pivot's label, with its own after the
budget is gone, or without a label.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .dense import CosineGraph
from .graph import both_ways
from .pivot import first_k, settle
from .sampling import first_of_trials


def anchors_of(ranked: DataFrame, trials: DataFrame) -> DataFrame:
    """``trial, id, key`` of each trial's ``r`` earliest nodes."""
    sized = ranked.join(F.broadcast(trials.select("trial", F.col("r").alias("wanted"))), "trial")
    return first_of_trials(sized, "key").select("trial", "id", "key")


def anchored_pivot(ranked: DataFrame, anchors: DataFrame, pairs: DataFrame, trials: DataFrame, k_max: int | None = None) -> DataFrame:
    """``trial, id, pivot (null where undetermined), calls, part`` for every node.

    ``trials`` has ``trial, k``; ``pairs`` are the positive pairs of which at least one end is an anchor
    in some trial (more do no harm).
    """
    k_max = k_max or trials.agg(F.max("k")).first()[0]
    mark = anchors.select("trial", F.col("id").alias("near"), F.col("key").alias("near_key"))
    if isinstance(pairs, CosineGraph):  # anchors are the earliest nodes, so the first neighbours that are anchors are the first anchors
        near = pairs.earlier(trials, k_max).join(mark.select("trial", "near"), ["trial", "near"], "left_semi").select("trial", "id", "near", "near_key")
    else:
        near = both_ways(pairs).join(mark, "near").join(ranked.select("trial", "id", "key"), ["trial", "id"]).where(F.struct("near_key", "near") < F.struct("key", "id")).select("trial", "id", "near", "near_key")
        near = first_k(near, k_max).drop("place")  # each costs one call at least, so no lookup sees more
    among = near.join(anchors.select("trial", "id"), ["trial", "id"], "left_semi")
    settled = settle(anchors, among, k_max)
    # a settled anchor's exact pivot status is known when it did not time out at the largest budget
    state = settled.select("trial", F.col("id").alias("near"), F.col("calls"), (~F.col("timed_out") & (F.col("pivot") == F.col("id"))).alias("is_pivot"))
    # a fold that gathers no list: it ends at the first pivot in order, and has spent the calls up to there
    order = F.struct("near_key", "near")
    stop = F.min(F.when(F.col("is_pivot"), order)).over(Window.partitionBy("trial", "id"))
    spent = near.join(state, ["trial", "near"]).withColumn("stop", stop).where(F.col("stop").isNull() | (order <= F.col("stop")))
    folds = spent.groupBy("trial", "id").agg(F.sum(F.col("calls").cast("bigint")).alias("spent"), F.max("stop.near").alias("first"))
    rows = ranked.select("trial", "id").join(F.broadcast(trials.select("trial", F.col("k").cast("int").alias("k"))), "trial").join(folds, ["trial", "id"], "left").join(anchors.select("trial", "id", F.lit(True).alias("anchor")), ["trial", "id"], "left")
    calls = F.least(1 + F.coalesce("spent", F.lit(0).cast("bigint")), (F.col("k") + 1).cast("bigint")).cast("int")
    folded = rows.withColumn("calls", calls).withColumn("f", F.struct("calls", F.when(F.col("calls") <= F.col("k"), F.col("first")).alias("pivot")))
    own = (F.col("f.calls") > F.col("k")) | F.coalesce("anchor", F.lit(False)) & F.col("f.pivot").isNull()
    pivot = F.when(own, F.col("id")).otherwise(F.col("f.pivot"))
    return folded.select("trial", "id", pivot.alias("pivot"), F.col("f.calls").alias("calls"), F.when(pivot.isNull(), "B").otherwise("A").alias("part"))


def split_nodes(labels: DataFrame) -> DataFrame:
    """Anchored (``A``) and residual (``B``) nodes."""
    return labels.withColumn("part", F.when(F.col("pivot").isNull(), F.lit("B")).otherwise(F.lit("A")))


def part_sizes(labels: DataFrame, degrees: DataFrame) -> DataFrame:
    """``part, nodes, max_degree``."""
    return labels.join(degrees, "id").groupBy("part").agg(F.count("*").alias("nodes"), F.max("degree").alias("max_degree"))
