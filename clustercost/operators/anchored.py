"""Estimator of the anchored part: mismatches with at least one anchored end.

A first sample classifies nodes by their mismatches with it.  Nodes with many are
rescaled; of the others a second sample gets exact degrees.  Half the sum of both is the estimate.

``mode`` decides what the rescaled counts come from: ``paper`` uses the classifying sample itself,
``two_sample`` an independent one of the same size (free of the selection's bias), and
``floor`` raises the cut-off to a least number of hits.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..lineage import checkpointed
from .dense import CosineGraph
from .graph import both_ways
from .mismatch import is_anchored_mismatch
from .sampling import bottom_k_trials

FLOOR_HITS = 4


def hit_counts(labels: DataFrame, sample: DataFrame, pairs: DataFrame) -> DataFrame:
    """``trial, id, hits``: anchored mismatches of every node with the sample (``trial, id, pivot``), itself excluded."""
    if isinstance(pairs, CosineGraph):
        counted = pairs.counted(labels, sample)
    else:
        mine = sample.select("trial", F.col("id").alias("near"), F.col("pivot").alias("ps"))
        similar = both_ways(pairs).join(mine, "near").join(labels.select("trial", "id", F.col("pivot").alias("pu")), ["trial", "id"])
        counted = similar.groupBy("trial", "id").agg(F.count_if(is_anchored_mismatch(F.col("pu"), F.col("ps"), F.lit(True))).alias("cross"), F.count_if(F.col("pu") == F.col("ps")).alias("same"))
    held = sample.where("pivot IS NOT NULL").groupBy("trial", "pivot").agg(F.count("*").alias("held"))
    self_hit = sample.select("trial", "id", F.lit(1).alias("own"))
    rows = labels.select("trial", "id", "pivot").join(counted, ["trial", "id"], "left").join(held, ["trial", "pivot"], "left").join(self_hit, ["trial", "id"], "left")
    inner = F.when(F.col("pivot").isNotNull(), F.coalesce("held", F.lit(0)) - F.coalesce("own", F.lit(0)) - F.coalesce("same", F.lit(0))).otherwise(0)
    return rows.select("trial", "id", (F.coalesce("cross", F.lit(0)) + inner).cast("bigint").alias("hits"))


def sample_degrees(labels: DataFrame, sample: DataFrame, pairs: DataFrame) -> DataFrame:
    """``trial, id, degree_a`` of the sampled nodes, over all nodes."""
    if isinstance(pairs, CosineGraph):
        counted = pairs.counted(labels, sample, of="others")
    else:
        mine = sample.select("trial", "id", F.col("pivot").alias("pu"))
        ways = both_ways(pairs).join(mine, "id").join(labels.select("trial", F.col("id").alias("near"), F.col("pivot").alias("pv")), ["trial", "near"])
        counted = ways.groupBy("trial", "id").agg(F.count_if(is_anchored_mismatch(F.col("pu"), F.col("pv"), F.lit(True))).alias("cross"), F.count_if(F.col("pu") == F.col("pv")).alias("same"))
    sizes = labels.where("pivot IS NOT NULL").groupBy("trial", "pivot").agg(F.count("*").alias("c"))
    rows = sample.select("trial", "id", "pivot").join(counted, ["trial", "id"], "left").join(sizes, ["trial", "pivot"], "left")
    inner = F.when(F.col("pivot").isNotNull(), F.col("c") - 1 - F.coalesce("same", F.lit(0))).otherwise(0)
    return rows.select("trial", "id", (F.coalesce("cross", F.lit(0)) + inner).cast("bigint").alias("degree_a"))


def classify_by_sample(labels: DataFrame, pairs: DataFrame, trials: DataFrame, mode: str = "two_sample") -> DataFrame:
    """``trial, id, pivot, hits, is_high, estimate_hits``; ``trials`` has ``trial, seed, t1, cutoff``."""
    first = bottom_k_trials(labels, trials, "t1", "s1")
    limit = F.greatest(F.col("cutoff"), F.lit(float(FLOOR_HITS))) if mode == "floor" else F.col("cutoff")
    rows = labels.select("trial", "id", "pivot").join(hit_counts(labels, first, pairs), ["trial", "id"]).join(F.broadcast(trials.select("trial", "cutoff")), "trial")
    high = rows.withColumn("is_high", (F.col("hits") >= limit) & (F.col("hits") > 0)).drop("cutoff")
    if mode != "two_sample":
        return high.withColumn("estimate_hits", F.col("hits"))
    second = hit_counts(labels, bottom_k_trials(labels, trials, "t1", "s1b"), pairs)
    return high.join(second.withColumnRenamed("hits", "estimate_hits"), ["trial", "id"])


def estimate_anchored_part(labels: DataFrame, pairs: DataFrame, trials: DataFrame, mode: str = "two_sample") -> DataFrame:
    """``trial, m_a, n, n_low, t1, t2`` with the sizes that were really drawn; ``trials`` has ``trial, seed, t1, t2, cutoff``."""
    rows = classify_by_sample(labels, pairs, trials, mode)
    rows = checkpointed(rows) if isinstance(pairs, CosineGraph) else rows
    totals = rows.groupBy("trial").agg(F.count("*").alias("n"), F.count_if(~F.col("is_high")).alias("n_low"), F.coalesce(F.sum(F.when(F.col("is_high"), F.col("estimate_hits"))), F.lit(0)).alias("high_hits"))
    low = bottom_k_trials(rows.where(~F.col("is_high")).select("trial", "id", "pivot"), trials, "t2", "s2")
    low = checkpointed(low) if isinstance(pairs, CosineGraph) else low
    degrees = sample_degrees(labels, low, pairs).groupBy("trial").agg(F.sum("degree_a").alias("d"), F.count("*").alias("drawn"))
    met = totals.join(degrees, "trial", "left").join(F.broadcast(trials.select("trial", "t1")), "trial").withColumn("t1", F.least("t1", "n"))
    drawn = F.coalesce("drawn", F.lit(0))
    low_sum = F.coalesce(F.col("n_low") * F.col("d") / F.nullif("drawn", F.lit(0)), F.lit(0.0))
    high_sum = F.coalesce(F.col("n") * F.col("high_hits") / F.nullif("t1", F.lit(0)), F.lit(0.0))
    return met.select("trial", ((high_sum + low_sum) / 2).alias("m_a"), "n", "n_low", F.col("t1").cast("bigint").alias("t1"), drawn.cast("bigint").alias("t2"))
