"""Estimator of the residual part: mismatches between nodes that the anchors do not determine.

Sampled residual nodes bring their neighbourhoods; members whose budgeted pivot is the sampled
node form its cluster (none, if it is no pivot).  Each cluster counts its inner negatives
whole and its positives to other residual nodes half, and the sum is scaled to all residual
nodes.  Outer positives are the members' residual degrees less twice the inner positives, so the
last scan of the printed method is not needed.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..lineage import checkpointed
from .dense import CosineGraph
from .graph import both_ways
from .sampling import bottom_k_trials


def neighbourhoods(centers: DataFrame, pairs: DataFrame) -> DataFrame:
    """``trial, center, member``: each center's positive neighbours and itself."""
    near = centers.select("trial", F.col("id").alias("center")).join(both_ways(pairs).select(F.col("id").alias("center"), F.col("near").alias("member")), "center").select("trial", "center", "member")
    return near.unionByName(centers.select("trial", F.col("id").alias("center"), F.col("id").alias("member")))


def cluster_of(centers: DataFrame, labels: DataFrame, pairs: DataFrame) -> DataFrame:
    """``trial, center, member``: members labelled by the center, where the center is its own pivot.

    A node that timed out is the center of itself only: nobody else carries its label.
    """
    if isinstance(pairs, CosineGraph):  # whoever carries a center's label is near to it or the center
        return labels.join(centers.select("trial", F.col("id").alias("pivot")), ["trial", "pivot"], "left_semi").select("trial", F.col("pivot").alias("center"), F.col("id").alias("member"))
    members = neighbourhoods(centers, pairs)
    return members.join(labels.select("trial", F.col("id").alias("member"), F.col("pivot").alias("center")), ["trial", "member", "center"], "left_semi")


def center_mismatch_counts(clusters: DataFrame, labels: DataFrame, pairs: DataFrame) -> DataFrame:
    """``trial, center, size, n_in, n_out`` for non-empty clusters; ``labels`` gives the residual nodes (null pivot)."""
    residual = labels.where("pivot IS NULL").select("trial", "id")
    if isinstance(pairs, CosineGraph):
        clusters = checkpointed(clusters)
        held = clusters.select("trial", F.col("member").alias("id"), F.col("center").alias("pivot"))
        by_center = lambda d, name: d.join(held, ["trial", "id"]).groupBy("trial", F.col("pivot").alias("center")).agg(F.sum("n").alias(name))
        outer = by_center(pairs.counted(residual.withColumn("pivot", F.lit(None).cast("bigint")), held, of="others").select("trial", "id", F.col("cross").alias("n")), "ends")
        inner = by_center(pairs.counted(held, held).select("trial", "id", F.col("same").alias("n")), "ends_in").select("trial", "center", F.expr("ends_in DIV 2").alias("kept"))
    else:
        ways = both_ways(pairs)
        outer = clusters.join(ways.select(F.col("id").alias("member"), "near"), "member").join(residual.select("trial", F.col("id").alias("near")), ["trial", "near"], "left_semi").groupBy("trial", "center").agg(F.count("*").alias("ends"))
        a = clusters.select("trial", "center", F.col("member").alias("u"))
        b = clusters.select("trial", "center", F.col("member").alias("v"))
        inner = a.join(pairs.select("u", "v"), "u").join(b, ["trial", "center", "v"]).groupBy("trial", "center").agg(F.count("*").alias("kept"))
    sizes = clusters.groupBy("trial", "center").agg(F.count("*").alias("size"))
    rows = sizes.join(outer, ["trial", "center"], "left").join(inner, ["trial", "center"], "left")
    kept, ends = F.coalesce("kept", F.lit(0)), F.coalesce("ends", F.lit(0))
    together = F.expr("size * (size - 1) DIV 2")
    return rows.select("trial", "center", "size", (together - kept).cast("bigint").alias("n_in"), (ends - 2 * kept).cast("bigint").alias("n_out"))


def sample_centers(labels: DataFrame, trials: DataFrame) -> DataFrame:
    """``trial, id``: the residual sample; ``trials`` has ``trial, seed, t``."""
    return bottom_k_trials(labels.where("pivot IS NULL").select("trial", "id"), trials, "t", "sb")


def estimate_residual_part(labels: DataFrame, member_labels: DataFrame, pairs: DataFrame, trials: DataFrame) -> DataFrame:
    """``trial, m_b, n_b, t`` with the size that was really drawn; 0 where no node is residual.

    ``labels`` are anchored labels; ``member_labels(trial, id, pivot)`` are budgeted ones of at least
    the neighbourhoods' members (by walks or by rounds).
    """
    centers = sample_centers(labels, trials)
    centers = checkpointed(centers) if isinstance(pairs, CosineGraph) else centers
    counts = center_mismatch_counts(cluster_of(centers, member_labels, pairs), labels, pairs)
    sums = counts.groupBy("trial").agg(F.sum(F.col("n_in") + F.col("n_out") / 2).alias("s"))
    totals = labels.groupBy("trial").agg(F.count_if(F.col("pivot").isNull()).alias("n_b"))
    met = totals.join(F.broadcast(trials.select("trial", "t")), "trial").join(sums, "trial", "left").withColumn("t", F.least("t", "n_b"))
    scaled = F.coalesce(F.col("n_b") * F.col("s") / F.nullif("t", F.lit(0)), F.lit(0.0))
    return met.select("trial", scaled.alias("m_b"), "n_b", F.col("t").cast("bigint").alias("t"))
