"""Choosing a similarity threshold by its clustering cost, and cost as a measure of inconsistency."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..lineage import checkpointed
from . import sets
from .mismatch import clustering_cost
from .pivot import earlier_neighbours, settle
from .ranking import rank_key
from .similarity import Jaccard


def tune_threshold(ids: DataFrame, scored: DataFrame, grid: list[float], seed: str = "s") -> DataFrame:
    """``theta, m, cost, is_best``: exact pivot cost at each threshold of the grid.

    ``scored(u, v, score)`` holds the pairs above the least threshold; one join serves the whole grid,
    whose points become trials.  Ties go to the smaller threshold.
    """
    spark = ids.sparkSession
    points = spark.createDataFrame([(i, float(x)) for i, x in enumerate(sorted(grid))], "trial int, theta double")
    held = checkpointed(scored)
    pairs = held.crossJoin(F.broadcast(points)).where("score > theta").select("trial", "u", "v")
    ranked = ids.select("id").crossJoin(F.broadcast(points.select("trial"))).select("trial", "id", rank_key(seed).alias("key"))
    a, b = ranked.select("trial", F.col("id").alias("u"), F.col("key").alias("ku")), ranked.select("trial", F.col("id").alias("v"), F.col("key").alias("kv"))
    first = F.struct("ku", "u") < F.struct("kv", "v")
    met = pairs.join(a, ["trial", "u"]).join(b, ["trial", "v"])
    earlier = met.select("trial", F.when(first, F.col("v")).otherwise(F.col("u")).alias("id"), F.when(first, F.col("u")).otherwise(F.col("v")).alias("near"), F.when(first, F.col("ku")).otherwise(F.col("kv")).alias("near_key"))
    labels = checkpointed(settle(ranked, earlier))
    return _chosen(trial_costs(labels, pairs), points)


def tune_sets(nodes: DataFrame, similarity: Jaccard, grid: list[float], seed: str = "s", block: int = sets.BLOCK) -> DataFrame:
    """As ``tune_threshold`` over ``similarity.scored(nodes)`` (thresholds of 0 or more), which is not listed: pairs are counted by blocks of sets."""
    grid = sorted(float(x) for x in grid)
    points = nodes.sparkSession.createDataFrame(list(enumerate(grid)), "trial int, theta double")
    held, n = sets.shared_sets(nodes, similarity, seed), nodes.count()
    cost = nodes.sparkSession.createDataFrame(sets.trial_costs(held, grid, n, block) if n else [], "trial int, m bigint, cost bigint")
    return _chosen(cost, points)


def _chosen(cost: DataFrame, points: DataFrame) -> DataFrame:
    best = cost.agg(F.min_by("trial", F.struct("cost", "trial")).alias("best"))
    return cost.join(F.broadcast(points), "trial").crossJoin(F.broadcast(best)).select("theta", "m", "cost", (F.col("trial") == F.col("best")).alias("is_best"))


def trial_costs(labels: DataFrame, pairs: DataFrame) -> DataFrame:
    """``trial, n, m, cost`` where each trial has its own pairs ``(trial, u, v)``."""
    a = labels.select("trial", F.col("id").alias("u"), F.col("pivot").alias("pu"))
    b = labels.select("trial", F.col("id").alias("v"), F.col("pivot").alias("pv"))
    inside = pairs.join(a, ["trial", "u"]).join(b, ["trial", "v"]).groupBy("trial").agg(F.count("*").alias("m"), F.count_if(F.col("pu") == F.col("pv")).alias("kept"))
    sizes = labels.groupBy("trial", "pivot").agg(F.count("*").alias("c")).groupBy("trial").agg(F.sum("c").alias("n"), F.expr("CAST(sum(c * (c - 1) DIV 2) AS BIGINT)").alias("together"))
    m, kept = F.coalesce("m", F.lit(0)), F.coalesce("kept", F.lit(0))
    return sizes.join(inside, "trial", "left").select("trial", "n", m.alias("m"), (m + F.col("together") - 2 * kept).alias("cost"))


def inconsistency(ids: DataFrame, pairs: DataFrame, group: str, seed: str = "s") -> DataFrame:
    """``group, n, cost, share`` and a total row (null group): pivot cost within each group of ``ids(id, group)``.

    Pairs count where both ends are in one group; the total row clusters all nodes together.
    """
    grouped = ids.select("id", F.col(group).alias("g"))
    within = pairs.join(grouped.select(F.col("id").alias("u"), F.col("g").alias("gu")), "u").join(grouped.select(F.col("id").alias("v"), F.col("g").alias("gv")), "v").where("gu <=> gv").select("u", "v")
    ranked = ids.select(F.lit(0).alias("trial"), "id", rank_key(seed).alias("key"))
    local = checkpointed(settle(ranked, earlier_neighbours(ranked, within)))
    by = _by_group(local.join(grouped, "id"), within)
    whole = clustering_cost(settle(ranked, earlier_neighbours(ranked, pairs)), pairs).select(F.lit(None).cast("string").alias("g"), "n", "cost")
    rows = by.unionByName(whole)
    return rows.select(F.col("g").alias(group), "n", "cost", F.round(F.col("cost") / F.nullif(F.expr("n * (n - 1) DIV 2"), F.lit(0)), 9).alias("share"))


def _by_group(labels: DataFrame, within: DataFrame) -> DataFrame:
    a, b = labels.select(F.col("id").alias("u"), F.col("pivot").alias("pu"), "g"), labels.select(F.col("id").alias("v"), F.col("pivot").alias("pv"))
    inside = within.join(a, "u").join(b, "v").groupBy("g").agg(F.count("*").alias("m"), F.count_if(F.col("pu") == F.col("pv")).alias("kept"))
    sizes = labels.groupBy("g", "pivot").agg(F.count("*").alias("c")).groupBy("g").agg(F.sum("c").alias("n"), F.expr("CAST(sum(c * (c - 1) DIV 2) AS BIGINT)").alias("together"))
    m, kept = F.coalesce("m", F.lit(0)), F.coalesce("kept", F.lit(0))
    return sizes.join(inside, sizes["g"].eqNullSafe(inside["g"]), "left").select(sizes["g"], "n", (m + F.col("together") - 2 * kept).alias("cost"))
