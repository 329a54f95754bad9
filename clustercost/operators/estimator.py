"""The compact cost estimate: anchored part plus residual part, for one or many trials at once.

A trial is a row ``trial, seed, k, r, t1, t2, t, cutoff``; trials multiply the state, not the scans,
and positive pairs do not depend on the order, so one similarity join serves all.
"""

from __future__ import annotations

from dataclasses import asdict
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..lineage import checkpointed
from ..params import Sizes, budget_sizes, theory_sizes, words_stored
from .anchored import classify_by_sample, estimate_anchored_part
from .dense import CosineGraph
from .lookup import anchored_pivot, anchors_of
from .pivot import earlier_neighbours, settle, within_budget
from .ranking import ranked_trials
from .residual import estimate_residual_part, neighbourhoods, sample_centers
from .sampling import bottom_k_trials
from .similarity import Cosine, Similarity
from .walker import walk_pivots

TRIALS = "trial int, seed string, k int, space double, r int, t1 int, t2 int, t int, cutoff double"


def trial_table(spark: SparkSession, rows: list[tuple[str, int, float, Sizes]]) -> DataFrame:
    """Trials from ``(seed, k, space, sizes)``, numbered in order."""
    return spark.createDataFrame([(i, seed, k, space, *asdict(s).values()) for i, (seed, k, space, s) in enumerate(rows)], TRIALS)


def exact_labels(ids: DataFrame, pairs: DataFrame, trials: DataFrame, k_max: int) -> DataFrame:
    """Exact pivots and calls (saturated at k_max + 1) by *seed*: ``trial, id, pivot, calls, late``, shared by trials of one seed.

    ``late`` marks lookups beyond ``k_max``, whose exact pivot is then not kept.
    """
    seeds = trials.groupBy("seed").agg(F.min("trial").alias("trial"))
    ranked = ranked_trials(ids, seeds)
    earlier = pairs.earlier(seeds, k_max) if isinstance(pairs, CosineGraph) else earlier_neighbours(ranked, pairs)
    labels = settle(ranked, earlier, k_max)
    by_seed = labels.join(F.broadcast(seeds), "trial").drop("trial")
    return by_seed.join(F.broadcast(trials.select("trial", "seed", "k")), "seed").drop("seed")


def budgeted_trials(ids: DataFrame, pairs: DataFrame, trials: DataFrame) -> DataFrame:
    """``trial, id, pivot, calls, timed_out`` under each trial's own k."""
    k_max = trials.agg(F.max("k")).first()[0]
    return within_budget(exact_labels(ids, pairs, trials, k_max), "k").select("trial", "id", "pivot", "calls", "timed_out")


def estimate_trials(ids: DataFrame, pairs: DataFrame, trials: DataFrame, mode: str = "two_sample", member_labels: DataFrame | None = None) -> DataFrame:
    """``trial, estimate, m_a, m_b, n, n_b, r, t1, t2, t`` for all trials in one plan."""
    ranked = checkpointed(ranked_trials(ids, trials))
    labels = checkpointed(anchored_pivot(ranked, checkpointed(anchors_of(ranked, trials)), pairs, trials))
    if member_labels is None:
        member_labels = checkpointed(budgeted_trials(ids, pairs, trials))
    a = estimate_anchored_part(labels, pairs, trials, mode)
    b = estimate_residual_part(labels, member_labels, pairs, trials)
    return a.join(b, "trial").join(F.broadcast(trials.select("trial", "r")), "trial").select("trial", (F.col("m_a") + F.col("m_b")).alias("estimate"), "m_a", "m_b", "n", "n_b", F.least("r", "n").cast("bigint").alias("r"), "t1", "t2", "t")


def estimate_cost(
    nodes: DataFrame,
    similarity: Similarity,
    k: int = 15,
    budget: float = 0.04,
    alpha: float = 0.0,
    eps: float | None = None,
    normalize: bool = False,
    seed: str = "s",
    mode: str = "two_sample",
    labels: str = "walk",
    gathered: tuple[DataFrame, DataFrame] | None = None,
) -> DataFrame:
    """One row ``estimate, m_a, m_b, n, r, t1, t2, t, passes, words, evaluations``; similarities are evaluated on demand.

    ``passes`` counts the scans of this run over the nodes (at most k + 4), ``words`` what it stored, and
    ``evaluations`` the similarities it asked for, at most two for each walk, scan and node.

    Nodes meet only samples: the anchors, the first and second sample, the residual sample and the
    walks' probes.  With ``eps`` the sizes follow theory (at ``eps / 8``) and ``normalize`` gives the
    form that does not fall below the true count; otherwise ``budget`` is the stored share of
    nodes.  ``labels='rounds'`` settles the whole graph instead of walking.  ``gathered`` are the anchors and both first
    samples where a live pass has drawn them already.
    """
    spark = nodes.sparkSession
    counted = CosineGraph(nodes, similarity) if labels == "rounds" and isinstance(similarity, Cosine) else None
    n = nodes.count()
    sizes = theory_sizes(n, k, alpha, eps / 8) if eps else budget_sizes(n, budget, alpha=alpha)
    trials = trial_table(spark, [(seed, k, budget, sizes)])
    ids = checkpointed(nodes.select("id"))
    ranked = checkpointed(ranked_trials(ids, trials))
    scans, evaluations = 1, 0  # the ranks were one scan

    def met(*some: DataFrame) -> DataFrame:
        """The positive pairs of some nodes with all, by one scan that they share."""
        nonlocal scans, evaluations
        chosen = checkpointed(reduce(DataFrame.unionByName, [x.select("id") for x in some]).distinct())
        scans, evaluations = scans + 1, evaluations + chosen.count() * n
        return _sampled_pairs(nodes, similarity, chosen) if counted is None else counted

    if gathered:
        anchors, firsts = gathered
    else:
        anchors = checkpointed(anchors_of(ranked, trials))
        firsts = checkpointed(bottom_k_trials(ranked, trials, "t1", "s1").unionByName(bottom_k_trials(ranked, trials, "t1", "s1b")))
    first_pairs = met(anchors, firsts)
    al = checkpointed(anchored_pivot(ranked, anchors, first_pairs, trials))
    low = checkpointed(bottom_k_trials(classify_by_sample(al, first_pairs, trials, mode).where(~F.col("is_high")).select("trial", "id", "pivot"), trials, "t2", "s2"))
    centers = checkpointed(sample_centers(al, trials))
    around = met(low, centers)
    a = estimate_anchored_part(al, counted or checkpointed(first_pairs.unionByName(around).distinct()), trials, mode)
    if counted is None:
        gamma = checkpointed(neighbourhoods(centers, around))
        members = checkpointed(gamma.select("trial", F.col("member").alias("id")).distinct())
        held = gamma.agg(F.count("*").alias("gamma"))
    else:
        one = F.lit(0).cast("bigint").alias("pivot")
        met_by = counted.counted(al.select("trial", "id", one), centers.select("trial", "id", one), of="others").agg(F.sum("same").alias("near"))
        held = met_by.crossJoin(centers.agg(F.count("*").alias("own"))).select((F.coalesce("near", F.lit(0)) + F.col("own")).alias("gamma"))
    if counted is not None:
        inner = counted
        walked = budgeted_trials(ids, inner, trials)
    elif labels == "walk":
        walked = checkpointed(walk_pivots(members, ranked, nodes, similarity, k))
        rounds, each = walked.agg(F.coalesce(F.max("scans"), F.lit(0)), F.coalesce(F.sum("scans"), F.lit(0))).first()
        scans, evaluations = scans + rounds, evaluations + 2 * each * n
        inner = checkpointed(around.unionByName(met(members)).distinct())
    else:
        inner = checkpointed(similarity.pairs(nodes))
        walked = budgeted_trials(ids, inner, trials)
    b = estimate_residual_part(al, checkpointed(walked.select("trial", "id", "pivot")), inner, trials)
    out = a.join(b, "trial").crossJoin(held)
    raw = F.col("m_a") + F.col("m_b")
    estimate = (raw + 0.375 * (eps or 0.0) * float(n) ** (1 - alpha)) / (1 - (eps or 0.0) / 8) if normalize else raw
    drawn = Sizes(min(sizes.r, n), min(sizes.t1, n), min(sizes.t2, n), min(sizes.t, n), sizes.cutoff)
    words = F.lit(words_stored(drawn, k)) + F.col("gamma") * (1 + 2 * k)
    return out.select(estimate.alias("estimate"), "m_a", "m_b", F.col("n"), F.lit(drawn.r).cast("bigint").alias("r"), "t1", "t2", "t", F.lit(scans).alias("passes"), words.cast("bigint").alias("words"), F.lit(evaluations).cast("bigint").alias("evaluations"))


def _sampled_pairs(nodes: DataFrame, similarity: Similarity, some: DataFrame) -> DataFrame:
    """Positive pairs with an end in the sample, as ``u, v``."""
    left = nodes.join(some.select("id").distinct(), "id", "left_semi")
    return checkpointed(similarity.pairs_between(left, nodes).select(F.least("id", "near").alias("u"), F.greatest("id", "near").alias("v")).distinct())


def boosted_estimate(ids: DataFrame, pairs: DataFrame, k: int, budget: float, repeats: int = 9, seed: str = "s", mode: str = "two_sample") -> DataFrame:
    """``median_estimate, repeats``: independent repetitions in one plan."""
    n = ids.count()
    trials = trial_table(ids.sparkSession, [(f"{seed}{i}", k, budget, budget_sizes(n, budget)) for i in range(repeats)])
    return estimate_trials(ids, pairs, trials, mode).agg(F.median("estimate").alias("median_estimate"), F.count("*").alias("repeats"))

