"""The methods that the estimate is compared with.

Two of them are reconstructions: only their kind and behaviour are published, so the prior
pivot-based and the prior sparse-dense estimators follow their descriptions here, not their code.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..lineage import checkpointed
from .anchored import sample_degrees
from .dense import CosineGraph
from .graph import both_ways, degrees
from .mismatch import is_mismatch
from .ranking import places, rank_key
from .sampling import bottom_k_trials


def drawn_pairs(ranked: DataFrame, trials: DataFrame, salt: str) -> DataFrame:
    """``trial, u, v``: ``q`` distinct pairs of each trial, by hashed pair numbers over rank places.

    Twice as many numbers are hashed as wanted and the first distinct ones kept.
    """
    indexed = places(ranked, "trial").withColumnRenamed("place", "i")
    sizes = ranked.groupBy("trial").agg(F.count("*").alias("n")).join(F.broadcast(trials.select("trial", "seed", "q")), "trial")
    all_pairs = F.expr("n * (n - 1) DIV 2")
    tries = sizes.where("n > 1").withColumn("all", all_pairs).withColumn("q", F.least("q", "all")).select("*", F.explode(F.sequence(F.lit(0), F.col("q") * 2 + 20)).alias("j"))
    number = F.conv(F.substring(F.md5(F.concat(F.lit(salt + ":"), "seed", F.lit(":"), F.col("j").cast("string"))), 1, 12), 16, 10).cast("bigint") % F.col("all")
    first = tries.groupBy("trial", "q", number.alias("p")).agg(F.min("j").alias("j"))
    kept = first.withColumn("o", F.row_number().over(Window.partitionBy("trial").orderBy("j"))).where("o <= q")
    high = F.floor((1 + F.sqrt(1 + 8 * F.col("p").cast("double"))) / 2).cast("bigint")
    fixed = kept.withColumn("h", high).withColumn("h", F.when(F.expr("h * (h - 1) DIV 2 > p"), F.col("h") - 1).when(F.expr("h * (h + 1) DIV 2 <= p"), F.col("h") + 1).otherwise(F.col("h")))
    ends = fixed.select("trial", F.col("h").alias("hi"), F.expr("p - h * (h - 1) DIV 2").alias("lo"))
    a, b = indexed.select("trial", F.col("i").alias("hi"), F.col("id").alias("a")), indexed.select("trial", F.col("i").alias("lo"), F.col("id").alias("b"))
    return ends.join(a, ["trial", "hi"]).join(b, ["trial", "lo"]).select("trial", F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v"))


def pair_estimate(drawn: DataFrame, labels: DataFrame, pairs: DataFrame, n: DataFrame) -> DataFrame:
    """``trial, estimate, q``: the share of mismatches among drawn pairs, scaled to all pairs; ``n`` is ``trial, n``."""
    if isinstance(pairs, CosineGraph):
        drawn = checkpointed(drawn)
        pairs = pairs.tested(drawn)
    a = labels.select("trial", F.col("id").alias("u"), F.col("pivot").alias("pu"))
    b = labels.select("trial", F.col("id").alias("v"), F.col("pivot").alias("pv"))
    tested = drawn.join(a, ["trial", "u"]).join(b, ["trial", "v"]).join(pairs.select("u", "v", F.lit(True).alias("near")), ["u", "v"], "left")
    counts = tested.groupBy("trial").agg(F.count_if(is_mismatch(F.col("pu"), F.col("pv"), F.coalesce("near", F.lit(False)))).alias("hits"), F.count("*").alias("q"))
    return counts.join(n, "trial").select("trial", (F.col("hits") * F.expr("n * (n - 1) DIV 2") / F.col("q")).alias("estimate"), "q")


def pair_sampling(ranked: DataFrame, labels: DataFrame, pairs: DataFrame, trials: DataFrame) -> DataFrame:
    """Test ``q`` sampled pairs under budgeted labels (of at least their ends) and scale back."""
    n = ranked.groupBy("trial").agg(F.count("*").alias("n"))
    return pair_estimate(drawn_pairs(ranked, trials, "pair"), labels, pairs, n)


def prior_pivot(ranked: DataFrame, anchored_labels: DataFrame, pairs: DataFrame, trials: DataFrame) -> DataFrame:
    """Reconstruction of the prior pivot-based estimator: pivots only among the anchors, the rest singletons, cost by sampled pairs.

    ``anchored_labels`` come from an anchored lookup with a budget that never binds.
    """
    labels = anchored_labels.select("trial", "id", F.coalesce("pivot", "id").alias("pivot"))
    n = ranked.groupBy("trial").agg(F.count("*").alias("n"))
    return pair_estimate(drawn_pairs(ranked, trials, "prior"), labels, pairs, n)


def prior_sparse_dense(ids: DataFrame, pairs: DataFrame, trials: DataFrame, eta: float = 0.5, delta: float = 0.001, near_sample: int = 8) -> DataFrame:
    """Reconstruction of the prior sparse-dense estimator; ``trials`` has ``trial, seed, t``.

    A sampled node is sparse if at least an ``eta`` share of its sampled neighbours differ from it in
    ``eta`` of the larger degree or more; it then contributes half its degree, else half its
    neighbours outside its dense group.  Sums scale by n/t, and ``delta * n**2`` is added.
    """
    counted = isinstance(pairs, CosineGraph)
    d = checkpointed(pairs.degrees()) if counted else degrees(ids, pairs)
    rows = ids.select("id").crossJoin(F.broadcast(trials.select("trial")))
    sample = bottom_k_trials(rows, trials, "t", "sd").join(d, "id")
    if counted:
        sample = checkpointed(sample)
        ways, common = pairs.common(sample.select("trial", "id"))
    else:
        ways = both_ways(pairs)
        common = sample.select("trial", "id").join(ways, "id").join(ways.select(F.col("id").alias("near"), F.col("near").alias("third")), "near").join(ways.select("id", F.col("near").alias("third")), ["id", "third"], "left_semi").groupBy("trial", "id", "near").agg(F.count("*").alias("c"))
    near = sample.join(ways, "id").join(d.select(F.col("id").alias("near"), F.col("degree").alias("d2")), "near")
    met = near.join(common, ["trial", "id", "near"], "left").withColumn("differ", F.col("degree") + F.col("d2") - 2 * F.coalesce("c", F.lit(0)) - 2 >= eta * F.greatest("degree", "d2"))
    seeded = met.join(F.broadcast(trials.select("trial", "seed")), "trial").withColumn("o", F.row_number().over(Window.partitionBy("trial", "id").orderBy(rank_key(F.concat(F.lit("sn:"), "seed"), F.col("near")), "near")))
    judged = seeded.groupBy("trial", "id", "degree").agg(F.count_if((F.col("o") <= near_sample) & F.col("differ")).alias("far"), F.count_if(F.col("o") <= near_sample).alias("seen"), F.count_if(F.col("differ")).alias("outside"))
    part = F.when(F.col("far") >= eta * F.col("seen"), F.col("degree")).otherwise(F.col("outside")) / 2
    sums = judged.groupBy("trial").agg(F.sum(part).alias("s"))
    sizes = sample.groupBy("trial").agg(F.count("*").alias("t"))
    n = ids.agg(F.count("*").alias("n"))
    return sizes.join(sums, "trial", "left").crossJoin(F.broadcast(n)).select("trial", (F.coalesce("s", F.lit(0.0)) * F.col("n") / F.col("t") + delta * F.col("n") * F.col("n")).alias("estimate"))


def naive_degree(labels: DataFrame, pairs: DataFrame, trials: DataFrame) -> DataFrame:
    """``trial, estimate``: one uniform sample's exact anchored degrees, scaled and halved; ``trials`` has ``t2``."""
    sample = bottom_k_trials(labels.select("trial", "id", "pivot"), trials, "t2", "nd")
    sums = sample_degrees(labels, sample, pairs).groupBy("trial").agg(F.sum("degree_a").alias("d"), F.count("*").alias("t"))
    n = labels.groupBy("trial").agg(F.count("*").alias("n"))
    return sums.join(n, "trial").select("trial", (F.col("d") * F.col("n") / F.col("t") / 2).alias("estimate"))
