"""Fixed-size samples as the smallest hash keys: uniform without replacement, mergeable, order-free."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .ranking import rank_key

LARGE = 10_000_000


def bottom_k(nodes: DataFrame, t: int, salt: str, seed: str, n: int | None = None) -> DataFrame:
    """The ``t`` nodes with the smallest ``md5(salt ':' seed ':' id)``.

    Up to ten million rows this is one top-k per task and a merge.  Beyond, a cut-off first
    keeps a little more than ``t`` of the ``n`` nodes, so that no single task merges them all.
    """
    keyed = nodes.withColumn("key", rank_key(f"{salt}:{seed}" if salt else seed))
    if t > LARGE and n:
        share = min(1.0, (t + 10 * t**0.5) / n)
        keyed = keyed.where(F.substring("key", 1, 8) <= F.lit(f"{int(share * 0xFFFFFFFF):08x}"))
    return keyed.orderBy("key", "id").limit(t)


def first_of_trials(keyed: DataFrame, by: str) -> DataFrame:
    """Rows of ``keyed(trial, wanted, id, ...)`` whose place in the order ``(by, id)`` of their trial is at most ``wanted``.

    Keys are uniform hashes in hex, so their first digits cut the order into even cells.  Cells are counted,
    the few counts tell in which cell a trial's last row falls, and rows are numbered
    within cells only: no task orders a whole trial.
    """
    parts = int(keyed.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    width = max(1, 65536 // max(1, min(parts * 4, 4096)))
    cut = keyed.withColumn("cell", F.floor(F.conv(F.substring(by, 1, 4), 16, 10).cast("int") / width).cast("int"))
    counts = cut.groupBy("trial", "cell").agg(F.count("*").alias("n"), F.first("wanted").alias("wanted"))
    up_to = F.sum("n").over(Window.partitionBy("trial").orderBy("cell"))  # at most 4,096 cells a trial
    over = counts.withColumn("up_to", up_to).where(F.col("up_to") > F.col("wanted"))
    last = over.groupBy("trial").agg(F.min_by(F.struct(F.col("cell").alias("last"), (F.col("wanted") - F.col("up_to") + F.col("n")).alias("need")), "cell").alias("e")).select("trial", "e.*")
    near = cut.join(F.broadcast(last), "trial", "left").where(F.col("last").isNull() | (F.col("cell") <= F.col("last")))  # one row a trial
    place = F.row_number().over(Window.partitionBy("trial", "cell").orderBy(by, "id"))
    kept = near.withColumn("place", place).where(F.col("last").isNull() | (F.col("cell") < F.col("last")) | (F.col("place") <= F.col("need")))
    return kept.drop("cell", "last", "need", "place")


def bottom_k_trials(rows: DataFrame, trials: DataFrame, size: str, salt: str) -> DataFrame:
    """Per trial, the rows of its ``size`` (a column of ``trials``) smallest salted keys."""
    seeded = rows.join(F.broadcast(trials.select("trial", "seed", F.col(size).alias("wanted"))), "trial")
    keyed = seeded.withColumn("sample_key", rank_key(F.concat(F.lit(f"{salt}:"), "seed") if salt else F.col("seed")))
    return first_of_trials(keyed, "sample_key").select(*rows.columns)


def bottom_k_strata(nodes: DataFrame, strata: str, t: int, seed: str) -> DataFrame:
    """The ``t`` smallest keys of each stratum."""
    place = F.row_number().over(Window.partitionBy(strata).orderBy("key", "id"))
    return nodes.withColumn("key", rank_key(seed)).withColumn("place", place).where(F.col("place") <= t).drop("place")
