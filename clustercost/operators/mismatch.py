"""Mismatches: tests, exact costs by counting, mismatch pairs and degrees.

Joined negatives are never listed: within a cluster of c nodes they are c(c-1)/2 less the positive pairs inside.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..lineage import checkpointed
from .dense import CosineGraph


def is_mismatch(a: Column, b: Column, similar: Column) -> Column:
    """Whether a pair with labels a and b is cut though similar, or joined though not."""
    return F.when(similar, a != b).otherwise(a == b)


def is_anchored_mismatch(a: Column, b: Column, similar: Column) -> Column:
    """The same where labels may be missing: two missing ones give no, one missing gives ``similar``."""
    return F.when(a.isNull() & b.isNull(), F.lit(False)).when(a.isNull() | b.isNull(), similar).otherwise(is_mismatch(a, b, similar))


def labelled_pairs(labels: DataFrame, pairs: DataFrame, *by: str) -> DataFrame:
    """Pairs with both ends' labels ``pu, pv``, per group of ``by``."""
    a = labels.select(*by, F.col("id").alias("u"), F.col("pivot").alias("pu"))
    b = labels.select(*by, F.col("id").alias("v"), F.col("pivot").alias("pv"))
    return pairs.select("u", "v").join(a, "u").join(b, [*by, "v"])


def clustering_cost(labels: DataFrame, pairs: DataFrame, *by: str) -> DataFrame:
    """``n, m, cut_positive, joined_negative, cost`` per group of ``by`` (or one row)."""
    if isinstance(pairs, CosineGraph):
        rows = labels.select(F.col("trial") if by else F.lit(0).alias("trial"), "id", "pivot")
        inside = pairs.counted(rows, rows).groupBy(*by).agg(F.expr("sum(cross + same) DIV 2").alias("m"), F.expr("sum(same) DIV 2").alias("kept"))
    else:
        inside = labelled_pairs(labels, pairs, *by).groupBy(*by).agg(F.count("*").alias("m"), F.count_if(F.col("pu") == F.col("pv")).alias("kept"))
    sizes = labels.groupBy(*by, "pivot").agg(F.count("*").alias("size"))
    joined = sizes.groupBy(*by).agg(F.sum("size").alias("n"), F.expr("CAST(sum(size * (size - 1) DIV 2) AS BIGINT)").alias("together"))
    both = joined.join(inside, list(by), "left") if by else joined.crossJoin(inside)
    m, kept = F.coalesce("m", F.lit(0)), F.coalesce("kept", F.lit(0))
    cut, wrong = m - kept, F.coalesce("together", F.lit(0)) - kept
    return both.select(*by, F.coalesce("n", F.lit(0)).alias("n"), m.alias("m"), cut.alias("cut_positive"), wrong.alias("joined_negative"), (cut + wrong).alias("cost"))


def mismatch_pairs(labels: DataFrame, pairs: DataFrame) -> DataFrame:
    """``u, v, kind`` of all mismatches; joined pairs are listed, so for data of small clusters."""
    cut = labelled_pairs(labels, pairs).where("pu <> pv").select("u", "v", F.lit("cut").alias("kind"))
    a, b = labels.select(F.col("id").alias("u"), "pivot"), labels.select(F.col("id").alias("v"), "pivot")
    joined = a.join(b, "pivot").where("u < v").select("u", "v").join(pairs, ["u", "v"], "left_anti").select("u", "v", F.lit("joined").alias("kind"))
    return cut.unionByName(joined)


def part_costs(labels: DataFrame, parts: DataFrame, pairs: DataFrame) -> DataFrame:
    """``exact_a, exact_b``: mismatches that touch an anchored node, and those between residual ones.

    Clusters are purely of one kind, so joined negatives split by their cluster's kind.
    """
    joined = labels.select("id", "pivot").join(parts.select("id", "part"), "id")
    if isinstance(pairs, CosineGraph):
        joined = checkpointed(joined)
        rows = joined.select(F.lit(0).alias("trial"), "id", "pivot", "part")
        total = lambda d, x: pairs.counted(d, d).agg(F.coalesce(F.expr("sum(cross) DIV 2"), F.lit(0)).alias(f"cut_{x}"), F.coalesce(F.expr("sum(same) DIV 2"), F.lit(0)).alias(f"kept_{x}"))
        counts = total(rows, "all").crossJoin(total(rows.where("part = 'B'"), "b")).withColumns({"cut_a": F.col("cut_all") - F.col("cut_b"), "kept_a": F.col("kept_all") - F.col("kept_b")})
    else:
        a = joined.select(F.col("id").alias("u"), F.col("pivot").alias("pu"), F.col("part").alias("au"))
        b = joined.select(F.col("id").alias("v"), F.col("pivot").alias("pv"), F.col("part").alias("av"))
        ends = pairs.join(a, "u").join(b, "v")
        residual = (F.col("au") == "B") & (F.col("av") == "B")
        counts = ends.agg(
            F.count_if(~residual & (F.col("pu") != F.col("pv"))).alias("cut_a"), F.count_if(residual & (F.col("pu") != F.col("pv"))).alias("cut_b"), F.count_if(~residual & (F.col("pu") == F.col("pv"))).alias("kept_a"), F.count_if(residual & (F.col("pu") == F.col("pv"))).alias("kept_b")
        )
    sizes = joined.groupBy("part", "pivot").agg(F.count("*").alias("c"))
    together = sizes.agg(*[F.coalesce(F.expr(f"CAST(sum(IF(part = '{x}', c * (c - 1) DIV 2, 0)) AS BIGINT)"), F.lit(0)).alias(f"together_{x.lower()}") for x in "AB"])
    return counts.crossJoin(together).select((F.col("cut_a") + F.col("together_a") - F.col("kept_a")).alias("exact_a"), (F.col("cut_b") + F.col("together_b") - F.col("kept_b")).alias("exact_b"))


def mismatch_degree(labels: DataFrame, pairs: DataFrame) -> DataFrame:
    """``id, degree``: mismatches at each node under full labels."""
    return anchored_degree(labels, pairs).withColumnRenamed("degree_a", "degree")


def anchored_degree(labels: DataFrame, pairs: DataFrame, of: DataFrame | None = None) -> DataFrame:
    """``id, degree_a``: mismatches in the anchored part at each node (of ``of``), under nullable labels.

    Similar neighbours with another or a missing label count, and the rest of one's cluster less
    the similar ones in it.
    """
    from .graph import both_ways

    some = labels if of is None else labels.join(of.select("id"), "id", "left_semi")
    if isinstance(pairs, CosineGraph):
        row = lambda d: d.select(F.lit(0).alias("trial"), "id", "pivot")
        counts = pairs.counted(row(some), row(labels)).drop("trial")
    else:
        ways = both_ways(pairs).join(some.select("id", F.col("pivot").alias("pu")), "id").join(labels.select(F.col("id").alias("near"), F.col("pivot").alias("pv")), "near")
        counts = ways.groupBy("id").agg(F.count_if(is_anchored_mismatch(F.col("pu"), F.col("pv"), F.lit(True))).alias("cross"), F.count_if(F.col("pu") == F.col("pv")).alias("same"))
    sizes = labels.where("pivot IS NOT NULL").groupBy("pivot").agg(F.count("*").alias("c"))
    rows = some.select("id", "pivot").join(counts, "id", "left").join(sizes, "pivot", "left")
    return rows.select("id", (F.coalesce("cross", F.lit(0)) + F.when(F.col("pivot").isNotNull(), F.col("c") - 1 - F.coalesce("same", F.lit(0))).otherwise(0)).cast("bigint").alias("degree_a"))
