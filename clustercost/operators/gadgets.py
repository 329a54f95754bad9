"""Instances on which sublinear estimation is hard: one for single passes, one for relative error only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def index_gadget(bits: DataFrame, b: int) -> DataFrame:
    """``id, kind, x``: sparse points (map from coordinate) of bits ``(i from 1, bit)`` and a queried index.

    With l bits there are 2l points: one on the axis for each bit, and l around place 4b.  If bit b
    is 0 they form a star (optimum l - 1), else no two are similar (optimum 0).
    """
    axis = bits.select(F.col("i").cast("bigint").alias("id"), F.lit("bit").alias("kind"), F.create_map(F.lit(0), (4 * F.col("i") + F.col("bit")).cast("double")).alias("x"))
    l = bits.agg(F.max("i").alias("l"))
    around = bits.crossJoin(F.broadcast(l)).select((F.col("l") + F.col("i")).cast("bigint").alias("id"), F.lit("query").alias("kind"), F.create_map(F.lit(0), F.lit(4.0 * b), F.col("i").cast("int"), F.lit(1.0)).alias("x"))
    return axis.unionByName(around)


def index_optimum(bits: DataFrame, b: int) -> DataFrame:
    """``b, bit, n, true_opt``."""
    return bits.agg(F.lit(b).alias("b"), F.max(F.when(F.col("i") == b, F.col("bit"))).alias("bit"), (2 * F.count("*")).alias("n")).withColumn("true_opt", F.when(F.col("bit") == 1, F.lit(0)).otherwise(F.expr("n DIV 2") - 1).cast("bigint"))


def disjointness_gadget(bits: DataFrame) -> DataFrame:
    """``id, kind, x, y``: four points in the plane for each position ``(i from 1, bx, by)``; a shared 1 joins them to a path of four."""
    point = lambda kind, place, y: F.struct(F.lit(kind).alias("kind"), (F.col("i") * 4 + place).cast("bigint").alias("id"), (F.col("i") * 2).cast("double").alias("x"), y.cast("double").alias("y"))
    points = F.array(point("a", 0, F.col("bx")), point("p", 1, F.col("bx") - 1), point("b", 2, 3 - F.col("by")), point("q", 3, 4 - F.col("by")))
    return bits.select(F.explode(points).alias("e")).select("e.id", "e.kind", "e.x", "e.y")
