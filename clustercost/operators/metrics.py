"""Measures over trial results, and the ledgers of space and scans."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def relative_error(value: Column, pivot_cost: Column) -> Column:
    """``(value - pivot) / pivot``; null where the pivot cost is 0."""
    return (value - pivot_cost) / F.nullif(pivot_cost, F.lit(0))


def summary(trials: DataFrame, value: str, *by: str, digits: int = 6) -> DataFrame:
    """``mean, sd, sd_share`` of a column by group."""
    out = trials.groupBy(*by).agg(F.avg(value).alias("mean"), F.stddev_samp(value).alias("sd"))
    return out.select(*by, F.round("mean", digits).alias("mean"), F.round("sd", digits).alias("sd"), F.round(F.col("sd") / F.nullif(F.abs("mean"), F.lit(0.0)), digits).alias("sd_share"))


def success_rate(inside: Column) -> Column:
    return F.avg(inside.cast("double"))


def space_ledger(k: int, anchors: DataFrame, first: DataFrame, again: DataFrame, second: DataFrame, residual: DataFrame, gamma: DataFrame) -> DataFrame:
    """``stage, nodes, words`` of what an estimate stores, from the samples and neighbourhoods that it drew."""
    stages = (("anchors", anchors, 1), ("first sample", first, 2), ("first sample again", again, 2), ("second sample", second, 2), ("residual sample", residual, 1), ("neighbourhoods", gamma, 1), ("walks", gamma, 2 * k))
    rows = [d.agg(F.count("*").alias("n")).select(F.lit(stage).alias("stage"), (F.lit(0).cast("bigint") if stage == "walks" else F.col("n")).alias("nodes"), (F.col("n") * each).alias("words")) for stage, d, each in stages]
    return reduce(DataFrame.unionByName, rows)


def pass_ledger(nodes: DataFrame, k: int) -> DataFrame:
    """``stage, scan_no, nodes`` of an estimate with the printed k + 4 scans, each of which reads all of ``nodes(id)``."""
    rows = [("anchors", 1), ("first sample", 2), ("classification", 3), ("residual sample", 2), ("second sample degrees", 4), ("neighbourhoods", 3), *[("walk", 4 + i) for i in range(k)], ("outer mismatches", k + 4)]
    stages = nodes.sparkSession.createDataFrame(rows, "stage string, scan_no int")
    return stages.crossJoin(F.broadcast(nodes.agg(F.count("id").alias("nodes"))))


def timed_out_share(labels: DataFrame) -> DataFrame:
    return labels.agg(F.avg(F.col("timed_out").cast("double")).alias("share"))


def calls_histogram(labels: DataFrame) -> DataFrame:
    return labels.groupBy("calls").agg(F.count("*").alias("nodes"))
