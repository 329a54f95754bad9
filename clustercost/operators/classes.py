"""Shared-item graphs by classes of nodes with equal item sets: no pair of nodes is listed.

Nodes with one set are similar to each other and to the same other nodes, so the pairs of classes and the membership
hold every pair.  Each class is named by its first node in rank order.  Where no two sets are equal, classes are nodes
and their pairs are the graph's own.

*Exact pivots*: the members of a class come after its first node, so whoever closes the first closes them too, and
if the first is a pivot, no other pivot is near to the class; all members thus have the first's pivot.
*Budgeted pivots*: a lookup within budget k sees at most the first k nodes of its own and the neighbouring classes.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..lineage import checkpointed
from .graph import both_ways
from .pivot import first_k, pivot_cluster, settle
from .ranking import rank_key
from .similarity import SharedItems, meet


@dataclass
class Classes:
    """``ids(id)`` of all nodes, ``members(id, key, class)`` of those that can be similar to others, ``pairs(u, v)`` of classes."""

    ids: DataFrame
    members: DataFrame
    pairs: DataFrame

    def sizes(self) -> DataFrame:
        return self.members.groupBy("class").agg(F.count("*").alias("size"))


def classes_of(nodes: DataFrame, similarity: SharedItems, seed: str = "s", first: Column | None = None) -> Classes:
    """Classes of ``nodes`` with the items that ``similarity`` compares; ``first`` names a class by another order than the seed's."""
    items = F.array_sort(F.array_distinct(F.array_compact(similarity.column)))
    sets = nodes.select("id", rank_key(seed).alias("key"), items.alias("items")).where(F.size("items") >= similarity.least)
    order = F.struct("key", "id") if first is None else first
    named = checkpointed(sets.groupBy("items").agg(F.min_by("id", order).alias("class")))
    members = checkpointed(sets.join(named, "items").select("id", "key", "class"))
    pairs = SharedItems("items", similarity.least).pairs(named.select(F.col("class").alias("id"), "items"))
    return Classes(nodes.select("id"), members, checkpointed(pairs))


def node_pairs(found: Classes, members: DataFrame | None = None, *carried: str) -> DataFrame:
    """All pairs ``u, v`` of nodes, and ``members``' columns ``carried`` as ``<name>_u, <name>_v``: streamed, without a shuffle of pairs.

    Only members cross a shuffle, once for each neighbouring class.
    """
    members = found.members if members is None else members
    own = found.members.select(F.col("class").alias("a"), F.col("class").alias("b")).distinct()
    sides = checkpointed(found.pairs.select(F.col("u").alias("a"), F.col("v").alias("b")).unionByName(own))
    left = members.select(F.col("class").alias("a"), "id", *[F.col(c).alias(f"{c}_l") for c in carried]).join(sides, "a")
    right = members.select(F.col("class").alias("b"), F.col("id").alias("near"), *[F.col(c).alias(f"{c}_r") for c in carried]).join(sides, "b")
    met = meet(left, right, ["a", "b"]).where("a <> b OR id < near")
    before = F.col("id") < F.col("near")
    ends = [x for c in carried for x in (F.when(before, F.col(f"{c}_l")).otherwise(F.col(f"{c}_r")).alias(f"{c}_u"), F.when(before, F.col(f"{c}_r")).otherwise(F.col(f"{c}_l")).alias(f"{c}_v"))]
    return met.select(F.least("id", "near").alias("u"), F.greatest("id", "near").alias("v"), *ends)


def class_labels(found: Classes, seed: str = "s") -> DataFrame:
    """``class, pivot``: exact pivots of the classes' first nodes."""
    firsts = found.members.select(F.col("class").alias("id")).distinct()
    return pivot_cluster(firsts, found.pairs, seed).select(F.col("id").alias("class"), "pivot")


def pivot_labels(found: Classes, seed: str = "s") -> DataFrame:
    """``id, pivot`` of all nodes; the classes are those of the seed's order."""
    labelled = found.members.join(class_labels(found, seed), "class").select("id", "pivot")
    return found.ids.join(labelled, "id", "left").select("id", F.coalesce("pivot", "id").alias("pivot"))


def pivot_cost(found: Classes, seed: str = "s") -> DataFrame:
    """``n, m, cut_positive, joined_negative, cost`` from the sizes of classes: all members of a class share one pivot."""
    labels = checkpointed(class_labels(found, seed).join(found.sizes(), "class"))
    square = "CAST(coalesce(sum({0} * ({0} - 1) DIV 2), 0) AS BIGINT)"
    whole = labels.agg(F.expr(square.format("size")).alias("inside"), F.coalesce(F.sum("size"), F.lit(0)).alias("held"))
    together = labels.groupBy("pivot").agg(F.sum("size").alias("c")).agg(F.expr(square.format("c")).alias("together"))
    a, b = (labels.select(F.col("class").alias(x), F.col("size").alias(f"s{x}"), F.col("pivot").alias(f"p{x}")) for x in "uv")
    met = found.pairs.join(a, "u").join(b, "v").withColumn("w", F.col("su") * F.col("sv"))
    across = met.agg(F.coalesce(F.sum("w"), F.lit(0)).alias("across"), F.coalesce(F.sum(F.when(F.col("pu") == F.col("pv"), F.col("w"))), F.lit(0)).alias("same"))
    row = found.ids.agg(F.count("*").alias("n")).crossJoin(whole).crossJoin(together).crossJoin(across)
    m, kept = F.col("inside") + F.col("across"), F.col("inside") + F.col("same")
    return row.select("n", m.alias("m"), (m - kept).alias("cut_positive"), (F.col("together") - kept).alias("joined_negative"), (m + F.col("together") - 2 * kept).alias("cost"))


def budgeted_labels(found: Classes, k: int, seed: str = "s") -> DataFrame:
    """``id, pivot, calls, timed_out``: each node meets the first k nodes of its own and the neighbouring classes only."""
    place = F.row_number().over(Window.partitionBy("class").orderBy("key", "id"))
    tops = found.members.withColumn("place", place).where(F.col("place") <= k).select(F.col("class").alias("other"), F.col("id").alias("near"), F.col("key").alias("near_key"))
    own = found.members.select("class", F.col("class").alias("other")).distinct()
    around = both_ways(found.pairs).select(F.col("id").alias("class"), F.col("near").alias("other")).unionByName(own)
    lists = first_k(around.join(tops, "other").select(F.lit(0).alias("trial"), F.col("class").alias("id"), "near", "near_key"), k)
    met = found.members.join(lists.select(F.col("id").alias("class"), "near", "near_key"), "class").where(F.struct("near_key", "near") < F.struct("key", "id"))
    ranked = found.ids.select(F.lit(0).alias("trial"), "id", rank_key(seed).alias("key"))
    return settle(ranked, met.select(F.lit(0).alias("trial"), "id", "near", "near_key"), k).select("id", "pivot", "calls", "timed_out")
