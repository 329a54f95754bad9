"""Budgeted pivots of a few queried nodes by scans of the node stream.

State is one row a query: the path of nodes under evaluation, each with its next candidate.
A scan can only change two elements of a path: the last, and the one before it, whose
candidates resume above the node that was just pushed; what lies before was settled by
earlier scans.  The distinct probes ``(x, above, below)`` of all queries meet the nodes in one
similarity join that keeps the earliest neighbour ranked between the bounds.  One scan
evaluates one node, so after k scans an unanswered query is its own pivot.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..lineage import checkpointed
from .similarity import Similarity

FLOOR = ""  # below every key
ELEMENT = "struct<x:bigint,xk:string,y:bigint,yk:string>"


def probe_set(opened: DataFrame) -> DataFrame:
    """Distinct ``trial, x, above, below`` of the paths' last two elements."""
    last, before = F.element_at("path", -1), F.try_element_at("path", F.lit(-2))
    probes = F.array(
        F.struct(last["x"].alias("x"), F.lit(FLOOR).alias("above"), last["xk"].alias("below")),
        F.struct(before["x"].alias("x"), last["xk"].alias("above"), before["xk"].alias("below")),
    )
    return opened.select("trial", F.explode(probes).alias("p")).where("p.x IS NOT NULL").select("trial", "p.*").distinct()


def scan(probes: DataFrame, ranked: DataFrame, nodes: DataFrame, similarity: Similarity) -> DataFrame:
    """``trial, x, above, best``: the earliest neighbour of each probe between its bounds."""
    near = similarity.pairs_between(nodes.join(probes.select(F.col("x").alias("id")).distinct(), "id", "left_semi"), nodes)
    keyed = near.join(ranked.select("trial", F.col("id").alias("near"), F.col("key").alias("yk")), "near").withColumnRenamed("id", "x")
    between = (F.col("yk") > F.col("above")) & (F.col("yk") < F.col("below"))
    return keyed.join(probes, ["trial", "x"]).where(between).groupBy("trial", "x", "above").agg(F.min(F.struct("yk", F.col("near").alias("y"))).alias("best"))


def _element(x: Column, xk: Column, y: Column | None = None, yk: Column | None = None) -> Column:
    none = lambda kind: F.lit(None).cast(kind)
    return F.struct(x.alias("x"), xk.alias("xk"), (none("bigint") if y is None else y).alias("y"), (none("string") if yk is None else yk).alias("yk")).cast(ELEMENT)


def advance(opened: DataFrame, found: DataFrame, k: int) -> DataFrame:
    """One step of each path after a scan.

    A last element without a candidate is a pivot and claims the element before it: both go, or the
    query is answered when nothing is left; then the last candidate is pushed.
    """
    path, n = F.col("path"), F.size("path")
    last, before = F.element_at("path", -1), F.try_element_at("path", F.lit(-2))
    at_last = found.select("trial", F.col("x").alias("lx"), F.col("above").alias("la"), F.col("best").alias("lb"))
    at_before = found.select("trial", F.col("x").alias("bx"), F.col("above").alias("ba"), F.col("best").alias("bb"))
    keyed = opened.select("trial", "id", "path", last["x"].alias("lx"), F.lit(FLOOR).alias("la"), before["x"].alias("bx"), last["xk"].alias("ba"))
    met = keyed.join(at_last, ["trial", "lx", "la"], "left").join(at_before, ["trial", "bx", "ba"], "left")
    tail = F.array(_element(last["x"], last["xk"], F.col("lb.y"), F.col("lb.yk")))
    two = F.concat(F.array(_element(before["x"], before["xk"], F.col("bb.y"), F.col("bb.yk"))), tail)
    fresh = F.when(n == 1, tail).otherwise(F.concat(F.slice(path, 1, n - 2), two))

    def drop(state: Column, _: Column) -> Column:
        end, size = F.element_at(state["path"], -1), F.size(state["path"])
        stop = state["answer"].isNotNull() | end["y"].isNotNull()
        short = size <= 2
        shorter = F.slice(state["path"], 1, F.greatest(size - 2, F.lit(1)))
        return F.when(stop, state).otherwise(F.struct(F.when(short, state["path"]).otherwise(shorter).alias("path"), F.when(short, end["x"]).alias("answer")))

    zero = F.struct(F.col("fresh").alias("path"), F.lit(None).cast("bigint").alias("answer"))
    walked = met.withColumn("fresh", fresh).withColumn("w", F.aggregate(F.sequence(F.lit(1), F.lit(k)), zero, drop))
    end = F.element_at("w.path", -1)
    body = F.slice("w.path", 1, F.size("w.path") - 1)
    pushed = F.concat(body, F.array(_element(end["x"], end["xk"]), _element(end["y"], end["yk"])))
    return walked.select("trial", "id", F.when(F.col("w.answer").isNull(), pushed).otherwise(F.col("w.path")).alias("path"), F.col("w.answer").alias("pivot"))


def walk_pivots(queries: DataFrame, ranked: DataFrame, nodes: DataFrame, similarity: Similarity, k: int) -> DataFrame:
    """``trial, id, pivot, scans`` for ``queries(trial, id)``; ``nodes`` carries what ``similarity`` reads."""
    start = queries.select("trial", "id").distinct().join(ranked, ["trial", "id"])
    state = checkpointed(start.select("trial", "id", F.array(_element(F.col("id"), F.col("key"))).alias("path"), F.lit(None).cast("bigint").alias("pivot"), F.lit(0).alias("scans")))
    for number in range(1, k + 1):
        opened = state.where("pivot IS NULL")
        probes = checkpointed(probe_set(opened))
        if probes.isEmpty():
            break
        moved = advance(opened, scan(probes, ranked, nodes, similarity), k).withColumn("scans", F.lit(number))
        state = checkpointed(state.where("pivot IS NOT NULL").unionByName(moved))
    return state.select("trial", "id", F.coalesce("pivot", "id").alias("pivot"), "scans")
