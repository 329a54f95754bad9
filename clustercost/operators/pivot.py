"""Pivot clustering and its budgeted form over ``ranked(trial, id, key)`` and ``earlier``.

``earlier(trial, id, near, near_key)`` holds each node's earlier-ranked positive neighbours.
A node's *calls* are one more than the calls of its earlier neighbours in order, up to and
including the first that is a pivot; the budgeted label is the pivot's label if calls stay
within ``k``, else the node itself.

Two physical forms give the same rows.  *Rounds* settle the whole graph by joins, for any
size.  *Local* hands each trial to one pandas task and is chosen only when the counted rows
are few.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..lineage import checkpointed
from .graph import both_ways

LOCAL_ROWS = 2_000_000
LABELS = "trial int, id bigint, pivot bigint, calls int, timed_out boolean"


def earlier_neighbours(ranked: DataFrame, pairs: DataFrame) -> DataFrame:
    """Orient each pair in each trial: ``trial, id, near, near_key`` with near ranked before id."""
    a = ranked.select("trial", F.col("id").alias("u"), F.col("key").alias("ku"))
    b = ranked.select("trial", F.col("id").alias("v"), F.col("key").alias("kv"))
    both = pairs.select("u", "v").join(a, "u").join(b, ["trial", "v"])
    first = F.struct("ku", "u") < F.struct("kv", "v")
    return both.select("trial", F.when(first, F.col("v")).otherwise(F.col("u")).alias("id"), F.when(first, F.col("u")).otherwise(F.col("v")).alias("near"), F.when(first, F.col("ku")).otherwise(F.col("kv")).alias("near_key"))


def settle(ranked: DataFrame, earlier: DataFrame, k: int | None = None, strategy: str = "auto", local_rows: int = LOCAL_ROWS) -> DataFrame:
    """``trial, id, pivot``: exact pivots; with ``k`` also ``calls, timed_out``: budgeted, calls saturated at k + 1.

    ``strategy`` is ``rounds``, ``local``, or ``auto``, which takes the local form up to
    ``local_rows`` counted rows; all give the same rows.
    """
    if strategy == "auto":
        ranked, earlier = checkpointed(ranked), checkpointed(earlier)
        strategy = "local" if earlier.count() + ranked.count() <= local_rows else "rounds"
    if strategy == "local":
        found = _local(ranked, earlier, k)
        return found.select("trial", "id", "pivot") if k is None else found
    return _rounds_exact(ranked, earlier) if k is None else _rounds_budgeted(ranked, earlier, k)


def _local(ranked: DataFrame, earlier: DataFrame, k: int | None) -> DataFrame:
    def run(key: tuple, nodes: pd.DataFrame, near: pd.DataFrame) -> pd.DataFrame:
        nodes = nodes.sort_values(["key", "id"], ignore_index=True)
        place = {x: i for i, x in enumerate(nodes["id"])}
        n = len(nodes)
        lists: list[list[int]] = [[] for _ in range(n)]
        for x, y in zip(near["id"], near["near"], strict=True):
            if x in place and y in place:
                lists[place[x]].append(place[y])
        pivot, calls = np.arange(n), np.ones(n, np.int64)
        cap = 2**31 - 1 if k is None else k + 1
        for i in range(n):
            total = 1
            for j in sorted(lists[i]):
                total += int(calls[j])
                if pivot[j] == j:
                    pivot[i] = j
                    break
            calls[i] = min(total, cap)
        late = np.zeros(n, bool) if k is None else calls > k
        ids = nodes["id"].to_numpy()
        return pd.DataFrame({"trial": np.full(n, key[0], np.int32), "id": ids, "pivot": np.where(late, ids, ids[pivot]), "calls": calls.astype(np.int32), "timed_out": late})

    near = earlier.select(*[F.col(c).alias(c) for c in ("trial", "id", "near")])  # columns of its own, should both share a source
    return ranked.select("trial", "id", "key").groupBy("trial").cogroup(near.groupBy("trial")).applyInPandas(run, LABELS)


def _rounds_exact(ranked: DataFrame, earlier: DataFrame, most_rounds: int = 200) -> DataFrame:
    """Open nodes without an open earlier neighbour become pivots and close their neighbours.

    Labels are taken only after the fixpoint: a node closed by one pivot may have an earlier
    one that settles in a later round.
    """
    earlier = checkpointed(earlier)
    opened, pivots = checkpointed(ranked.select("trial", "id")), None
    for _ in range(most_rounds):
        if opened.isEmpty():
            break
        near_open = earlier.join(opened.withColumnRenamed("id", "near"), ["trial", "near"], "left_semi").select("trial", "id")
        fresh = checkpointed(opened.join(near_open, ["trial", "id"], "left_anti"))
        pivots = fresh if pivots is None else pivots.unionByName(fresh)
        closed = earlier.join(fresh.withColumnRenamed("id", "near"), ["trial", "near"], "left_semi").select("trial", "id")
        opened = checkpointed(opened.join(fresh, ["trial", "id"], "left_anti").join(closed, ["trial", "id"], "left_anti"))
    else:
        raise RuntimeError("nodes are still open after the allowed rounds")
    if pivots is None:
        pivots = opened
    first = earlier.join(pivots.withColumnRenamed("id", "near"), ["trial", "near"]).groupBy("trial", "id").agg(F.min_by("near", F.struct("near_key", "near")).alias("first"))
    own = pivots.withColumn("own", F.lit(True))
    labelled = ranked.select("trial", "id").join(own, ["trial", "id"], "left").join(first, ["trial", "id"], "left")
    return labelled.select("trial", "id", F.when(F.col("own"), F.col("id")).otherwise(F.col("first")).alias("pivot"))


def first_k(earlier: DataFrame, k: int) -> DataFrame:
    """The first k earlier neighbours of each node: no lookup within the budget sees more."""
    from pyspark.sql import Window

    return earlier.withColumn("place", F.row_number().over(Window.partitionBy("trial", "id").orderBy("near_key", "near"))).where(F.col("place") <= k)


def _rounds_budgeted(ranked: DataFrame, earlier: DataFrame, k: int) -> DataFrame:
    """At most k rounds: each folds the known neighbours in order and stops at the first unsettled one.

    A node settles when its fold meets a pivot, exceeds the budget, or ends; whoever is still
    open after k rounds has used the budget up.
    """
    near = checkpointed(first_k(earlier, k).join(ranked.select("trial", "id"), ["trial", "id"], "left_semi"))
    settled = checkpointed(ranked.join(near, ["trial", "id"], "left_anti").select("trial", "id", F.col("id").alias("pivot"), F.lit(1).alias("calls")))
    opened = checkpointed(near.select("trial", "id").distinct())
    zero = F.struct(F.lit(1).alias("calls"), F.lit("more").alias("state"), F.lit(None).cast("bigint").alias("pivot"))

    def step(state, x):
        total = F.least(state["calls"] + x["calls"], F.lit(k + 1))
        seen = F.when(x["calls"].isNull(), F.struct(state["calls"].alias("calls"), F.lit("wait").alias("state"), state["pivot"].alias("pivot"))).otherwise(
            F.struct(total.alias("calls"), F.when(x["pivot"] == x["near"], F.lit("pivot")).when(total > k, F.lit("late")).otherwise(F.lit("more")).alias("state"), F.when(x["pivot"] == x["near"], x["near"]).alias("pivot"))
        )
        return F.when(state["state"] == "more", seen).otherwise(state)

    for _ in range(k):
        if opened.isEmpty():
            break
        # a settled neighbour that timed out is no pivot: its label is itself only by truncation
        known = settled.select("trial", F.col("id").alias("near"), F.when(F.col("calls") > k, F.lit(None)).otherwise(F.col("pivot")).alias("pivot"), "calls")
        rows = near.join(opened, ["trial", "id"], "left_semi").join(known, ["trial", "near"], "left")
        lists = rows.groupBy("trial", "id").agg(F.sort_array(F.collect_list(F.struct("place", "near", "pivot", "calls"))).alias("list"))
        folded = lists.select("trial", "id", F.aggregate("list", zero, step).alias("f")).where(F.col("f.state") != "wait")
        fresh = checkpointed(folded.select("trial", "id", F.when(F.col("f.state") == "pivot", F.col("f.pivot")).otherwise(F.col("id")).alias("pivot"), F.col("f.calls").alias("calls")))
        settled = checkpointed(settled.unionByName(fresh))
        opened = checkpointed(opened.join(fresh, ["trial", "id"], "left_anti"))
    late = opened.select("trial", "id", F.col("id").alias("pivot"), F.lit(k + 1).alias("calls"))
    done = settled.unionByName(late)
    over = F.col("calls") > k
    return done.select(F.col("trial").cast("int").alias("trial"), "id", F.when(over, F.col("id")).otherwise(F.col("pivot")).alias("pivot"), F.col("calls").cast("int").alias("calls"), over.alias("timed_out"))


def within_budget(labels: DataFrame, k) -> DataFrame:
    """Budgeted labels from exact pivots and calls; ``k`` is a number or a column name."""
    k = F.lit(k) if isinstance(k, int) else F.col(k)
    late = F.col("calls") > k
    return labels.withColumn("timed_out", late).withColumn("pivot", F.when(late, F.col("id")).otherwise(F.col("pivot"))).withColumn("calls", F.least(F.col("calls"), (k + 1).cast("int")))


def _single(nodes: DataFrame, seed: str) -> DataFrame:
    from .ranking import rank_key

    return nodes.select(F.lit(0).alias("trial"), "id", rank_key(seed).alias("key"))


def pivot_cluster(nodes: DataFrame, pairs: DataFrame, seed: str = "s", form: str = "auto") -> DataFrame:
    """``id, pivot``; ``form`` is ``rounds``, ``local`` or, for small graphs on the driver, ``recursive``."""
    ranked = _single(nodes, seed)
    earlier = earlier_neighbours(ranked, pairs)
    if form == "recursive":
        return _recursive(ranked, earlier)
    return settle(ranked, earlier, None, form).select("id", "pivot")


def budgeted_pivot(nodes: DataFrame, pairs: DataFrame, k: int, seed: str = "s", strategy: str = "auto") -> DataFrame:
    """``id, pivot, calls, timed_out`` with calls saturated at k + 1."""
    ranked = _single(nodes, seed)
    return settle(ranked, earlier_neighbours(ranked, pairs), k, strategy).select("id", "pivot", "calls", "timed_out")


def _recursive(ranked: DataFrame, earlier: DataFrame) -> DataFrame:
    """The recursive definition, on the driver: for tests on small graphs only."""
    keys = {r["id"]: (r["key"], r["id"]) for r in ranked.collect()}
    near: dict[int, list[int]] = {x: [] for x in keys}
    for r in earlier.collect():
        near[r["id"]].append(r["near"])
    known: dict[int, int] = {}

    def lookup(x: int) -> int:
        if x not in known:
            known[x] = next((y for y in sorted(near[x], key=keys.get) if lookup(y) == y), x)
        return known[x]

    for x in sorted(keys, key=keys.get):
        lookup(x)
    return ranked.sparkSession.createDataFrame(list(known.items()), "id bigint, pivot bigint")


def neighbours_of(pairs: DataFrame, some: DataFrame) -> DataFrame:
    """``trial, id, near`` for the nodes of ``some(trial, id)``."""
    return some.select("trial", "id").join(both_ways(pairs), "id")
