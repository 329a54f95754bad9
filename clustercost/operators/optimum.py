"""The optimum of tiny graphs by enumeration, and a lower bound for any graph."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..lineage import checkpointed
from .graph import bad_triangles, components

MOST_NODES = 10


def partitions(n: int) -> Iterator[list[int]]:
    """All set partitions of n things, as block numbers that first appear in order."""

    def grow(prefix: list[int], used: int) -> Iterator[list[int]]:
        if len(prefix) == n:
            yield prefix
            return
        for block in range(used + 1):
            yield from grow([*prefix, block], max(used, block + 1))

    yield from grow([], 0)


def optimum_of(n: int, edges: set[tuple[int, int]]) -> int:
    """Least mismatches over all partitions of ``0..n-1``; ``edges`` has pairs i < j."""
    if n == 0:
        return 0
    best = len(edges)
    for blocks in partitions(n):
        cost = sum((blocks[i] == blocks[j]) != ((i, j) in edges) for j in range(n) for i in range(j))
        best = min(best, cost)
    return best


def brute_force_optimum(ids: DataFrame, pairs: DataFrame, most: int = MOST_NODES) -> DataFrame:
    """One row ``opt``: the cost is additive over connected components, each enumerated in its own group."""
    labels = components(ids, pairs)

    def solve(rows: pd.DataFrame) -> pd.DataFrame:
        nodes = sorted({int(x) for x in rows["u"]} | {int(x) for x in rows["v"]})
        if len(nodes) > most:
            raise ValueError(f"a component has {len(nodes)} nodes; enumeration stops at {most}")
        place = {x: i for i, x in enumerate(nodes)}
        edges = {tuple(sorted((place[int(a)], place[int(b)]))) for a, b in zip(rows["u"], rows["v"], strict=True)}
        return pd.DataFrame({"opt": [optimum_of(len(nodes), edges)]})

    inside = pairs.join(labels.select(F.col("id").alias("u"), "component"), "u")
    return inside.groupBy("component").applyInPandas(solve, "opt bigint").agg(F.coalesce(F.sum("opt"), F.lit(0)).alias("opt"))


def bad_triangle_bound(pairs: DataFrame, seed: str = "s", most_rounds: int = 100) -> DataFrame:
    """One row ``packed``: a greedy packing of pair-disjoint triangles with one negative pair; each costs any clustering 1.

    Rounds keep the triangles that come first, by hash, on all their three pairs, and drop
    those that meet them.
    """
    key = F.md5(F.concat_ws(":", F.lit(seed), "center", "a", "b"))
    left = checkpointed(bad_triangles(pairs).withColumn("key", key))
    packed = 0
    for _ in range(most_rounds):
        if left.isEmpty():
            break
        sides = lambda d: d.select("key", F.explode(F.array(*[F.struct(F.least(x, y).alias("u"), F.greatest(x, y).alias("v")) for x, y in (("center", "a"), ("center", "b"), ("a", "b"))])).alias("p"))
        flat = sides(left)
        first = flat.groupBy("p").agg(F.min("key").alias("key"))
        kept = checkpointed(flat.join(first, ["p", "key"]).groupBy("key").agg(F.count("*").alias("n")).where("n = 3").select("key"))
        packed += kept.count()
        taken = flat.join(kept, "key", "left_semi").select("p").distinct()
        hurt = flat.join(taken, "p", "left_semi").select("key").distinct()
        left = checkpointed(left.join(hurt, "key", "left_anti"))
    return pairs.sparkSession.createDataFrame([(packed,)], "packed bigint")
