"""Similarity models: each is a join plan that yields positive pairs, not a row function.

``pairs(nodes)`` gives ``u, v`` (u < v, distinct) and ``scored`` adds a score where the model has
one; ``pairs_between(left, right)`` gives ``id, near`` for a part of the nodes against others.
A null payload is similar to nothing; a node is always similar to itself (never listed).
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..lineage import checkpointed

#: Rows of one key that a join holds together; keys with more are dealt over several salts.
HOT = 4096


def _ordered(pairs: DataFrame) -> DataFrame:
    return pairs.where(F.col("id") != F.col("near")).select(F.least("id", "near").alias("u"), F.greatest("id", "near").alias("v")).distinct()


def meet(left: DataFrame, right: DataFrame, on: list[str], hot: int | None = None) -> DataFrame:
    """``left`` joined to ``right(near, *on)`` with the right rows of a hot key dealt over salts.

    Each left row of such a key meets every salt, so no pair is lost, and a task holds at most some ``hot`` right rows of
    one key, however many nodes share it.
    """
    hot = hot or HOT
    crowded = right.groupBy(*on).agg(F.count("*").alias("n")).where(F.col("n") > hot).select(*on, F.ceil(F.col("n") / hot).cast("int").alias("salts"))
    salts = F.coalesce("salts", F.lit(1))
    spread = left.join(crowded, on, "left").withColumn("salt", F.explode(F.sequence(F.lit(0), salts - 1))).drop("salts")
    dealt = right.join(crowded, on, "left").withColumn("salt", F.pmod(F.xxhash64("near"), salts).cast("int")).drop("salts")
    return spread.join(dealt, [*on, "salt"]).drop("salt")


class Similarity:
    def pairs_between(self, left: DataFrame, right: DataFrame) -> DataFrame:
        raise NotImplementedError

    def pairs(self, nodes: DataFrame) -> DataFrame:
        return _ordered(self.pairs_between(nodes, nodes))


@dataclass
class EdgeTable(Similarity):
    """Pairs that are given."""

    table: DataFrame

    def pairs(self, nodes: DataFrame) -> DataFrame:
        from .graph import induced, symmetrize

        return induced(symmetrize(self.table, "u", "v"), nodes)

    def pairs_between(self, left: DataFrame, right: DataFrame) -> DataFrame:
        from .graph import both_ways

        return both_ways(self.table).join(left.select("id"), "id", "left_semi").join(right.select(F.col("id").alias("near")), "near", "left_semi").select("id", "near")


def cosine(a: Column, b: Column) -> Column:
    """Cosine of two numeric arrays in double precision; null where either is zero."""
    wide = lambda x: F.transform(x, lambda e: e.cast("double"))
    dot = F.aggregate(F.zip_with(wide(a), wide(b), lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    norm = lambda x: F.sqrt(F.aggregate(wide(x), F.lit(0.0), lambda s, e: s + e * e))
    return dot / F.nullif(norm(a) * norm(b), F.lit(0.0))


@dataclass
class Cosine(Similarity):
    """Cosine above ``theta`` (strictly).

    The left side travels to every task in row blocks and meets the right side's Arrow batches
    as matrix products, so nothing but positive pairs is shuffled.  A left side of more than
    ``broadcast_rows`` rows is dealt by a hash of its ids into blocks of about that size, which are
    taken one after the other, their pairs written and joined to one table; the driver holds
    one block at a time.  The work is |left| x |right| at any size.
    """

    column: str
    theta: float
    block_rows: int = 4096
    broadcast_rows: int = 200_000

    def scored_between(self, left: DataFrame, right: DataFrame, ordered: bool = False) -> DataFrame:
        blocks = -(-left.count() // self.broadcast_rows)
        if blocks < 2:
            return self._scored_block(left, right, ordered)[0]
        parts = []
        for k in range(blocks):
            scored, shared = self._scored_block(left.where(F.pmod(F.xxhash64("id"), F.lit(blocks)) == k), right, ordered)
            parts.append(checkpointed(scored))
            shared.unpersist()
        return reduce(DataFrame.unionByName, parts)

    def _scored_block(self, left: DataFrame, right: DataFrame, ordered: bool) -> tuple[DataFrame, Broadcast]:
        theta, column = self.theta, self.column
        got = left.select("id", column).where(F.col(column).isNotNull()).toArrow()
        ids = got.column("id").to_numpy()
        matrix = _unit(got.column(column).combine_chunks() if isinstance(got.column(column), pa.ChunkedArray) else got.column(column), len(ids))
        shared = left.sparkSession.sparkContext.broadcast((ids, matrix))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            mine, block = shared.value
            for batch in batches:
                batch = batch.filter(batch.column(1).is_valid())
                if not batch.num_rows or not len(mine):
                    continue
                yours, other = batch.column(0).to_numpy(), _unit(batch.column(1), batch.num_rows)
                for a in range(0, len(mine), self.block_rows):
                    score = block[a : a + self.block_rows] @ other.T
                    i, j = np.nonzero(score > theta)
                    keep = mine[a + i] < yours[j] if ordered else mine[a + i] != yours[j]
                    i, j = i[keep], j[keep]
                    yield pa.RecordBatch.from_arrays([pa.array(mine[a + i]), pa.array(yours[j]), pa.array(score[i, j])], names=["id", "near", "score"])

        return right.select("id", column).mapInArrow(run, "id bigint, near bigint, score double"), shared

    def pairs_between(self, left: DataFrame, right: DataFrame) -> DataFrame:
        return self.scored_between(left, right).select("id", "near")

    def scored(self, nodes: DataFrame) -> DataFrame:
        return self.scored_between(nodes, nodes, ordered=True).select(F.col("id").alias("u"), F.col("near").alias("v"), "score")

    def pairs(self, nodes: DataFrame) -> DataFrame:
        return self.scored(nodes).select("u", "v")


def _unit(column: pa.Array, n: int) -> np.ndarray:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    flat = np.asarray(column.flatten().to_numpy(zero_copy_only=False), np.float64)
    if not n:
        return np.zeros((0, 1))
    matrix = flat.reshape(n, -1)
    norm = np.sqrt((matrix * matrix).sum(1, keepdims=True))
    return np.divide(matrix, norm, out=np.zeros_like(matrix), where=norm > 0)


@dataclass
class SharedItems(Similarity):
    """At least ``least`` common members of an array column, by an inverted index."""

    column: str
    least: int = 1

    def pairs_between(self, left: DataFrame, right: DataFrame) -> DataFrame:
        explode = lambda d, n: d.select(F.col("id").alias(n), F.explode(F.array_distinct(self.column)).alias("item"))
        met = meet(explode(left, "id"), explode(right, "near"), ["item"]).where(F.col("id") != F.col("near"))
        return met.groupBy("id", "near").agg(F.count("*").alias("n")).where(F.col("n") >= self.least).select("id", "near")

    def pairs(self, nodes: DataFrame) -> DataFrame:
        explode = nodes.select("id", F.explode(F.array_distinct(self.column)).alias("item"))
        met = meet(explode.select(F.col("id").alias("u"), "item"), explode.select(F.col("id").alias("near"), "item"), ["item"]).where("u < near")
        return met.groupBy("u", F.col("near").alias("v")).agg(F.count("*").alias("n")).where(F.col("n") >= self.least).select("u", "v")


@dataclass
class Jaccard(Similarity):
    """Jaccard of an array column's sets above ``theta`` (strictly).

    Items are ordered by rarity, and only each set's prefix can hold the first common item of a pair
    above ``theta``; frequent items thus drop out of the join without loss.  Null items are no items.
    Where the items are the runs of ``words`` words of a ``text`` column, split at single spaces, they can be hashed from there.
    """

    column: str
    theta: float
    text: str | None = None
    words: int = 4

    def scored(self, nodes: DataFrame) -> DataFrame:
        hashed = F.transform(F.array_compact(self.column), lambda x: F.xxhash64(x))  # equal items, eight bytes each
        sets = checkpointed(nodes.select("id", F.array_distinct(hashed).alias("items")).where(F.size("items") > 0))
        flat = sets.select("id", F.size("items").alias("n"), F.explode("items").alias("item"))
        rarity = flat.groupBy("item").agg(F.count("*").alias("df")).where("df > 1")
        ordered = flat.join(rarity, "item").groupBy("id", "n").agg(F.sort_array(F.collect_list(F.struct("df", "item"))).alias("items"))
        # a pair above theta shares more than theta * n items of either set; unique items cannot be shared
        prefix = F.slice("items", 1, F.greatest(F.lit(0), F.size("items") - F.floor(F.col("n") * self.theta).cast("int")))
        heads = ordered.select("id", "n", F.explode(prefix).alias("e")).select("id", "n", "e.item")
        a, b = heads.select(F.col("id").alias("u"), F.col("n").alias("nu"), "item"), heads.select(F.col("id").alias("near"), F.col("n").alias("nv"), "item")
        candidates = meet(a, b, ["item"]).where("u < near").where(F.least("nu", "nv") > F.greatest("nu", "nv") * self.theta).select("u", F.col("near").alias("v")).distinct()
        left, right = sets.select(F.col("id").alias("u"), F.col("items").alias("x")), sets.select(F.col("id").alias("v"), F.col("items").alias("y"))
        met = candidates.join(left, "u").join(right, "v").withColumn("common", F.size(F.array_intersect("x", "y")))
        score = F.col("common") / (F.size("x") + F.size("y") - F.col("common"))
        return met.select("u", "v", score.alias("score")).where(F.col("score") > self.theta)

    def pairs(self, nodes: DataFrame) -> DataFrame:
        return self.scored(nodes).select("u", "v")

    def pairs_between(self, left: DataFrame, right: DataFrame) -> DataFrame:
        """For a sample on the left: every common item counts, no prefix is needed."""
        explode = lambda d, a, s: d.select(F.col("id").alias(a), F.size(F.array_distinct(F.array_compact(self.column))).alias(s), F.explode(F.array_distinct(F.array_compact(self.column))).alias("item"))
        met = meet(explode(left, "id", "x"), explode(right, "near", "y"), ["item"]).where(F.col("id") != F.col("near"))
        counted = met.groupBy("id", "near", "x", "y").agg(F.count("*").alias("c"))
        return counted.where(F.col("c") / (F.col("x") + F.col("y") - F.col("c")) > self.theta).select("id", "near")


@dataclass
class CoOccurrence(Similarity):
    """Nodes that meet in at least ``least`` distinct groups of a membership table ``(group, id)``."""

    members: DataFrame
    least: int = 1

    def _met(self, left: DataFrame, right: DataFrame) -> DataFrame:
        rows = self.members.select("group", "id").distinct()
        a = rows.join(left.select("id"), "id", "left_semi")
        b = rows.join(right.select("id"), "id", "left_semi").select("group", F.col("id").alias("near"))
        return meet(a, b, ["group"]).where(F.col("id") != F.col("near")).groupBy("id", "near").agg(F.count("*").alias("n")).where(F.col("n") >= self.least)

    def pairs_between(self, left: DataFrame, right: DataFrame) -> DataFrame:
        return self._met(left, right).select("id", "near")

    def pairs(self, nodes: DataFrame) -> DataFrame:
        rows = self.members.select("group", "id").distinct().join(nodes.select("id"), "id", "left_semi")
        met = meet(rows.select("group", F.col("id").alias("u")), rows.select("group", F.col("id").alias("near")), ["group"]).where("u < near")
        return met.groupBy("u", F.col("near").alias("v")).agg(F.count("*").alias("n")).where(F.col("n") >= self.least).select("u", "v")


@dataclass
class SameKey(Similarity):
    """Equal values in all of ``columns`` (null equals nothing); transitive, so its cost is 0 without any pairs."""

    columns: tuple[str, ...]

    def pairs_between(self, left: DataFrame, right: DataFrame) -> DataFrame:
        return meet(left.select("id", *self.columns), right.select(F.col("id").alias("near"), *self.columns), list(self.columns)).where("id <> near").select("id", "near")

    def classes(self, nodes: DataFrame) -> DataFrame:
        return nodes.groupBy(*self.columns).agg(F.count("*").alias("size"))


@dataclass
class NearInKey(Similarity):
    """Same ``key`` and numeric ``value`` at most ``gap`` apart: a range join through buckets of the gap."""

    key: str
    value: str
    gap: float

    def pairs_between(self, left: DataFrame, right: DataFrame) -> DataFrame:
        bucket = F.floor(F.col(self.value) / self.gap)
        a = left.select("id", F.col(self.key).alias("k"), F.col(self.value).alias("x"), F.explode(F.array(bucket - 1, bucket, bucket + 1)).alias("b"))
        b = right.select(F.col("id").alias("near"), F.col(self.key).alias("k"), F.col(self.value).alias("y"), bucket.alias("b"))
        return meet(a, b, ["k", "b"]).where((F.col("id") != F.col("near")) & (F.abs(F.col("x") - F.col("y")) <= self.gap)).select("id", "near")


@dataclass
class L1Ball(Similarity):
    """Points of a few numeric columns at l1 distance at most ``radius``: neighbouring grid cells, then the exact test."""

    columns: tuple[str, ...]
    radius: float = 1.0

    def pairs_between(self, left: DataFrame, right: DataFrame) -> DataFrame:
        cells = [F.floor(F.col(c) / self.radius) for c in self.columns]
        a = left.select("id", *[F.col(c).alias(f"x{i}") for i, c in enumerate(self.columns)], *[c.alias(f"c{i}") for i, c in enumerate(cells)])
        for i in range(len(self.columns)):
            a = a.withColumn(f"c{i}", F.explode(F.array(F.col(f"c{i}") - 1, F.col(f"c{i}"), F.col(f"c{i}") + 1)))
        b = right.select(F.col("id").alias("near"), *[F.col(c).alias(f"y{i}") for i, c in enumerate(self.columns)], *[c.alias(f"c{i}") for i, c in enumerate(cells)])
        distance = sum((F.abs(F.col(f"x{i}") - F.col(f"y{i}")) for i in range(len(self.columns))), F.lit(0.0))
        return a.join(b, [f"c{i}" for i in range(len(self.columns))]).where((F.col("id") != F.col("near")) & (distance <= self.radius)).select("id", "near")


def sparse_l1(a: Column, b: Column) -> Column:
    """l1 distance of two sparse points, as maps from coordinate to value."""
    gaps = F.map_zip_with(a, b, lambda k, x, y: F.abs(F.coalesce(x, F.lit(0.0)) - F.coalesce(y, F.lit(0.0))))
    return F.aggregate(F.map_values(gaps), F.lit(0.0), lambda s, x: s + x)


@dataclass
class SparseL1(Similarity):
    """Sparse points within ``radius``, where coordinate 0 is always present: a grid on that coordinate, then the exact test."""

    column: str
    radius: float = 1.0

    def pairs_between(self, left: DataFrame, right: DataFrame) -> DataFrame:
        base = lambda: F.floor(F.coalesce(F.element_at(self.column, 0), F.lit(0.0)) / self.radius)
        a = left.select("id", F.col(self.column).alias("x"), F.explode(F.array(base() - 1, base(), base() + 1)).alias("c"))
        b = right.select(F.col("id").alias("near"), F.col(self.column).alias("y"), base().alias("c"))
        return a.join(b, "c").where((F.col("id") != F.col("near")) & (sparse_l1(F.col("x"), F.col("y")) <= self.radius)).select("id", "near")


@dataclass
class Custom(Similarity):
    """Any symmetric predicate of two rows: a nested loop, refused beyond ``most_left`` rows on the left."""

    test: Callable[[Callable[[str], Column], Callable[[str], Column]], Column]
    most_left: int = 10_000

    def pairs_between(self, left: DataFrame, right: DataFrame) -> DataFrame:
        if left.limit(self.most_left + 1).count() > self.most_left:
            raise ValueError(f"a custom predicate compares every pair; the left side has over {self.most_left} rows")
        a, b = left.alias("l"), right.alias("r")
        met = b.join(F.broadcast(a), (F.col("l.id") != F.col("r.id")) & self.test(lambda c: F.col(f"l.{c}"), lambda c: F.col(f"r.{c}")))
        return met.select(F.col("l.id").alias("id"), F.col("r.id").alias("near"))
