"""Functions for SQL: scalar expressions, Arrow UDFs, grouped aggregates and table functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, LongType


@F.pandas_udf(DoubleType())
def cosine_sim(a: pd.Series, b: pd.Series) -> pd.Series:
    """Cosine of two arrays, batch by batch; null where either is zero or missing."""

    def one(x, y) -> float | None:
        if x is None or y is None:
            return None
        u, v = np.asarray(x, np.float64), np.asarray(y, np.float64)
        n = np.sqrt(u @ u) * np.sqrt(v @ v)
        return float(u @ v / n) if n else None

    return pd.Series([one(x, y) for x, y in zip(a, b, strict=True)], dtype="float64")


@F.pandas_udf(ArrayType(LongType()))
def bottom_k_agg(ids: pd.Series, keys: pd.Series, k: pd.Series) -> list:
    """The ids of the k smallest (key, id) of a group, in order."""
    rows = sorted(zip(keys, ids, strict=True))[: int(k.iloc[0]) if len(k) else 0]
    return [int(x) for _, x in rows]


def _table_functions():
    """UDTFs, made when asked for: their classes need a running session."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="id bigint, kind string, place double, axis int")
    class IndexGadget:
        """The points of the index gadget for an array of bits and a queried place."""

        def eval(self, bits: list[int], b: int) -> Iterator[tuple]:
            for i, bit in enumerate(bits, 1):
                yield i, "bit", None if bit is None else float(4 * i + bit), None
            for i in range(1, len(bits) + 1):
                yield len(bits) + i, "query", float(4 * b), i

    @udtf(returnType="n bigint, cost bigint")
    class EstimateClusters:
        """Pivot cost of the rows of one partition ``(id, key, near)``: small tables only, the DataFrame API serves large ones.

        With a column ``size`` a row stands for so many nodes that are near to each other and to the same rows, itself the first of them.
        """

        def __init__(self) -> None:
            self.keys: dict[int, str] = {}
            self.near: dict[int, set[int]] = {}
            self.size: dict[int, int] = {}

        def eval(self, row) -> None:
            self.keys[row["id"]] = row["key"]
            self.near[row["id"]] = set(row["near"] or [])
            self.size[row["id"]] = row["size"] if "size" in row else 1

        def terminate(self) -> Iterator[tuple[int, int]]:
            pivot: dict[int, int] = {}
            order = sorted(self.keys, key=lambda x: (self.keys[x], x))
            place = {x: i for i, x in enumerate(order)}
            for x in order:
                pivot[x] = next((y for y in sorted(self.near[x], key=place.__getitem__) if place[y] < place[x] and pivot[y] == y), x)
            sizes: dict[int, int] = {}
            for x, p in pivot.items():
                sizes[p] = sizes.get(p, 0) + self.size[x]
            inside = sum(c * (c - 1) // 2 for c in self.size.values())
            m = inside + sum(self.size[x] * self.size[y] for x, near in self.near.items() for y in near) // 2
            kept = inside + sum(self.size[x] * self.size[y] for x, near in self.near.items() for y in near if pivot[x] == pivot[y]) // 2
            yield sum(self.size.values()), m + sum(c * (c - 1) // 2 for c in sizes.values()) - 2 * kept

    return {"index_gadget": IndexGadget, "estimate_clusters": EstimateClusters}


SCALARS = {
    "cc_rank_key": "(seed STRING, id BIGINT) RETURNS STRING RETURN md5(concat(seed, ':', CAST(id AS STRING)))",
    "cc_is_mismatch": "(a BIGINT, b BIGINT, similar BOOLEAN) RETURNS BOOLEAN RETURN CASE WHEN similar THEN a <> b ELSE a = b END",
    "cc_budget_factor": "(k INT) RETURNS DOUBLE RETURN 9 + 24 / (k - 1)",
}


def register_all(spark: SparkSession) -> None:
    """Register everything for ``spark.sql``; SQL functions are plain expressions that Catalyst inlines."""
    for name, body in SCALARS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    spark.udf.register("cc_cosine_sim", cosine_sim)
    spark.udf.register("cc_bottom_k", bottom_k_agg)
    for name, f in _table_functions().items():
        spark.udtf.register(name, f)
