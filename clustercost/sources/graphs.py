"""The graphs on the given tables: nodes with their payload, and the similarity on them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..lineage import checkpointed
from ..operators.similarity import CoOccurrence, Cosine, Jaccard, NearInKey, SameKey, SharedItems, Similarity

GRAPHS = ("emb", "emb3", "page", "page2", "part", "doc", "doc2", "cust", "evt")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shingles(text, size: int = 4):
    """Distinct runs of ``size`` words of the lower-cased text, split at single spaces; a shorter text is one run.

    Shifted copies of the word array are zipped, so the text is split once for each shift and
    not once for each run.
    """
    words = F.split(F.lower(text), " ")
    n = F.size(words)
    shifted = F.arrays_zip(*[F.slice(words, i + 1, F.greatest(n - size + 1, F.lit(1))).alias(f"w{i}") for i in range(size)])
    runs = F.transform(shifted, lambda z: F.concat_ws(" ", *[z[f"w{i}"] for i in range(size)]))
    return F.array_distinct(F.when(n < size, F.array(F.array_join(words, " "))).otherwise(runs))


def hrefs(html):
    return F.array_distinct(F.regexp_extract_all(html, F.lit('href="([^"]*)"'), 1))


def load_graph(spark: SparkSession, sf_dir: str, graph: str) -> tuple[DataFrame, Similarity]:
    """``(nodes, similarity)``; nodes have ``id`` and the payload that the similarity reads."""
    if graph in ("emb", "emb3"):
        nodes = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), "embedding")
        return nodes, Cosine("embedding", 0.2 if graph == "emb" else 0.3)
    if graph in ("page", "page2"):
        nodes = table(spark, sf_dir, "pages").select(F.col("page_id").alias("id"), hrefs(F.col("html")).alias("targets"))
        return nodes, SharedItems("targets", 1 if graph == "page" else 2)
    if graph == "part":
        nodes = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"))
        members = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("group"), F.col("l_partkey").alias("id"))
        return nodes, CoOccurrence(members, 2)
    if graph in ("doc", "doc2"):
        nodes = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), shingles(F.col("text")).alias("shingles"), F.lower("text").alias("lowered"))
        return nodes, Jaccard("shingles", 0.05 if graph == "doc" else 0.2, "lowered")
    if graph == "cust":
        nodes = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("id"), "c_nationkey", "c_mktsegment")
        return nodes, SameKey(("c_nationkey", "c_mktsegment"))
    if graph == "evt":
        nodes = table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("at"))
        return nodes, NearInKey("user_id", "at", 3_600_000_000)
    raise ValueError(f"unknown graph {graph}")


def nodes_and_pairs(spark: SparkSession, sf_dir: str, graph: str) -> tuple[DataFrame, DataFrame]:
    """``(ids, pairs)`` with the pairs settled once, for plans that read them several times."""
    nodes, similarity = load_graph(spark, sf_dir, graph)
    return nodes.select("id"), checkpointed(similarity.pairs(nodes))
