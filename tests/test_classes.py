"""Shared-item graphs by classes of equal sets against the pair-by-pair forms."""

import random

import pytest
from pyspark.sql import functions as F

from clustercost.functions.registered import register_all
from clustercost.operators import classes, graph, mismatch, pivot
from clustercost.operators.similarity import SharedItems


@pytest.fixture(scope="module", params=[1, 2])
def made(spark, request):
    """Copies of few sets, a lone set, an empty one, nulls in and for a set; the form by pairs beside the classes."""
    rng = random.Random(request.param)
    kinds = [rng.sample("abcdefghij", rng.randrange(1, 4)) for _ in range(9)]
    rows = [(i, rng.sample(s := rng.choice(kinds), len(s))) for i in range(70)] + [(70, ["z"]), (71, []), (72, None), (73, ["a", None, "a"])]
    nodes = spark.createDataFrame(rows, "id bigint, items array<string>")
    similarity = SharedItems("items", request.param)
    return nodes.select("id"), similarity.pairs(nodes).checkpoint() if spark.sparkContext._jsc.sc().getCheckpointDir().isDefined() else similarity.pairs(nodes).cache(), classes.classes_of(nodes, similarity)


def rows(df, *columns):
    return sorted(tuple(r) for r in df.select(*(columns or df.columns)).collect())


def test_pairs_stay_between_classes(made):
    _, pairs, found = made
    assert rows(classes.node_pairs(found)) == rows(pairs)
    assert found.pairs.count() <= 9 * 8 // 2 + 9 < pairs.count()
    carried = classes.node_pairs(found, found.members, "key").where((F.md5(F.concat(F.lit("s:"), "u")) != F.col("key_u")) | (F.md5(F.concat(F.lit("s:"), "v")) != F.col("key_v")))
    assert carried.isEmpty()


def test_labels_and_costs_by_classes(made):
    ids, pairs, found = made
    labels = pivot.pivot_cluster(ids, pairs)
    assert rows(classes.pivot_labels(found)) == rows(labels)
    assert rows(classes.pivot_cost(found)) == rows(mismatch.clustering_cost(labels, pairs))


@pytest.mark.parametrize("k", [1, 2, 5, 30])
def test_budgeted_labels_by_classes(made, k):
    ids, pairs, found = made
    assert rows(classes.budgeted_labels(found, k), "id", "pivot", "calls", "timed_out") == rows(pivot.budgeted_pivot(ids, pairs, k), "id", "pivot", "calls", "timed_out")


def test_no_node_is_similar(spark):
    found = classes.classes_of(spark.createDataFrame([(1, []), (2, None)], "id bigint, items array<string>"), SharedItems("items"))
    assert rows(classes.pivot_labels(found)) == [(1, 1), (2, 2)] and rows(classes.pivot_cost(found)) == [(2, 0, 0, 0, 0)] and classes.node_pairs(found).isEmpty()


def test_table_function_weighs_classes(spark, made):
    ids, pairs, found = made
    register_all(spark)
    near = graph.both_ways(found.pairs).groupBy("id").agg(F.collect_list("near").alias("near"))
    alone = ids.join(found.members.select("id"), "id", "left_anti").withColumn("size", F.lit(1).cast("bigint"))
    table = found.sizes().withColumnRenamed("class", "id").unionByName(alone).withColumn("key", F.md5(F.concat(F.lit("s:"), "id"))).join(near, "id", "left")
    got = spark.sql("SELECT * FROM estimate_clusters(TABLE(SELECT id, key, near, size FROM {rows}) WITH SINGLE PARTITION)", rows=table)
    assert rows(got) == rows(mismatch.clustering_cost(pivot.pivot_cluster(ids, pairs), pairs), "n", "cost")
