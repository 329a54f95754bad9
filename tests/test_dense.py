"""Pivots of a cosine graph in batches against the form by pairs."""

import numpy as np
import pytest

from clustercost import catalog
from clustercost.operators import dense, estimator, graph, lookup, mismatch, pivot, ranking
from clustercost.operators.similarity import Cosine
from clustercost.params import Sizes


@pytest.mark.parametrize("theta, batch", [(0.2, 7), (0.7, 16), (0.99, 64)])
def test_pivots_without_pairs(spark, monkeypatch, theta, batch):
    rng = np.random.default_rng(5)
    vectors = [[float(x) for x in v] for v in rng.normal(size=(90, 4))]
    rows = [*enumerate(vectors), (90, vectors[3]), (91, [0.0] * 4), (92, [0.0] * 4), (93, None)]
    nodes = spark.createDataFrame(rows, "id bigint, e array<float>")
    similarity = Cosine("e", theta)
    want = sorted(tuple(r) for r in pivot.pivot_cluster(nodes.select("id"), similarity.pairs(nodes).cache()).collect())
    monkeypatch.setattr(Cosine, "pairs", None)
    assert sorted(tuple(r) for r in dense.cosine_pivots(nodes, similarity, batch=batch).collect()) == want


@pytest.mark.parametrize("name", ["anchored_labels_emb", "naive_degree_emb", "estimate_anchored_emb_two_sample"])
def test_anchored_queries_list_no_pairs(spark, sf, monkeypatch, name):
    monkeypatch.setattr(Cosine, "pairs", None)
    assert catalog.QUERIES[name](spark, sf).count()


@pytest.fixture(scope="module")
def listed(spark):
    """Vectors with copies, zero and null ones; their pairs beside the graph that counts; two trials of one order and one of another."""
    rng = np.random.default_rng(7)
    vectors = [[float(x) for x in v] for v in rng.normal(size=(120, 4))]
    rows = [*enumerate(vectors), (120, vectors[3]), (121, [0.0] * 4), (122, None)]
    nodes = spark.createDataFrame(rows, "id bigint, e array<float>").cache()
    similarity = Cosine("e", 0.4)
    pairs = similarity.pairs(nodes).cache()
    trials = estimator.trial_table(spark, [("s", 5, 0.1, Sizes(20, 9, 9, 9, 2.0)), ("s", 3, 0.1, Sizes(9, 20, 9, 40, 1.0)), ("r", 4, 0.1, Sizes(12, 20, 40, 9, 1.0))])
    return nodes.select("id"), pairs, dense.CosineGraph(nodes, similarity), trials


def rows(df):
    return sorted((tuple(r) for r in df.collect()), key=str)


def test_counts_without_pairs(listed, monkeypatch):
    monkeypatch.setattr(dense, "HELD", 37)
    monkeypatch.setattr(dense, "ROWS", 5)
    ids, pairs, counted, trials = listed
    assert rows(counted.degrees()) == rows(graph.degrees(ids, pairs))
    assert rows(estimator.estimate_trials(ids, counted, trials)) == rows(estimator.estimate_trials(ids, pairs, trials))
    budgeted = estimator.budgeted_trials(ids, pairs, trials).cache()
    assert rows(mismatch.clustering_cost(budgeted, counted, "trial")) == rows(mismatch.clustering_cost(budgeted, pairs, "trial"))
    ranked = ranking.ranked_trials(ids, trials.where("trial = 0"))
    labels = lookup.anchored_pivot(ranked, lookup.anchors_of(ranked, trials), pairs, trials.where("trial = 0")).cache()
    assert rows(mismatch.anchored_degree(labels, counted)) == rows(mismatch.anchored_degree(labels, pairs))
    full = budgeted.where("trial = 0")
    assert rows(mismatch.part_costs(full, labels, counted)) == rows(mismatch.part_costs(full, labels, pairs))


@pytest.mark.parametrize("batch", [7, 50, 500])
def test_first_neighbours_without_pairs(listed, batch):
    ids, pairs, counted, trials = listed
    earlier = pivot.earlier_neighbours(ranking.ranked_trials(ids, trials), pairs)
    want = rows(pivot.first_k(earlier, 6).select("trial", "id", "near", "near_key"))
    counted._first.clear()
    assert rows(counted.earlier(trials, 6, batch)) == want


@pytest.mark.parametrize("name", ["part_sizes_emb", "anchored_degree_emb", "mismatch_parts_emb", "estimate_residual_emb", "center_counts_emb", "estimate_cost_emb", "bound_checks", "unbiased_residual_emb", "prior_pivot_emb", "prior_sparse_dense_emb", "boosted_estimate_emb", "estimate_cost_normalized_emb"])
def test_queries_list_no_pairs(spark, sf, monkeypatch, name):
    monkeypatch.setattr(Cosine, "pairs", None)
    assert catalog.QUERIES[name](spark, sf).count()


@pytest.mark.parametrize("held", [1000, 40])
def test_bad_triangles_without_pairs(spark, monkeypatch, held):
    rng = np.random.default_rng(8)
    vectors = [[float(x) for x in v] for v in rng.normal(size=(90, 4))]
    rows_in = [*((7 * i % 90, v) for i, v in enumerate(vectors)), (90, vectors[3]), (91, [0.0] * 4), (92, None)]
    nodes = spark.createDataFrame(rows_in, "id bigint, e array<float>")
    similarity = Cosine("e", 0.3)
    want = rows(graph.bad_triangles(similarity.pairs(nodes).cache()))
    monkeypatch.setattr(Cosine, "scored_between", None)
    monkeypatch.setattr(dense, "TILE", 7)
    found = dense.dense_bad_triangles(nodes, similarity, held)
    assert rows(found) == want and want
    assert "Exchange hashpartitioning(center" not in found._jdf.queryExecution().toString() and "Join" not in found._jdf.queryExecution().toString()
