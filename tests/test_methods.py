"""Worked examples, identities and statistics of the methods."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from clustercost.operators import anchored, estimator, gadgets, graph, lookup, mismatch, optimum, pivot, residual, similarity
from clustercost.operators.ranking import dense_rank_order, rank_key, ranked_trials
from clustercost.operators.sampling import bottom_k
from clustercost.operators.similarity import Cosine, Custom, EdgeTable, Jaccard, L1Ball, NearInKey, SameKey, SharedItems, SparseL1
from clustercost.operators.walker import walk_pivots
from clustercost.params import Sizes, budget_sizes, cutoff_of, passes, theory_sizes
from clustercost.sources.files import validated
from clustercost.sources.graphs import nodes_and_pairs

MICRO = {  # name: (nodes, pairs, optimum)
    "empty": (0, [], 0),
    "one": (1, [], 0),
    "isolated": (4, [], 0),
    "clique": (4, list(itertools.combinations(range(4), 2)), 0),
    "path3": (3, [(0, 1), (1, 2)], 1),
    "path4": (4, [(0, 1), (1, 2), (2, 3)], 1),
    "star": (5, [(0, i) for i in range(1, 5)], 3),
    "cycle4": (4, [(0, 1), (1, 2), (2, 3), (0, 3)], 2),
    "cycle5": (5, [(0, 1), (1, 2), (2, 3), (3, 4), (0, 4)], 3),
    "nearly": (4, [p for p in itertools.combinations(range(4), 2) if p != (0, 1)], 1),
    "bridge": (6, [(0, 1), (0, 2), (1, 2), (3, 4), (3, 5), (4, 5), (2, 3)], 1),
    "path6": (6, [(i, i + 1) for i in range(5)], 2),
}


def frames(spark, n, pairs):
    return spark.createDataFrame([(i,) for i in range(n)], "id bigint"), spark.createDataFrame([tuple(sorted(p)) for p in pairs], "u bigint, v bigint")


def brute_cost(labels, pairs):
    near = {tuple(sorted(p)) for p in pairs}
    return sum((labels[a] == labels[b]) != ((a, b) in near) for a, b in itertools.combinations(sorted(labels), 2))


def random_graph(seed, n=24, p=0.2):
    rng = random.Random(seed)
    return n, [e for e in itertools.combinations(range(n), 2) if rng.random() < p]


@pytest.mark.parametrize("name", MICRO)
def test_optimum_and_pivot_on_small_graphs(spark, name):
    n, pairs, best = MICRO[name]
    assert optimum.optimum_of(n, {tuple(sorted(p)) for p in pairs}) == best
    ids, edges = frames(spark, n, pairs)
    labels = pivot.pivot_cluster(ids, edges)
    got = mismatch.clustering_cost(labels, edges).first()
    assert got["n"] == n and got["m"] == len(pairs)
    assert got["cost"] == brute_cost({r["id"]: r["pivot"] for r in labels.collect()}, pairs) >= best
    assert optimum.brute_force_optimum(ids, edges).first()["opt"] == best
    assert optimum.bad_triangle_bound(edges).first()["packed"] <= best


def in_order(spark, n, pairs):
    """Nodes ranked 0, 1, 2, ..."""
    ids, edges = frames(spark, n, pairs)
    return ids, edges, ids.select(F.lit(0).alias("trial"), "id", F.lpad(F.col("id").cast("string"), 5, "0").alias("key"))


@pytest.mark.parametrize("strategy", ["local", "rounds"])
def test_path_of_six_in_order(spark, strategy):
    ids, edges, ranked = in_order(spark, 6, MICRO["path6"][1])
    earlier = pivot.earlier_neighbours(ranked, edges)
    exact = {r["id"]: r["pivot"] for r in pivot.settle(ranked, earlier, None, strategy).collect()}
    assert exact == {0: 0, 1: 0, 2: 2, 3: 2, 4: 4, 5: 4}
    labels = {r["id"]: (r["pivot"], r["calls"], r["timed_out"]) for r in pivot.settle(ranked, earlier, 5, strategy).collect()}
    assert labels == {0: (0, 1, False), 1: (0, 2, False), 2: (2, 3, False), 3: (2, 4, False), 4: (4, 5, False), 5: (5, 6, True)}
    trials = spark.createDataFrame([(0, "s", 5, 3)], "trial int, seed string, k int, r int")
    parts = lookup.anchored_pivot(ranked, lookup.anchors_of(ranked, trials), edges, trials)
    assert {r["id"]: r["part"] for r in parts.collect()} == {0: "A", 1: "A", 2: "A", 3: "A", 4: "B", 5: "B"}
    full = spark.createDataFrame([(i, p) for i, (p, _, _) in labels.items()], "id bigint, pivot bigint")
    assert tuple(mismatch.part_costs(full, parts, edges).first()) == (2, 1)


@pytest.mark.parametrize("seed", range(3))
def test_forms_agree_and_budget_truncates(spark, seed):
    n, pairs = random_graph(seed)
    ids, edges = frames(spark, n, pairs)
    want = pivot.pivot_cluster(ids, edges, f"t{seed}", "recursive").collect()
    for form in ("local", "rounds"):
        assert sorted(pivot.pivot_cluster(ids, edges, f"t{seed}", form).collect()) == sorted(want)
    exact = {r["id"]: r["pivot"] for r in want}
    ranked = ids.select(F.lit(0).alias("trial"), "id", rank_key(f"t{seed}").alias("key"))
    calls = {r["id"]: r["calls"] for r in pivot.settle(ranked, pivot.earlier_neighbours(ranked, edges), 1_000_000, "local").collect()}
    for k in (1, 2, 3, 5):
        rounds = {r["id"]: (r["pivot"], r["calls"]) for r in pivot.budgeted_pivot(ids, edges, k, f"t{seed}", "rounds").collect()}
        assert rounds == {i: (exact[i] if calls[i] <= k else i, min(calls[i], k + 1)) for i in exact}
        walked = walk_pivots(ranked.select("trial", "id"), ranked, ids, EdgeTable(edges), k)
        assert {r["id"]: r["pivot"] for r in walked.collect()} == {i: p for i, (p, _) in rounds.items()}
    two, three = ({r["id"]: r["pivot"] for r in pivot.budgeted_pivot(ids, edges, k, f"t{seed}").collect()} for k in (2, 3))
    assert two == three  # no pivot takes two calls
    one = pivot.budgeted_pivot(ids, edges, 1, f"t{seed}")
    assert mismatch.clustering_cost(one, edges).first()["cost"] == len(pairs)


def test_special_anchor_sets(spark):
    n, pairs = random_graph(7)
    ids, edges = frames(spark, n, pairs)
    trials = spark.createDataFrame([(0, "s", 5, n), (1, "s", 5, 0), (2, "s", 5, 6)], "trial int, seed string, k int, r int")
    ranked = ranked_trials(ids, trials)
    got = lookup.anchored_pivot(ranked, lookup.anchors_of(ranked, trials), edges, trials).collect()
    whole = {r["id"]: r["pivot"] for r in pivot.budgeted_pivot(ids, edges, 5).collect()}
    assert {r["id"]: r["pivot"] for r in got if r["trial"] == 0} == whole
    assert all(r["pivot"] is None for r in got if r["trial"] == 1)
    part = {r["id"]: r["part"] for r in got if r["trial"] == 2}
    assert all(r["pivot"] == whole[r["id"]] for r in got if r["trial"] == 2 and r["part"] == "A")
    assert all(part[i] == part[p] for i, p in whole.items())  # clusters are purely anchored or residual


def test_whole_samples_give_the_exact_cost(spark):
    n, pairs = random_graph(11, 40, 0.15)
    ids, edges = frames(spark, n, pairs)
    trials = estimator.trial_table(spark, [(f"s{i}", 5, 1.0, Sizes(r, n, n, n, cutoff_of(n, n))) for i, r in enumerate((0, 5, 20, n))])
    got = {r["trial"]: r["estimate"] for r in estimator.estimate_trials(ids, edges, trials).collect()}
    labels = estimator.budgeted_trials(ids, edges, trials)
    want = {r["trial"]: r["cost"] for r in mismatch.clustering_cost(labels, edges, "trial").collect()}
    assert got == pytest.approx(want)


def test_estimates_are_unbiased_and_spread_shrinks(spark, sf):
    ids, pairs = nodes_and_pairs(spark, sf, "emb")
    n, rows = ids.count(), []
    for size in (20, 80):
        rows += [(f"d{i}", 5, 0.1, Sizes(50, size, size, size, cutoff_of(n, size))) for i in range(40)]
    trials = estimator.trial_table(spark, rows)
    found = estimator.estimate_trials(ids, pairs, trials).toPandas().sort_values("trial")
    costs = mismatch.clustering_cost(estimator.budgeted_trials(ids, pairs, trials), pairs, "trial").toPandas().sort_values("trial")
    gap = (found["estimate"].to_numpy() - costs["cost"].to_numpy()) / costs["cost"].to_numpy()
    small, large = gap[:40], gap[40:]
    for g in (small, large):
        assert abs(g.mean()) < 4 * g.std() / len(g) ** 0.5
    assert large.std() < small.std()


def test_estimate_on_demand_equals_batch(spark):
    n, pairs = random_graph(3, 60, 0.1)
    ids, edges = frames(spark, n, pairs)
    one = estimator.trial_table(spark, [("s", 5, 0.5, budget_sizes(n, 0.5))])
    batch = estimator.estimate_trials(ids, edges, one).first()
    walked = estimator.estimate_cost(ids, EdgeTable(edges), k=5, budget=0.5).first()
    assert walked["estimate"] == pytest.approx(batch["estimate"]) and 4 <= walked["passes"] <= 5 + 4
    theory = estimator.estimate_cost(ids, EdgeTable(edges), k=5, eps=0.5, normalize=True, labels="rounds").first()
    exact = mismatch.clustering_cost(pivot.budgeted_pivot(ids, edges, 5), edges).first()["cost"]
    assert theory["estimate"] >= exact


def test_mismatch_degrees_sum_to_twice_the_cost(spark):
    n, pairs = random_graph(5)
    ids, edges = frames(spark, n, pairs)
    labels = pivot.pivot_cluster(ids, edges)
    cost = mismatch.clustering_cost(labels, edges).first()["cost"]
    assert mismatch.mismatch_degree(labels, edges).agg(F.sum("degree")).first()[0] == 2 * cost
    assert mismatch.mismatch_pairs(labels, edges).count() == cost


@pytest.mark.parametrize("bits,b,best", [((1, 0, 1), 2, 2), ((1, 0, 1), 1, 0), ((0, 1, 1, 0), 1, 3), ((0, 1, 1, 0), 2, 0)])
def test_index_gadget(spark, bits, b, best):
    nodes = gadgets.index_gadget(spark.createDataFrame([(i, x) for i, x in enumerate(bits, 1)], "i int, bit int"), b)
    pairs = SparseL1("x").pairs(nodes)
    edges = [(r["u"] - 1, r["v"] - 1) for r in pairs.collect()]
    assert nodes.count() == 2 * len(bits) and optimum.optimum_of(2 * len(bits), set(edges)) == best
    naive = Custom(lambda l, r: F.expr("true"))  # noqa: E741
    assert naive.pairs(nodes).count() == len(bits) * (2 * len(bits) - 1)


@pytest.mark.parametrize("x,y", [("00", "11"), ("10", "10"), ("11", "11")])
def test_disjointness_gadget(spark, x, y):
    rows = [(i, int(a), int(b)) for i, (a, b) in enumerate(zip(x, y, strict=True), 1)]
    nodes = gadgets.disjointness_gadget(spark.createDataFrame(rows, "i int, bx int, by int"))
    ids = sorted(r["id"] for r in nodes.collect())
    edges = {(ids.index(r["u"]), ids.index(r["v"])) for r in L1Ball(("x", "y")).pairs(nodes).collect()}
    assert optimum.optimum_of(len(ids), edges) == sum(a == b == "1" for a, b in zip(x, y, strict=True))


def test_cosine_takes_a_left_side_of_many_blocks(spark):
    rng = random.Random(4)
    v = spark.createDataFrame([(i, [rng.gauss(0, 1) for _ in range(4)] if i % 10 else None) for i in range(60)], "id bigint, e array<double>").persist()
    whole = sorted(tuple(r) for r in Cosine("e", 0.5).pairs(v).collect())
    assert whole and sorted(tuple(r) for r in Cosine("e", 0.5, broadcast_rows=7).pairs(v).collect()) == whole
    vectors = {r["id"]: r["e"] for r in v.where("e IS NOT NULL").collect()}
    unit = lambda x: [y / sum(z * z for z in x) ** 0.5 for y in x]
    assert whole == [(a, b) for a in sorted(vectors) for b in sorted(vectors) if a < b and sum(x * y for x, y in zip(unit(vectors[a]), unit(vectors[b]), strict=True)) > 0.5]


def test_similarities_on_odd_rows(spark):
    v = spark.createDataFrame([(1, [1.0, 0.0]), (2, [2.0, 0.0]), (3, [0.0, 0.0]), (4, None), (5, [0.0, 1.0])], "id bigint, e array<double>")
    assert [tuple(r) for r in Cosine("e", 0.5).pairs(v).collect()] == [(1, 2)]
    s = spark.createDataFrame([(1, ["a", "b", "b"]), (2, ["b", "a"]), (3, []), (4, None), (5, ["a"])], "id bigint, s array<string>")
    assert sorted(tuple(r) for r in Jaccard("s", 0.5).pairs(s).collect()) == [(1, 2)]
    assert sorted(tuple(r) for r in Jaccard("s", 0.4).pairs(s).collect()) == [(1, 2), (1, 5), (2, 5)]
    assert sorted(tuple(r) for r in SharedItems("s", 2).pairs(s).collect()) == [(1, 2)]
    k = spark.createDataFrame([(1, "a", 1), (2, "a", 4), (3, None, 1), (4, None, 1), (5, "a", 9)], "id bigint, k string, x bigint")
    assert sorted(tuple(r) for r in SameKey(("k",)).pairs(k).collect()) == [(1, 2), (1, 5), (2, 5)]
    assert sorted(tuple(r) for r in NearInKey("k", "x", 3).pairs(k).collect()) == [(1, 2)]
    messy = spark.createDataFrame([(2, 1), (1, 2), (3, 3), (1, 2)], "u bigint, v bigint")
    assert [tuple(r) for r in EdgeTable(messy).pairs(spark.range(1, 4)).collect()] == [(1, 2)]


def test_nodes_are_validated(spark):
    from pyspark.sql.types import LongType, StructField, StructType

    schema = StructType([StructField("id", LongType())])
    assert validated(spark.createDataFrame([(1, "x")], "id int, other string"), schema).columns == ["id"]
    with pytest.raises(ValueError):
        validated(spark.createDataFrame([(1,), (1,)], "id int"), schema)
    with pytest.raises(ValueError):
        validated(spark.createDataFrame([(1,)], "other int"), schema)


def test_ranks_and_samples(spark):
    ids = spark.range(1000)
    ranks = dense_rank_order(ids, "s").collect()
    assert [r["rank"] for r in sorted(ranks, key=lambda r: (r["key"], r["id"]))] == list(range(1, 1001))
    kept = {r["id"] for r in bottom_k(ids, 50, "s1", "s").collect()}
    parts = [bottom_k(ids.where(F.col("id") % 3 == i), 50, "s1", "s") for i in range(3)]
    merged = parts[0].unionByName(parts[1]).unionByName(parts[2]).orderBy("key", "id").limit(50)
    assert {r["id"] for r in merged.collect()} == kept  # samples merge


def test_sizes():
    s = theory_sizes(4206785, 15, 0.0, 0.1, capped=False)
    assert 9.0e8 < s.r < 1.1e9 and theory_sizes(500, 15).r == 500
    assert budget_sizes(1000, 0.12) == Sizes(60, 15, 15, 15, cutoff_of(1000, 15)) and passes(15) == 19


def test_plans(spark, sf):
    ids, pairs = nodes_and_pairs(spark, sf, "page")
    shown = lambda df: df._jdf.queryExecution().toString()
    assert "TakeOrderedAndProject" in shown(bottom_k(ids, 5, "", "s"))
    cost = shown(graph.degrees(ids, pairs))
    assert "CartesianProduct" not in cost
    pruned = shown(spark.read.parquet(f"{sf}/documents.parquet").where("n_chars > 5").select("doc_id"))
    assert "ReadSchema: struct<doc_id:bigint,n_chars:bigint>" in pruned and "PushedFilters: [IsNotNull(n_chars)" in pruned


def test_sampling_modes_differ_as_derived(spark, sf):
    """The classifying sample's own counts inflate the estimate; an independent sample does not."""
    ids, pairs = nodes_and_pairs(spark, sf, "emb3")
    n = ids.count()
    base = estimator.trial_table(spark, [("s", 5, 0.1, Sizes(50, 50, 50, 50, cutoff_of(n, 50)))])
    ranked = ranked_trials(ids, base)
    labels = lookup.anchored_pivot(ranked, lookup.anchors_of(ranked, base), pairs, base)
    trials = estimator.trial_table(spark, [(f"d{i}", 5, 0.1, Sizes(50, 50, 50, 25, cutoff_of(n, 50))) for i in range(40)])
    many = labels.drop("trial").crossJoin(F.broadcast(trials.select("trial")))
    truth = mismatch.part_costs(pivot.budgeted_pivot(ids, pairs, 5), labels, pairs).first()["exact_a"]
    mean = {m: anchored.estimate_anchored_part(many, pairs, trials, m).agg(F.avg("m_a")).first()[0] for m in ("paper", "two_sample")}
    assert mean["paper"] > 1.2 * truth and abs(mean["two_sample"] - truth) < 0.2 * truth
    assert residual.sample_centers(labels, base).count() > 0


def test_an_item_of_all_nodes_is_dealt_over_salts(spark, monkeypatch):
    """Forced low, the bound of a hot key changes no result of any join by key."""
    nodes = spark.range(300).select("id", F.array(F.lit(-1), F.col("id") % 40, F.lit(None).cast("bigint")).alias("items"), (F.col("id") % 3).alias("key"), (F.col("id") % 50).alias("x"))
    members = nodes.select("id", F.explode("items").alias("group"))
    models = [similarity.SharedItems("items", 2), similarity.Jaccard("items", 0.6), similarity.CoOccurrence(members, 2), similarity.SameKey(("key",)), similarity.NearInKey("key", "x", 5)]
    run = lambda: [sorted(m.pairs(nodes).collect()) for m in models] + [sorted(m.pairs_between(nodes.where("id < 20"), nodes).collect()) for m in models]
    whole = run()
    monkeypatch.setattr(similarity, "HOT", 7)
    assert run() == whole and all(whole)
