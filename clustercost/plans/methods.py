"""Queries of the methods, baselines, measures and experiments, each with its SQL where one exists."""

from __future__ import annotations

import re
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..lineage import checkpointed
from ..operators import anchored, baselines, bounds, classes, dense, estimator, gadgets, graph, lookup, metrics, mismatch, optimum, pivot, ranking, residual, sampling, tuning
from ..operators.similarity import CoOccurrence, Cosine, L1Ball, SameKey, SharedItems, SparseL1
from ..operators.walker import walk_pivots
from ..params import Sizes, budget_sizes, cutoff_of, pairs_for
from ..sources.graphs import load_graph, nodes_and_pairs, table
from . import oracle as o

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
SEED = "s"
GRAPHS = ("emb", "emb3", "page", "part", "doc", "cust")
R6 = lambda c: F.round(c, 6)


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def _trials(spark: SparkSession, ids: DataFrame, rows: list[tuple[str, int, float]], fixed: int | None = None, split: tuple | None = None) -> DataFrame:
    """Trial rows as in the SQL, with the pair counts of the sampling baselines."""
    n = ids.count()
    made = []
    for seed, k, space in rows:
        s = Sizes(fixed, fixed, fixed, fixed, cutoff_of(n, fixed)) if fixed else budget_sizes(n, space, **({"split": split} if split else {}))
        made.append((seed, k, space, s))
    extra = [(i, pairs_for(n, sp), pairs_for(n, sp, s.r)) for i, (_, _, sp, s) in enumerate(made)]
    return estimator.trial_table(spark, made).join(F.broadcast(spark.createDataFrame(extra, "trial int, q bigint, qp bigint")), "trial")


ONE = [(SEED, 15, 0.04)]
FIVE = [(SEED, 5, 0.1)]
T_ONE, T_FIVE = o.trials(ONE), o.trials(FIVE, fixed=50)

# --- graphs, orders, exact clusterings ---------------------------------------------------------------------


def _pairs(g: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        nodes, similarity = load_graph(spark, sf, g)
        return similarity.pairs(nodes)

    return run


def _degree(g: str) -> Query:
    return lambda spark, sf: graph.degrees(*nodes_and_pairs(spark, sf, g))


def _pivot_labels(g: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        nodes, similarity = load_graph(spark, sf, g)
        if isinstance(similarity, SharedItems):
            return classes.pivot_labels(classes.classes_of(nodes, similarity))
        if isinstance(similarity, Cosine):
            return dense.cosine_pivots(nodes, similarity)
        return pivot.pivot_cluster(*nodes_and_pairs(spark, sf, g))

    return run


def _pivot_cost(g: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        nodes, similarity = load_graph(spark, sf, g)
        if isinstance(similarity, SharedItems):
            return classes.pivot_cost(classes.classes_of(nodes, similarity))
        ids, pairs = nodes_and_pairs(spark, sf, g)
        return mismatch.clustering_cost(pivot.pivot_cluster(ids, pairs), pairs)

    return run


def _budgeted_labels(g: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        nodes, similarity = load_graph(spark, sf, g)
        if isinstance(similarity, SharedItems):
            return classes.budgeted_labels(classes.classes_of(nodes, similarity), 5)
        return pivot.budgeted_pivot(*nodes_and_pairs(spark, sf, g), k=5)

    return run


def _counted(spark: SparkSession, sf: str, g: str):
    """``(ids, pairs)``; for vectors a graph that counts takes the place of the pairs."""
    if g not in ("emb", "emb3"):
        return nodes_and_pairs(spark, sf, g)
    counted = dense.CosineGraph(*load_graph(spark, sf, g))
    return counted.ids, counted


def _estimate(g: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        ids, pairs = _counted(spark, sf, g)
        out = estimator.estimate_trials(ids, pairs, _trials(spark, ids, ONE))
        return out.select(R6("estimate").alias("estimate"), R6("m_a").alias("m_a"), R6("m_b").alias("m_b"), F.lit(19).cast("bigint").alias("passes"))

    return run


COST_COLUMNS = "SELECT n, m, m - kept AS cut_positive, together - kept AS joined_negative, cost FROM c"
for g in (*GRAPHS, "page2", "doc2", "evt"):
    query(f"pairs_{g}", o.query(o.GRAPH[g], "SELECT u, v FROM pairs"))(_pairs(g))
for g in GRAPHS:
    G = o.GRAPH[g]
    query(f"degree_{g}", o.query(G, "SELECT n.id, count(p.u)::BIGINT AS degree FROM nodes n LEFT JOIN (SELECT u, u AS id FROM pairs UNION ALL SELECT u, v FROM pairs) p USING (id) GROUP BY n.id"))(_degree(g))
    query(f"pivot_labels_{g}", o.query(G, T_ONE, o.fold(), "SELECT id, pivot FROM exact"))(_pivot_labels(g))
    query(f"pivot_cost_{g}", o.query(G, T_ONE, o.fold(), o.costs("exact", "c"), COST_COLUMNS))(_pivot_cost(g))
    query(f"budgeted_labels_{g}_k5", o.query(G, T_FIVE, o.fold(), o.BUDGETED, "SELECT id, pivot, calls::INTEGER AS calls, timed_out FROM labels"))(_budgeted_labels(g))
    query(f"estimate_cost_{g}", o.query(G, T_ONE, o.fold(), o.BUDGETED, o.ANCHORED, o.part_a("two_sample"), o.PART_B, "SELECT round(m_a + m_b, 6) AS estimate, round(m_a, 6) AS m_a, round(m_b, 6) AS m_b, 19::BIGINT AS passes FROM ea JOIN eb USING (trial)"))(_estimate(g))


def _profile_sql(g: str) -> str:
    inner = o.query(o.GRAPH[g], "SELECT n.id, count(p.u) AS degree FROM nodes n LEFT JOIN (SELECT u, u AS id FROM pairs UNION ALL SELECT u, v FROM pairs) p USING (id) GROUP BY n.id")
    return f"SELECT '{g}' AS graph, count(*) AS n, (sum(degree) // 2)::BIGINT AS m, round(avg(degree), 6) AS avg_degree, max(degree) AS max_degree, count(*) FILTER (degree = 0) AS isolated FROM ({inner})"


@query("profile_graphs", " UNION ALL ".join(_profile_sql(g) for g in ("emb", "emb3", "page", "part", "doc")))
def profile_graphs(spark: SparkSession, sf: str) -> DataFrame:
    out = None
    for g in ("emb", "emb3", "page", "part", "doc"):
        row = graph.profile(*nodes_and_pairs(spark, sf, g)).select(F.lit(g).alias("graph"), "*")
        out = row if out is None else out.unionByName(row)
    return out


EMB, EMB3 = o.GRAPH["emb"], o.GRAPH["emb3"]


@query("pivot_labels_page_rounds", ORACLES["pivot_labels_page"])
def pivot_labels_page_rounds(spark: SparkSession, sf: str) -> DataFrame:
    """The form for graphs of any size."""
    return pivot.pivot_cluster(*nodes_and_pairs(spark, sf, "page"), form="rounds")


@query("budgeted_labels_page_k5_rounds", ORACLES["budgeted_labels_page_k5"])
def budgeted_labels_page_k5_rounds(spark: SparkSession, sf: str) -> DataFrame:
    return pivot.budgeted_pivot(*nodes_and_pairs(spark, sf, "page"), k=5, strategy="rounds")


@query("rank_order_emb", "SELECT vec_id AS id, md5('s:' || vec_id) AS key, row_number() OVER (ORDER BY md5('s:' || vec_id), vec_id) AS rank FROM embeddings")
def rank_order_emb(spark: SparkSession, sf: str) -> DataFrame:
    return ranking.dense_rank_order(table(spark, sf, "embeddings").select(F.col("vec_id").alias("id")), SEED).select("id", "key", "rank")


@query("anchors_emb", "SELECT vec_id AS id, md5('s:' || vec_id) AS key FROM embeddings ORDER BY 2, 1 LIMIT 50")
def anchors_emb(spark: SparkSession, sf: str) -> DataFrame:
    return sampling.bottom_k(table(spark, sf, "embeddings").select(F.col("vec_id").alias("id")), 50, "", SEED).select("id", "key")


# --- budgeted pivot, sweeps of k, calls ------------------------------------------------------------------

DEPTHS = tuple(range(2, 21))


@query(
    "budgeted_cost_emb_sweep",
    o.query(EMB, o.trials([(SEED, k, 0.04) for k in DEPTHS]), o.fold(), o.BUDGETED, o.costs("labels", "c"), o.costs("exact", "x"), "SELECT t.k, c.cost, round((c.cost - x.cost) / x.cost, 6) AS rel_error FROM c JOIN trials t USING (trial) JOIN x USING (trial)"),
)
def budgeted_cost_emb_sweep(spark: SparkSession, sf: str) -> DataFrame:
    ids, pairs = nodes_and_pairs(spark, sf, "emb")
    trials = estimator.trial_table(spark, [(SEED, k, 0.04, budget_sizes(1, 1.0)) for k in DEPTHS])
    cost = mismatch.clustering_cost(checkpointed(estimator.budgeted_trials(ids, pairs, trials)), pairs, "trial")
    best = mismatch.clustering_cost(pivot.pivot_cluster(ids, pairs), pairs).select(F.col("cost").alias("best"))
    return cost.join(F.broadcast(trials.select("trial", "k")), "trial").crossJoin(F.broadcast(best)).select("k", "cost", R6(metrics.relative_error(F.col("cost"), F.col("best"))).alias("rel_error"))


@query("calls_histogram_emb", o.query(EMB, T_ONE, o.fold(), o.BUDGETED, "SELECT calls::INTEGER AS calls, count(*) AS nodes FROM labels GROUP BY ALL"))
def calls_histogram_emb(spark: SparkSession, sf: str) -> DataFrame:
    return metrics.calls_histogram(pivot.budgeted_pivot(*nodes_and_pairs(spark, sf, "emb"), k=15))


@query("timed_out_share_emb", o.query(EMB, T_ONE, o.fold(), o.BUDGETED, "SELECT round(avg(timed_out::INT), 6) AS share FROM labels"))
def timed_out_share_emb(spark: SparkSession, sf: str) -> DataFrame:
    return metrics.timed_out_share(pivot.budgeted_pivot(*nodes_and_pairs(spark, sf, "emb"), k=15)).select(R6("share").alias("share"))


# --- anchored lookups and exact parts -----------------------------------------------------------------


def _anchored(spark: SparkSession, sf: str, g: str = "emb", rows: list | None = None, fixed: int | None = 50):
    ids, pairs = nodes_and_pairs(spark, sf, g)
    trials = _trials(spark, ids, rows or FIVE, fixed)
    ranked = checkpointed(ranking.ranked_trials(ids, trials))
    labels = checkpointed(lookup.anchored_pivot(ranked, checkpointed(lookup.anchors_of(ranked, trials)), pairs, trials))
    return ids, pairs, trials, ranked, labels


def _anchored_counted(spark: SparkSession, sf: str):
    """The same for vectors with a graph that counts instead of pairs."""
    counted = dense.CosineGraph(*load_graph(spark, sf, "emb"))
    trials = checkpointed(_trials(spark, counted.ids, FIVE, 50))
    ranked = checkpointed(ranking.ranked_trials(counted.ids, trials))
    labels = checkpointed(lookup.anchored_pivot(ranked, checkpointed(lookup.anchors_of(ranked, trials)), counted, trials))
    return counted, trials, labels


def _anchored_on_demand(spark: SparkSession, sf: str):
    """The same for vectors with similarities between anchors and nodes only."""
    nodes, similarity = load_graph(spark, sf, "emb")
    ids = nodes.select("id")
    trials = checkpointed(_trials(spark, ids, FIVE, 50))
    ranked = checkpointed(ranking.ranked_trials(ids, trials))
    anchors = checkpointed(lookup.anchors_of(ranked, trials))
    met = lambda some: estimator._sampled_pairs(nodes, similarity, some)
    return trials, ranked, checkpointed(lookup.anchored_pivot(ranked, anchors, met(anchors), trials)), met


BASE5 = (EMB, T_FIVE, o.fold(), o.BUDGETED, o.ANCHORED)


@query("anchored_labels_emb", o.query(*BASE5, "SELECT id, coalesce(pivot, -1) AS pivot, calls::INTEGER AS calls, part FROM al"))
def anchored_labels_emb(spark: SparkSession, sf: str) -> DataFrame:
    """An undetermined pivot shows as -1."""
    return _anchored_on_demand(spark, sf)[2].select("id", F.coalesce("pivot", F.lit(-1)).alias("pivot"), "calls", "part")


@query("part_sizes_emb", o.query(*BASE5, "d AS (SELECT x AS id, count(*) AS degree FROM (SELECT u AS x FROM pairs UNION ALL SELECT v FROM pairs) GROUP BY x)", "SELECT part, count(*) AS nodes, max(coalesce(degree, 0))::BIGINT AS max_degree FROM al LEFT JOIN d USING (id) GROUP BY part"))
def part_sizes_emb(spark: SparkSession, sf: str) -> DataFrame:
    counted, _, labels = _anchored_counted(spark, sf)
    return lookup.part_sizes(labels, counted.degrees())


@query("mismatch_pairs_emb3", o.query(EMB3, T_ONE, o.fold(), "SELECT p.u, p.v, 'cut' AS kind FROM pairs p JOIN exact a ON a.id = p.u JOIN exact b ON b.id = p.v WHERE a.pivot <> b.pivot UNION ALL SELECT a.id AS u, b.id AS v, 'joined' AS kind FROM exact a JOIN exact b ON a.pivot = b.pivot AND a.id < b.id LEFT JOIN pairs p ON p.u = a.id AND p.v = b.id WHERE p.u IS NULL"))
def mismatch_pairs_emb3(spark: SparkSession, sf: str) -> DataFrame:
    ids, pairs = nodes_and_pairs(spark, sf, "emb3")
    return mismatch.mismatch_pairs(checkpointed(pivot.pivot_cluster(ids, pairs)), pairs)


@query(
    "mismatch_parts_emb",
    o.query(*BASE5, "mm AS (SELECT x.part = 'A' OR y.part = 'A' AS touched FROM labels a JOIN labels b ON a.id < b.id LEFT JOIN pairs p ON p.u = a.id AND p.v = b.id JOIN al x ON x.id = a.id JOIN al y ON y.id = b.id WHERE (p.u IS NOT NULL) = (a.pivot <> b.pivot))", "SELECT count(*) FILTER (touched) AS exact_a, count(*) FILTER (NOT touched) AS exact_b FROM mm"),
)
def mismatch_parts_emb(spark: SparkSession, sf: str) -> DataFrame:
    counted, trials, labels = _anchored_counted(spark, sf)
    return mismatch.part_costs(estimator.budgeted_trials(counted.ids, counted, trials), labels, counted)


@query("anchored_degree_emb", o.query(*BASE5, o.AMISMATCH, "SELECT a.id, count(m.y)::BIGINT AS degree_a FROM al a LEFT JOIN amis m ON m.x = a.id GROUP BY a.id"))
def anchored_degree_emb(spark: SparkSession, sf: str) -> DataFrame:
    counted, _, labels = _anchored_counted(spark, sf)
    return mismatch.anchored_degree(labels, counted)


@query("mismatch_degree_emb3", o.query(EMB3, T_ONE, o.fold(), "SELECT a.id, count(*) FILTER ((p.u IS NOT NULL) = (a.pivot <> b.pivot))::BIGINT AS degree FROM exact a JOIN exact b ON a.id <> b.id LEFT JOIN pairs p ON p.u = least(a.id, b.id) AND p.v = greatest(a.id, b.id) GROUP BY a.id"))
def mismatch_degree_emb3(spark: SparkSession, sf: str) -> DataFrame:
    ids, pairs = nodes_and_pairs(spark, sf, "emb3")
    return mismatch.mismatch_degree(checkpointed(pivot.pivot_cluster(ids, pairs)), pairs)


@query("hits_emb", o.query(*BASE5, o.part_a("paper"), "SELECT id, hits::BIGINT AS hits, is_high FROM cls"))
def hits_emb(spark: SparkSession, sf: str) -> DataFrame:
    _, pairs, trials, _, labels = _anchored(spark, sf)
    return anchored.classify_by_sample(labels, pairs, trials, "paper").select("id", "hits", "is_high")


def _part_a(mode: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        trials, ranked, labels, met = _anchored_on_demand(spark, sf)
        near = met(reduce(DataFrame.unionByName, [sampling.bottom_k_trials(ranked, trials, "t1", salt) for salt in ("s1", "s1b")]))
        low = anchored.classify_by_sample(labels, near, trials, mode).where(~F.col("is_high")).select("trial", "id", "pivot")
        pairs = checkpointed(near.unionByName(met(sampling.bottom_k_trials(low, trials, "t2", "s2"))).distinct())
        return anchored.estimate_anchored_part(labels, pairs, trials, mode).select(R6("m_a").alias("m_a"), "n_low", "t1", "t2")

    return run


for mode in ("paper", "floor", "two_sample"):
    query(f"estimate_anchored_emb_{mode}", o.query(*BASE5, o.part_a(mode), "SELECT round(m_a, 6) AS m_a, n_low, t1, t2 FROM ea"))(_part_a(mode))


@query("estimate_residual_emb", o.query(*BASE5, o.PART_B, "SELECT round(m_b, 6) AS m_b, n_b, t FROM eb"))
def estimate_residual_emb(spark: SparkSession, sf: str) -> DataFrame:
    counted, trials, labels = _anchored_counted(spark, sf)
    return residual.estimate_residual_part(labels, checkpointed(estimator.budgeted_trials(counted.ids, counted, trials)), counted, trials).select(R6("m_b").alias("m_b"), "n_b", "t")


@query("center_counts_emb", o.query(*BASE5, o.PART_B, "SELECT center, size, n_in::BIGINT AS n_in, n_out::BIGINT AS n_out FROM cen"))
def center_counts_emb(spark: SparkSession, sf: str) -> DataFrame:
    counted, trials, labels = _anchored_counted(spark, sf)
    members = checkpointed(estimator.budgeted_trials(counted.ids, counted, trials))
    return residual.center_mismatch_counts(residual.cluster_of(residual.sample_centers(labels, trials), members, counted), labels, counted).select("center", "size", "n_in", "n_out")


@query("walker_emb", o.query(EMB, T_FIVE, o.fold(), o.BUDGETED, "SELECT id, pivot FROM labels JOIN ranked USING (trial, id) ORDER BY rk DESC LIMIT 50"))
def walker_emb(spark: SparkSession, sf: str) -> DataFrame:
    nodes, similarity = load_graph(spark, sf, "emb")
    ranked = checkpointed(nodes.select(F.lit(0).alias("trial"), "id", ranking.rank_key(SEED).alias("key")))
    last = checkpointed(ranked.orderBy(F.desc("key"), F.desc("id")).limit(50).select("trial", "id"))
    return walk_pivots(last, ranked, nodes, similarity, 5).select("id", "pivot")


# --- the whole estimate -----------------------------------------------------------------------------------


#: Scans of a run: ranks, anchors and first samples, second sample and centers, walks, and the members' last scan.
#: A walk takes as many scans as its lookup has calls, and k at most.
COUNTED = "(SELECT 4 + coalesce(max(least(e.calls, 15)), 0) FROM exact e SEMI JOIN (SELECT id FROM sb UNION SELECT sym.y FROM sb JOIN sym ON sym.x = sb.id) g ON g.id = e.id)::INTEGER AS passes"


@query("estimate_cost_emb_on_demand", ORACLES["estimate_cost_emb"].replace("19::BIGINT AS passes", COUNTED))
def estimate_cost_emb_on_demand(spark: SparkSession, sf: str) -> DataFrame:
    """Similarities evaluated only between samples and nodes, residual members settled by walks."""
    nodes, similarity = load_graph(spark, sf, "emb")
    out = estimator.estimate_cost(nodes, similarity, k=15, budget=0.04)
    return out.select(R6("estimate").alias("estimate"), R6("m_a").alias("m_a"), R6("m_b").alias("m_b"), "passes")


@query("estimate_cost_normalized_emb", o.query(EMB, T_ONE, o.fold(), o.BUDGETED, o.costs("labels", "c"), "SELECT round((cost + 0.375 * 0.1 * n) / (1 - 0.1 / 8), 6) AS estimate FROM c"))
def estimate_cost_normalized_emb(spark: SparkSession, sf: str) -> DataFrame:
    """Theory sizes exceed these graphs, so samples are whole and the estimate is the exact cost, normalised."""
    nodes, similarity = load_graph(spark, sf, "emb")
    return estimator.estimate_cost(nodes, similarity, k=15, eps=0.1, normalize=True, labels="rounds").select(R6("estimate").alias("estimate"))


THEORY = [(0.0, 0.1, 15), (0.5, 0.1, 37), (0.0, 0.5, 15)]


@query(
    "theory_sizes",
    "SELECT user_id, n, alpha, eps, k, ceil(48 * k * pow(n, 1 - b) * ln(n))::BIGINT AS r, ceil(12 * pow(n, 1 - b) * ln(n) / (eps * eps))::BIGINT AS t1, ceil(32 * pow(n, alpha + b) * ln(n) / (eps * eps))::BIGINT AS t2, ceil(8 * pow(n, alpha + 2 * b) * ln(n) / (eps * eps))::BIGINT AS t, round(2 * ceil(12 * pow(n, 1 - b) * ln(n) / (eps * eps)) / pow(n, 1 - b), 4) AS cutoff FROM (SELECT *, (1 - alpha) / 4 AS b FROM (SELECT user_id, count(*) AS n FROM events GROUP BY user_id), (VALUES "
    + ", ".join(f"({a}::DOUBLE, {e}::DOUBLE, {k})" for a, e, k in THEORY)
    + ") v(alpha, eps, k))",
)
def theory_size_rows(spark: SparkSession, sf: str) -> DataFrame:
    """Uncapped sizes for the graph of each user's events."""
    points = F.broadcast(spark.createDataFrame(THEORY, "alpha double, eps double, k int"))
    rows = table(spark, sf, "events").groupBy("user_id").agg(F.count("*").alias("n")).crossJoin(points)
    b = (1 - F.col("alpha")) / 4
    log, e2 = F.ln("n"), F.col("eps") * F.col("eps")
    t1 = F.ceil(12 * F.pow("n", 1 - b) * log / e2)
    return rows.select(
        "user_id", "n", "alpha", "eps", "k", F.ceil(48 * F.col("k") * F.pow("n", 1 - b) * log).alias("r"), t1.alias("t1"), F.ceil(32 * F.pow("n", F.col("alpha") + b) * log / e2).alias("t2"), F.ceil(8 * F.pow("n", F.col("alpha") + 2 * b) * log / e2).alias("t"), F.round(2 * t1 / F.pow("n", 1 - b), 4).alias("cutoff")
    )


SEEDS9 = [(f"{SEED}{i}", 15, 0.2) for i in range(9)]
FULL = (o.fold(), o.BUDGETED, o.ANCHORED, o.part_a("two_sample"), o.PART_B)


@query("boosted_estimate_emb", o.query(EMB, o.trials(SEEDS9), *FULL, "SELECT round(median(m_a + m_b), 6) AS median_estimate, count(*) AS repeats FROM ea JOIN eb USING (trial)"))
def boosted_estimate_emb(spark: SparkSession, sf: str) -> DataFrame:
    return estimator.boosted_estimate(*_counted(spark, sf, "emb"), k=15, budget=0.2).select(R6("median_estimate").alias("median_estimate"), "repeats")


# --- experiments ------------------------------------------------------------------------------------------

SPACES = (0.02, 0.04, 0.08, 0.10, 0.12, 0.16)
SEEDS = tuple(f"{SEED}{i}" for i in range(5))


def sweep(spark: SparkSession, ids: DataFrame, pairs: DataFrame, rows: list[tuple[str, int, float]], methods: tuple[str, ...], split: tuple | None = None, mode: str = "two_sample") -> DataFrame:
    """``trial, method, value, best`` for each trial and method; ``best`` is the pivot cost under the same order."""
    trials = checkpointed(_trials(spark, ids, rows, split=split))
    ranked = checkpointed(ranking.ranked_trials(ids, trials))
    seeds = trials.groupBy("seed").agg(F.min("trial").alias("trial"))
    by_seed = ranked.join(F.broadcast(seeds.select("trial")), "trial")
    exact = checkpointed(pivot.settle(by_seed, pivot.earlier_neighbours(by_seed, pairs)))
    best = mismatch.clustering_cost(exact, pairs, "trial").join(F.broadcast(seeds), "trial").select("seed", F.col("cost").alias("best"))
    labels = checkpointed(estimator.budgeted_trials(ids, pairs, trials))
    found: list[DataFrame] = []
    if "pivot" in methods:
        found.append(trials.join(F.broadcast(best), "seed").select("trial", F.lit("pivot").alias("method"), F.col("best").cast("double").alias("value")))
    if "budgeted" in methods:
        found.append(mismatch.clustering_cost(labels, pairs, "trial").select("trial", F.lit("budgeted").alias("method"), F.col("cost").cast("double").alias("value")))
    if "compact" in methods:
        found.append(estimator.estimate_trials(ids, pairs, trials, mode, labels).select("trial", F.lit("compact").alias("method"), F.col("estimate").alias("value")))
    if "pair_sampling" in methods:
        found.append(baselines.pair_sampling(ranked, labels, pairs, trials).select("trial", F.lit("pair_sampling").alias("method"), F.col("estimate").cast("double").alias("value")))
    if "prior_pivot" in methods:
        free = trials.withColumn("k", F.lit(1_000_000))
        al = checkpointed(lookup.anchored_pivot(ranked, checkpointed(lookup.anchors_of(ranked, free)), pairs, free))
        found.append(baselines.prior_pivot(ranked, al, pairs, trials.drop("q").withColumnRenamed("qp", "q")).select("trial", F.lit("prior_pivot").alias("method"), F.col("estimate").cast("double").alias("value")))
    if "prior_sparse_dense" in methods:
        sized = trials.drop("t").withColumn("t", F.greatest(F.lit(1), F.floor(F.col("space") * ids.count() / 9 + 0.5)).cast("int"))
        found.append(baselines.prior_sparse_dense(ids, pairs, sized).select("trial", F.lit("prior_sparse_dense").alias("method"), F.col("estimate").cast("double").alias("value")))
    out = found[0]
    for more in found[1:]:
        out = out.unionByName(more)
    return checkpointed(out.join(F.broadcast(trials.select("trial", "seed", "k", "space")), "trial").join(F.broadcast(best), "seed"))


def _errors(found: DataFrame, *by: str) -> DataFrame:
    error = metrics.relative_error(F.col("value"), F.col("best"))
    return found.withColumn("e", error).groupBy(*by, "method").agg(R6(F.avg("e")).alias("mean_err"), R6(F.stddev_samp("e")).alias("sd_err"))


def _values(*methods: str) -> str:
    """SQL for ``val(trial, method, value)``."""
    each = {
        "budgeted": "SELECT trial, 'budgeted' AS method, cost::DOUBLE AS value FROM cb",
        "compact": "SELECT trial, 'compact' AS method, m_a + m_b AS value FROM ea JOIN eb USING (trial)",
        "pair_sampling": "SELECT trial, 'pair_sampling' AS method, estimate AS value FROM pe",
        "prior_pivot": "SELECT trial, 'prior_pivot' AS method, estimate AS value FROM pp",
        "prior_sparse_dense": "SELECT trial, 'prior_sparse_dense' AS method, estimate AS value FROM psd",
    }
    return "val AS MATERIALIZED (" + " UNION ALL ".join(each[m] for m in methods) + ")"


ERRORS = "SELECT {by}, v.method, round(avg((v.value - x.cost) / nullif(x.cost, 0)), 6) AS mean_err, round(stddev_samp((v.value - x.cost) / nullif(x.cost, 0)), 6) AS sd_err FROM val v JOIN trials t USING (trial) JOIN x USING (trial) GROUP BY {by}, v.method"
SPACE_ROWS = [(s, 15, f) for f in SPACES for s in SEEDS]
DEPTH_ROWS = [(s, k, 0.04) for k in (2, 3, 5, 8, 10, 15, 20) for s in SEEDS]
PRIOR = (
    "sp AS MATERIALIZED (SELECT o.trial, o.rk, min(o.near) FILTER (x.pivot = x.id) AS first FROM oriented o JOIN trials t USING (trial) JOIN exact x ON x.trial = o.trial AND x.rk = o.near WHERE o.near <= t.r GROUP BY ALL)",
    "pl AS MATERIALIZED (SELECT r.trial, r.id, coalesce(q.id, r.id) AS pivot FROM ranked r LEFT JOIN sp USING (trial, rk) LEFT JOIN ranked q ON q.trial = r.trial AND q.rk = sp.first)",
)


def _renamed(sql: str, suffix: str) -> str:
    """A second set of drawn pairs beside the first."""
    return re.sub(r"\b(num|kept|tri|dp)\b", rf"\g<1>{suffix}", sql)


for g in ("emb", "page", "part"):

    def _space(spark: SparkSession, sf: str, g: str = g) -> DataFrame:
        return _errors(sweep(spark, *nodes_and_pairs(spark, sf, g), SPACE_ROWS, ("budgeted", "compact")), "space")

    def _depth(spark: SparkSession, sf: str, g: str = g) -> DataFrame:
        return _errors(sweep(spark, *nodes_and_pairs(spark, sf, g), DEPTH_ROWS, ("budgeted", "compact")), "k")

    heavy = g == "part"  # pair-by-pair SQL over 2,000 nodes and 30 trials is out of reach
    query(f"space_sweep_{g}", None if heavy else o.query(o.GRAPH[g], o.trials(SPACE_ROWS), *FULL, o.costs("labels", "cb"), o.costs("exact", "x"), _values("budgeted", "compact"), ERRORS.format(by="t.space")))(_space)
    query(f"depth_sweep_{g}", None if heavy else o.query(o.GRAPH[g], o.trials(DEPTH_ROWS), *FULL, o.costs("labels", "cb"), o.costs("exact", "x"), _values("budgeted", "compact"), ERRORS.format(by="t.k")))(_depth)

#: The grids in full: a hundred orders, all spaces and every depth from 2 to 20; without SQL, since pair-by-pair SQL takes hours on them.
MANY = tuple(f"{SEED}{i}" for i in range(100))
for g in ("emb", "page"):

    def _space_many(spark: SparkSession, sf: str, g: str = g) -> DataFrame:
        return _errors(sweep(spark, *nodes_and_pairs(spark, sf, g), [(s, 15, f) for f in SPACES for s in MANY], ("budgeted", "compact", "pair_sampling", "prior_pivot")), "space")

    def _depth_many(spark: SparkSession, sf: str, g: str = g) -> DataFrame:
        return _errors(sweep(spark, *nodes_and_pairs(spark, sf, g), [(s, k, 0.04) for k in range(2, 21) for s in MANY], ("budgeted", "compact")), "k")

    query(f"space_sweep_{g}_orders100")(_space_many)
    query(f"depth_sweep_{g}_orders100")(_depth_many)

COMPETE_ROWS = [(s, 15, f) for f in (0.04, 0.1, 0.16) for s in SEEDS]
for g in ("emb", "page"):

    def _compete(spark: SparkSession, sf: str, g: str = g) -> DataFrame:
        return _errors(sweep(spark, *nodes_and_pairs(spark, sf, g), COMPETE_ROWS, ("compact", "pair_sampling", "prior_pivot")), "space")

    second = _renamed(o.drawn("prior", "qp"), "2")
    query(
        f"competitors_{g}",
        o.query(o.GRAPH[g], o.trials(COMPETE_ROWS), *FULL, o.costs("exact", "x"), o.drawn("pair"), o.pair_estimate("labels"), *PRIOR, second, o.pair_estimate("pl", "pp").replace("FROM dp d", "FROM dp2 d"), _values("compact", "pair_sampling", "prior_pivot"), ERRORS.format(by="t.space")),
    )(_compete)


def sparse_dense_sql(eta: float = 0.5, delta: float = 0.001, near_sample: int = 8) -> tuple[str, ...]:
    return (
        "deg AS MATERIALIZED (SELECT n.id, count(s.y) AS d FROM nodes n LEFT JOIN sym s ON s.x = n.id GROUP BY n.id)",
        "ssd AS MATERIALIZED (SELECT trial, seed, id FROM (SELECT t.trial, t.seed, n.id, row_number() OVER (PARTITION BY t.trial ORDER BY md5('sd:' || t.seed || ':' || n.id), n.id) AS o, greatest(1, floor(t.space * t.n / 9 + 0.5)) AS w FROM nodes n, trials t) WHERE o <= w)",
        f"nbr AS MATERIALIZED (SELECT s.trial, s.id, m.y AS near, a.d AS d1, b.d AS d2, row_number() OVER (PARTITION BY s.trial, s.id ORDER BY md5('sn:' || s.seed || ':' || m.y), m.y) AS o FROM ssd s JOIN sym m ON m.x = s.id JOIN deg a ON a.id = s.id JOIN deg b ON b.id = m.y)",
        "com AS MATERIALIZED (SELECT n.id, n.near, count(*) AS c FROM (SELECT DISTINCT id, near FROM nbr) n JOIN sym a ON a.x = n.id JOIN sym b ON b.x = n.near AND b.y = a.y GROUP BY ALL)",
        f"dif AS MATERIALIZED (SELECT n.*, n.d1 + n.d2 - 2 * coalesce(c.c, 0) - 2 >= {eta} * greatest(n.d1, n.d2) AS differ FROM nbr n LEFT JOIN com c USING (id, near))",
        f"jud AS MATERIALIZED (SELECT trial, id, d1, count(*) FILTER (o <= {near_sample} AND differ) AS far, count(*) FILTER (o <= {near_sample}) AS seen, count(*) FILTER (differ) AS outside FROM dif GROUP BY ALL)",
        f"psd AS MATERIALIZED (SELECT s.trial, coalesce(j.s, 0) * t.n / s.t + {delta} * t.n * t.n AS estimate FROM (SELECT trial, count(*) AS t FROM ssd GROUP BY trial) s JOIN trials t USING (trial) LEFT JOIN (SELECT trial, sum(CASE WHEN far >= {eta} * seen THEN d1 ELSE outside END / 2) AS s FROM jud GROUP BY trial) j USING (trial))",
    )


for g in ("emb", "page"):

    def _absolute(spark: SparkSession, sf: str, g: str = g) -> DataFrame:
        found = sweep(spark, *nodes_and_pairs(spark, sf, g), COMPETE_ROWS, ("compact", "prior_sparse_dense"))
        return found.groupBy("space", "method").agg(F.round(F.avg("value"), 4).alias("mean_cost"), F.round(F.stddev_samp("value"), 4).alias("sd_cost"))

    query(
        f"absolute_sparse_dense_{g}",
        o.query(o.GRAPH[g], o.trials(COMPETE_ROWS), *FULL, *sparse_dense_sql(), _values("compact", "prior_sparse_dense"), "SELECT t.space, v.method, round(avg(v.value), 4) AS mean_cost, round(stddev_samp(v.value), 4) AS sd_cost FROM val v JOIN trials t USING (trial) GROUP BY ALL"),
    )(_absolute)


def _one_trial(spark: SparkSession, sf: str, g: str = "emb"):
    ids, pairs = nodes_and_pairs(spark, sf, g)
    trials = _trials(spark, ids, [(SEED, 15, 0.1)])
    return ids, pairs, trials, checkpointed(ranking.ranked_trials(ids, trials))


T_TENTH = o.trials([(SEED, 15, 0.1)])


@query("pair_sampling_emb", o.query(EMB, T_TENTH, o.fold(), o.BUDGETED, o.drawn("pair"), o.pair_estimate("labels"), "SELECT round(estimate, 6) AS estimate, q FROM pe"))
def pair_sampling_emb(spark: SparkSession, sf: str) -> DataFrame:
    ids, pairs, trials, ranked = _one_trial(spark, sf)
    return baselines.pair_sampling(ranked, checkpointed(estimator.budgeted_trials(ids, pairs, trials)), pairs, trials).select(R6("estimate").alias("estimate"), "q")


@query("prior_pivot_emb", o.query(EMB, T_TENTH, o.fold(), *PRIOR, o.drawn("prior", "qp"), o.pair_estimate("pl"), "SELECT round(estimate, 6) AS estimate FROM pe"))
def prior_pivot_emb(spark: SparkSession, sf: str) -> DataFrame:
    ids, pairs = _counted(spark, sf, "emb")
    trials = checkpointed(_trials(spark, ids, [(SEED, 15, 0.1)]))
    ranked = checkpointed(ranking.ranked_trials(ids, trials))
    anchors = checkpointed(lookup.anchors_of(ranked, trials))
    al = checkpointed(dense.cosine_pivots(pairs.nodes, pairs.similarity, SEED, among=anchors).select(F.lit(0).alias("trial"), "id", "pivot"))
    return baselines.prior_pivot(ranked, al, pairs, trials.drop("q").withColumnRenamed("qp", "q")).select(R6("estimate").alias("estimate"))


SYM = "sym AS MATERIALIZED (SELECT u AS x, v AS y FROM pairs UNION ALL SELECT v, u FROM pairs)"


@query("prior_sparse_dense_emb", o.query(EMB, T_TENTH, SYM, *sparse_dense_sql(), "SELECT round(estimate, 6) AS estimate FROM psd"))
def prior_sparse_dense_emb(spark: SparkSession, sf: str) -> DataFrame:
    ids, pairs = _counted(spark, sf, "emb")
    trials = _trials(spark, ids, [(SEED, 15, 0.1)])
    sized = trials.drop("t").withColumn("t", F.greatest(F.lit(1), F.floor(F.col("space") * ids.count() / 9 + 0.5)).cast("int"))
    return baselines.prior_sparse_dense(ids, pairs, sized).select(R6("estimate").alias("estimate"))


@query("naive_degree_emb", o.query(*BASE5, o.AMISMATCH, o._sample("nd", "al", "t2", "nd"), "SELECT round((SELECT count(*) FROM amis m SEMI JOIN nd ON nd.id = m.x) * (SELECT count(*) FROM al) / (SELECT count(*) FROM nd) / 2, 6) AS estimate"))
def naive_degree_emb(spark: SparkSession, sf: str) -> DataFrame:
    trials, ranked, labels, met = _anchored_on_demand(spark, sf)
    return baselines.naive_degree(labels, met(sampling.bottom_k_trials(ranked, trials, "t2", "nd")), trials).select(R6("estimate").alias("estimate"))


@query("store_everything_emb", ORACLES["pivot_cost_emb"])
def store_everything_emb(spark: SparkSession, sf: str) -> DataFrame:
    """All nodes kept: the exact rounds form of pivot."""
    ids, pairs = nodes_and_pairs(spark, sf, "emb")
    return mismatch.clustering_cost(checkpointed(pivot.pivot_cluster(ids, pairs, form="rounds")), pairs)


@query("bad_triangle_bound_emb3")
def bad_triangle_bound_emb3(spark: SparkSession, sf: str) -> DataFrame:
    ids, pairs = nodes_and_pairs(spark, sf, "emb3")
    cost = mismatch.clustering_cost(pivot.pivot_cluster(ids, pairs), pairs).select("cost")
    return optimum.bad_triangle_bound(pairs).crossJoin(cost).select("packed", "cost", R6(F.col("cost") / F.nullif("packed", F.lit(0))).alias("ratio"))


@query("optimum_supplier")
def optimum_supplier(spark: SparkSession, sf: str) -> DataFrame:
    """Eight suppliers, similar at balances at most 2,000 apart: the optimum and the mean pivot cost over ten orders."""
    nodes = table(spark, sf, "supplier").where("s_suppkey < 9").select(F.col("s_suppkey").alias("id"), F.col("s_acctbal").alias("x"))
    pairs = checkpointed(L1Ball(("x",), 2000.0).pairs(nodes))
    trials = estimator.trial_table(spark, [(f"s{i}", 2, 1.0, budget_sizes(8, 1.0)) for i in range(10)])
    ranked = ranking.ranked_trials(nodes, trials)
    cost = mismatch.clustering_cost(pivot.settle(ranked, pivot.earlier_neighbours(ranked, pairs)), pairs, "trial")
    return optimum.brute_force_optimum(nodes, pairs).crossJoin(cost.agg(F.avg("cost").alias("mean_pivot")))


# --- tuning, inconsistency, gadgets, bounds, controls ---------------------------------------------------

EMB_GRID, DOC_GRID = (0.15, 0.2, 0.25, 0.3, 0.35), (0.001, 0.01, 0.05, 0.2, 0.5, 0.8)


def _tune_sql(g: str, grid: tuple) -> str:
    points = ", ".join(f"({i}, {x!r}::DOUBLE)" for i, x in enumerate(grid))
    return o.query(
        o.GRAPH[g], f"grid(trial, theta) AS (VALUES {points})", "trials AS MATERIALIZED (SELECT trial, 's' AS seed, 15 AS k, theta FROM grid)", "tpairs AS MATERIALIZED (SELECT g.trial, s.u, s.v FROM scored s, grid g WHERE s.score > g.theta)", o.fold(True), o.costs("exact", "c", True),
        "SELECT t.theta, c.m, c.cost, c.trial = (SELECT trial FROM c ORDER BY cost, trial LIMIT 1) AS is_best FROM c JOIN trials t USING (trial)",
    )


@query("tune_threshold_emb", _tune_sql("emb", EMB_GRID))
def tune_threshold_emb(spark: SparkSession, sf: str) -> DataFrame:
    nodes, similarity = load_graph(spark, sf, "emb")
    similarity.theta = min(EMB_GRID)
    return tuning.tune_threshold(nodes.select("id"), similarity.scored(nodes), list(EMB_GRID))


@query("tune_threshold_doc", _tune_sql("doc", DOC_GRID))
def tune_threshold_doc(spark: SparkSession, sf: str) -> DataFrame:
    return tuning.tune_sets(*load_graph(spark, sf, "doc"), list(DOC_GRID))


def _inconsistency_sql(group: str) -> str:
    return o.query(
        o.GRAPH["doc"], f"grp AS MATERIALIZED (SELECT doc_id AS id, {group} AS g FROM documents)", "trials AS MATERIALIZED (SELECT * FROM (VALUES (0, 's', 15), (1, 's', 15)) v(trial, seed, k))",
        "tpairs AS MATERIALIZED (SELECT 0 AS trial, p.u, p.v FROM pairs p JOIN grp a ON a.id = p.u JOIN grp b ON b.id = p.v WHERE a.g IS NOT DISTINCT FROM b.g UNION ALL SELECT 1, u, v FROM pairs)", o.fold(True), o.costs("exact", "c", True),
        "sz AS (SELECT g, sum(c)::BIGINT AS n, sum(c * (c - 1) // 2)::BIGINT AS together FROM (SELECT grp.g, e.pivot, count(*) AS c FROM exact e JOIN grp USING (id) WHERE e.trial = 0 GROUP BY ALL) GROUP BY g)",
        "ins AS (SELECT grp.g, count(*) AS m, count(*) FILTER (a.pivot = b.pivot) AS kept FROM tpairs p JOIN exact a ON a.trial = 0 AND a.id = p.u JOIN exact b ON b.trial = 0 AND b.id = p.v JOIN grp ON grp.id = p.u WHERE p.trial = 0 GROUP BY grp.g)",
        f"SELECT g AS {group}, n, cost, round(cost / nullif(n * (n - 1) // 2, 0), 9) AS share FROM (SELECT sz.g, sz.n, coalesce(m, 0) + together - 2 * coalesce(kept, 0) AS cost FROM sz LEFT JOIN ins ON sz.g IS NOT DISTINCT FROM ins.g UNION ALL SELECT NULL, n, cost FROM c WHERE trial = 1)",
    )


for group in ("lang", "source"):

    def _inconsistent(spark: SparkSession, sf: str, group: str = group) -> DataFrame:
        _, pairs = nodes_and_pairs(spark, sf, "doc")
        return tuning.inconsistency(table(spark, sf, "documents").select(F.col("doc_id").alias("id"), group), pairs, group)

    query(f"inconsistency_by_{group}", _inconsistency_sql(group))(_inconsistent)

BITS = "bits AS MATERIALIZED (SELECT row_number() OVER (ORDER BY doc_id) AS i, quality AS bit, toxic AS bit2 FROM labels)"


def _bits(spark: SparkSession, sf: str) -> DataFrame:
    """Label bits numbered by id: the gadget is a small instance, so one sorted task numbers it."""
    rows = table(spark, sf, "labels").select(F.col("doc_id").alias("id"), "quality", "toxic")
    return rows.select(F.row_number().over(Window.orderBy("id")).alias("i"), F.col("quality").alias("bit"), F.col("toxic").alias("bit2"))


GADGET_PLACES = (1, 2, 3, 5, 8, 13)


@query(
    "index_gadget_labels",
    f"WITH {BITS} SELECT b, (SELECT bit FROM bits WHERE i = b) AS bit, 2 * (SELECT count(*) FROM bits) AS n, CASE WHEN (SELECT bit FROM bits WHERE i = b) = 1 THEN 0 ELSE (SELECT count(*) FROM bits) - 1 END::BIGINT AS true_opt, CASE WHEN (SELECT bit FROM bits WHERE i = b) = 1 THEN 0 ELSE (SELECT count(*) FROM bits) END::BIGINT AS m FROM (SELECT unnest([{', '.join(map(str, GADGET_PLACES))}])::INTEGER AS b)",
)
def index_gadget_labels(spark: SparkSession, sf: str) -> DataFrame:
    """Optimum and positive pairs of the gadget for a few queried places."""
    bits, out = checkpointed(_bits(spark, sf).select("i", "bit")), None
    for b in GADGET_PLACES:
        m = SparseL1("x").pairs(gadgets.index_gadget(bits, b)).agg(F.count("*").alias("m"))
        row = gadgets.index_optimum(bits, b).crossJoin(m)
        out = row if out is None else out.unionByName(row)
    return out


@query("index_gadget_pivot", f"WITH {BITS} SELECT b, CASE WHEN (SELECT bit FROM bits WHERE i = b) = 1 THEN true ELSE NULL END AS zero FROM (SELECT unnest([{', '.join(map(str, GADGET_PLACES))}])::INTEGER AS b)")
def index_gadget_pivot(spark: SparkSession, sf: str) -> DataFrame:
    """Whether pivot costs nothing where the optimum is 0 (null where a star makes it depend on the order)."""
    bits, out = checkpointed(_bits(spark, sf).select("i", "bit")), None
    for b in GADGET_PLACES:
        nodes = gadgets.index_gadget(bits, b)
        pairs = checkpointed(SparseL1("x").pairs(nodes))
        cost = mismatch.clustering_cost(pivot.pivot_cluster(nodes, pairs), pairs).crossJoin(gadgets.index_optimum(bits, b).select("b", "bit"))
        row = cost.select("b", F.when(F.col("bit") == 1, F.col("cost") == 0).alias("zero"))
        out = row if out is None else out.unionByName(row)
    return out


DISJ = """pt AS MATERIALIZED (SELECT i * 4 + o AS id, (2 * i)::DOUBLE AS x, y::DOUBLE AS y FROM (SELECT i, unnest([0, 1, 2, 3]) AS o, unnest([bit, bit - 1, 3 - bit2, 4 - bit2]) AS y FROM bits)),
nodes AS MATERIALIZED (SELECT id FROM pt), pairs AS MATERIALIZED (SELECT a.id AS u, b.id AS v FROM pt a JOIN pt b ON a.id < b.id AND b.id < a.id + 12 AND abs(a.x - b.x) + abs(a.y - b.y) <= 1)"""


@query("disjointness_gadget_labels", o.query(BITS, DISJ, T_ONE, o.fold(), o.costs("exact", "c"), "SELECT c.n, (SELECT count(*) FROM bits WHERE bit = 1 AND bit2 = 1) AS shared, c.cost AS pivot_cost FROM c"))
def disjointness_gadget_labels(spark: SparkSession, sf: str) -> DataFrame:
    bits = checkpointed(_bits(spark, sf))
    nodes = gadgets.disjointness_gadget(bits.select("i", F.col("bit").alias("bx"), F.col("bit2").alias("by")))
    pairs = checkpointed(L1Ball(("x", "y")).pairs(nodes))
    cost = mismatch.clustering_cost(pivot.pivot_cluster(nodes, pairs), pairs)
    return cost.crossJoin(bits.agg(F.count_if((F.col("bit") == 1) & (F.col("bit2") == 1)).alias("shared"))).select("n", "shared", F.col("cost").alias("pivot_cost"))


@query("bound_checks", o.query(EMB, T_ONE, *FULL, o.costs("labels", "cb"), o.costs("exact", "x"), "z AS (SELECT 'budgeted' AS method, cb.cost::DOUBLE AS estimate, x.cost::DOUBLE AS truth FROM cb, x UNION ALL SELECT 'compact', ea.m_a + eb.m_b, cb.cost FROM ea, eb, cb)", "SELECT method, round(estimate, 6) AS estimate, truth, estimate BETWEEN 0.5 * truth - 500 AND 1.5 * truth + 500 AS within, truth <= estimate AND estimate <= 10 * truth + 500 AS cd FROM z"))
def bound_checks(spark: SparkSession, sf: str) -> DataFrame:
    ids, pairs = _counted(spark, sf, "emb")
    trials = checkpointed(_trials(spark, ids, ONE))
    labels = checkpointed(estimator.budgeted_trials(ids, pairs, trials))
    budgeted = mismatch.clustering_cost(labels, pairs).select(F.col("cost").cast("double").alias("b"))
    best = mismatch.clustering_cost(checkpointed(dense.cosine_pivots(pairs.nodes, pairs.similarity)), pairs).select(F.col("cost").cast("double").alias("p"))
    compact = estimator.estimate_trials(ids, pairs, trials, member_labels=labels).select(F.col("estimate").alias("e"))
    row = budgeted.crossJoin(best).crossJoin(compact)
    rows = row.select(F.explode(F.array(F.struct(F.lit("budgeted").alias("method"), F.col("b").alias("estimate"), F.col("p").alias("truth")), F.struct(F.lit("compact").alias("method"), F.col("e").alias("estimate"), F.col("b").alias("truth")))).alias("z")).select("z.*")
    return rows.select("method", R6("estimate").alias("estimate"), "truth", bounds.is_eps_approx(F.col("estimate"), F.col("truth"), 0.5, 500).alias("within"), bounds.is_cd_approx(F.col("estimate"), F.col("truth"), 10, 500).alias("cd"))


TAILS = (0.1, 0.5, 1.0)


@query("tail_bounds", "SELECT o_custkey, eps, mu, t, round(least(1, 2 * exp(-eps * eps * mu * t / 3)), 9) AS chernoff, round(least(1, 2 * exp(-t * eps * eps / (2 * 1 * (mu + eps / 3)))), 9) AS bernstein, 9 + 24 / (15 - 1) AS factor FROM (SELECT o_custkey, count(*) FILTER (o_orderstatus = 'F') / count(*) AS mu, count(*)::DOUBLE AS t FROM orders GROUP BY o_custkey), (VALUES " + ", ".join(f"({x}::DOUBLE)" for x in TAILS) + ") v(eps)")
def tail_bounds(spark: SparkSession, sf: str) -> DataFrame:
    """How far the share of finished orders among a customer's t orders may stray."""
    shares = table(spark, sf, "orders").groupBy("o_custkey").agg((F.count_if(F.col("o_orderstatus") == "F") / F.count("*")).alias("mu"), F.count("*").cast("double").alias("t"))
    rows = shares.select("*", F.explode(F.array(*map(F.lit, TAILS))).alias("eps"))
    return rows.select("o_custkey", "eps", "mu", "t", F.round(bounds.chernoff_tail(F.col("eps"), F.col("mu"), F.col("t")), 9).alias("chernoff"), F.round(bounds.bernstein_tail(F.col("eps"), F.col("mu"), 1.0, F.col("t")), 9).alias("bernstein"), bounds.budgeted_factor(15).alias("factor"))


@query("zero_controls", "SELECT graph, method, 0::DOUBLE AS cost FROM (VALUES ('cust'), ('doc2'), ('page2')) g(graph), (VALUES ('budgeted'), ('compact'), ('pivot')) m(method)")
def zero_controls(spark: SparkSession, sf: str) -> DataFrame:
    out = None
    for g in ("cust", "doc2", "page2"):
        found = sweep(spark, *nodes_and_pairs(spark, sf, g), [(SEED, 5, 0.1)], ("pivot", "budgeted", "compact"))
        row = found.select(F.lit(g).alias("graph"), "method", F.col("value").alias("cost"))
        out = row if out is None else out.unionByName(row)
    return out


@query("same_key_closed_form", "SELECT count(*) AS classes, sum(c)::BIGINT AS n, sum(c * (c - 1) // 2)::BIGINT AS m, 0::BIGINT AS cost FROM (SELECT count(*) AS c FROM customer GROUP BY c_nationkey, c_mktsegment)")
def same_key_closed_form(spark: SparkSession, sf: str) -> DataFrame:
    nodes, similarity = load_graph(spark, sf, "cust")
    assert isinstance(similarity, SameKey)
    return similarity.classes(nodes).agg(F.count("*").alias("classes"), F.sum("size").alias("n"), F.expr("CAST(sum(size * (size - 1) DIV 2) AS BIGINT)").alias("m"), F.lit(0).cast("bigint").alias("cost"))


# --- unbiasedness and ablations: one order, many sample seeds --------------------------------------------


def _draws(spark: SparkSession, ids: DataFrame, pairs: DataFrame, draws: int):
    """Anchored labels of one order, copied to trials that differ in their sample seeds only."""
    n = ids.count()
    base = _trials(spark, ids, FIVE, 50)
    ranked = checkpointed(ranking.ranked_trials(ids, base))
    labels = checkpointed(lookup.anchored_pivot(ranked, checkpointed(lookup.anchors_of(ranked, base)), pairs, base))
    budgeted = checkpointed(estimator.budgeted_trials(ids, pairs, base))
    trials = estimator.trial_table(spark, [(f"d{i}", 5, 0.1, Sizes(50, 50, 50, 25, cutoff_of(n, 50))) for i in range(draws)])
    copy = lambda d: d.drop("trial").crossJoin(F.broadcast(trials.select("trial")))
    return trials, labels, budgeted, checkpointed(copy(labels)), checkpointed(copy(budgeted))


def _spread(found: DataFrame, value: str, truth: DataFrame) -> DataFrame:
    stats = found.agg(F.avg(value).alias("mean"), F.stddev_samp(value).alias("sd"), F.count("*").alias("c"))
    return stats.crossJoin(truth).select("truth", R6("mean").alias("mean"), R6("sd").alias("sd"), R6(F.col("sd") / F.sqrt("c")).alias("se"))


DRAWS = 40


@query("unbiased_residual_emb")
def unbiased_residual_emb(spark: SparkSession, sf: str) -> DataFrame:
    ids, pairs = _counted(spark, sf, "emb")
    trials, labels, budgeted, many, many_budgeted = _draws(spark, ids, pairs, DRAWS)
    truth = mismatch.part_costs(budgeted, labels, pairs).select(F.col("exact_b").alias("truth"))
    return _spread(residual.estimate_residual_part(many, many_budgeted, pairs, trials), "m_b", truth)


@query("unbiased_anchored_emb")
def unbiased_anchored_emb(spark: SparkSession, sf: str) -> DataFrame:
    ids, pairs = nodes_and_pairs(spark, sf, "emb")
    trials, labels, budgeted, many, _ = _draws(spark, ids, pairs, DRAWS)
    truth = mismatch.part_costs(budgeted, labels, pairs).select(F.col("exact_a").alias("truth"))
    return _spread(anchored.estimate_anchored_part(many, pairs, trials), "m_a", truth)


@query("cutoff_ablation_emb")
def cutoff_ablation_emb(spark: SparkSession, sf: str) -> DataFrame:
    """The anchored part under the three modes: mean and SD of its relative error to the exact count."""
    ids, pairs = nodes_and_pairs(spark, sf, "emb3")
    trials, labels, budgeted, many, _ = _draws(spark, ids, pairs, DRAWS)
    truth = checkpointed(mismatch.part_costs(budgeted, labels, pairs).select(F.col("exact_a").alias("truth")))
    out = None
    for mode in ("paper", "floor", "two_sample"):
        error = anchored.estimate_anchored_part(many, pairs, trials, mode).crossJoin(F.broadcast(truth)).withColumn("e", (F.col("m_a") - F.col("truth")) / F.col("truth"))
        row = error.agg(R6(F.avg("e")).alias("mean_err"), R6(F.stddev_samp("e")).alias("sd_err")).select(F.lit(mode).alias("mode"), "*")
        out = row if out is None else out.unionByName(row)
    return out


@query("high_low_ablation")
def high_low_ablation(spark: SparkSession, sf: str) -> DataFrame:
    """Spread of the split estimator and of naive degree sampling on a star: hubs are what the split is for."""
    bits = checkpointed(_bits(spark, sf).select("i", F.lit(0).alias("bit")))
    nodes = gadgets.index_gadget(bits, 3)
    ids, pairs = checkpointed(nodes.select("id")), checkpointed(SparseL1("x").pairs(nodes))
    return _high_low(spark, ids, pairs, 40)


@query("high_low_ablation_part")
def high_low_ablation_part(spark: SparkSession, sf: str) -> DataFrame:
    """The same on parts that meet in at least one order, where a few parts are met by many."""
    nodes, _ = load_graph(spark, sf, "part")
    members = table(spark, sf, "lineitem").select(F.col("l_orderkey").alias("group"), F.col("l_partkey").alias("id"))
    return _high_low(spark, checkpointed(nodes.select("id")), checkpointed(CoOccurrence(members, 1).pairs(nodes)), 40)


def _high_low(spark: SparkSession, ids: DataFrame, pairs: DataFrame, t: int) -> DataFrame:
    n = ids.count()
    trials = checkpointed(estimator.trial_table(spark, [(f"h{i}", 5, 0.5, Sizes(n, t, t, t, cutoff_of(n, t))) for i in range(DRAWS)]))
    one = trials.where("trial = 0")
    ranked = checkpointed(ranking.ranked_trials(ids, one))
    labels = lookup.anchored_pivot(ranked, lookup.anchors_of(ranked, one), pairs, one)
    many = checkpointed(labels.drop("trial").crossJoin(F.broadcast(trials.select("trial"))))
    split = anchored.estimate_anchored_part(many, pairs, trials).select(F.lit("high_low").alias("method"), F.col("m_a").alias("value"))
    naive = baselines.naive_degree(many, pairs, trials).select(F.lit("naive").alias("method"), F.col("estimate").alias("value"))
    return metrics.summary(split.unionByName(naive), "value", "method")


SPLITS = {"even": (1 / 5, 1 / 5, 1 / 5, 1 / 5), "anchors": (7 / 10, 3 / 40, 3 / 40, 3 / 40), "default": (1 / 2, 1 / 8, 1 / 8, 1 / 8)}  # the second share counts twice


@query("split_ablation_emb")
def split_ablation_emb(spark: SparkSession, sf: str) -> DataFrame:
    ids, pairs = nodes_and_pairs(spark, sf, "emb")
    out = None
    for name, split in SPLITS.items():
        row = _errors(sweep(spark, ids, pairs, [(s, 15, 0.1) for s in SEEDS], ("compact",), split), "space").select(F.lit(name).alias("split"), "mean_err", "sd_err")
        out = row if out is None else out.unionByName(row)
    return out


# --- ledgers ----------------------------------------------------------------------------------------------


_DRAWN = "(SELECT (SELECT count(*) FROM ranked JOIN trials USING (trial) WHERE rk <= r) AS a, (SELECT count(*) FROM s1) AS f, (SELECT count(*) FROM s1b) AS g, (SELECT count(*) FROM s2) AS s, (SELECT count(*) FROM sb) AS b, (SELECT count(*) FROM sb) + (SELECT count(*) FROM sb JOIN sym ON sym.x = sb.id) AS w) c"


@query("space_ledger_emb", o.query(*BASE5, o.part_a("two_sample"), o.PART_B, f"SELECT stage, nodes::BIGINT AS nodes, words::BIGINT AS words FROM {_DRAWN}, LATERAL (SELECT stage, nodes, words FROM (VALUES ('anchors', a, a), ('first sample', f, 2 * f), ('first sample again', g, 2 * g), ('second sample', s, 2 * s), ('residual sample', b, b), ('neighbourhoods', w, w), ('walks', 0, 10 * w)) v(stage, nodes, words))"))
def space_ledger_emb(spark: SparkSession, sf: str) -> DataFrame:
    """What an estimate of fifty nodes a sample stores; similarities are evaluated between samples and nodes only."""
    nodes, similarity = load_graph(spark, sf, "emb")
    ids = checkpointed(nodes.select("id"))
    trials = checkpointed(_trials(spark, ids, FIVE, 50))
    ranked = checkpointed(ranking.ranked_trials(ids, trials))
    anchors = checkpointed(lookup.anchors_of(ranked, trials))
    first, again = (checkpointed(sampling.bottom_k_trials(ranked, trials, "t1", salt)) for salt in ("s1", "s1b"))
    near = estimator._sampled_pairs(nodes, similarity, anchors.unionByName(first).unionByName(again).select("id"))
    labels = checkpointed(lookup.anchored_pivot(ranked, anchors, near, trials))
    low = anchored.classify_by_sample(labels, near, trials).where(~F.col("is_high")).select("trial", "id", "pivot")
    centers = checkpointed(residual.sample_centers(labels, trials))
    gamma = residual.neighbourhoods(centers, estimator._sampled_pairs(nodes, similarity, centers))
    return metrics.space_ledger(5, anchors, first, again, sampling.bottom_k_trials(low, trials, "t2", "s2"), centers, gamma)


@query("pass_ledger_emb", "SELECT stage, scan_no, nodes FROM (SELECT stage, scan_no::INTEGER AS scan_no FROM (VALUES ('anchors', 1), ('first sample', 2), ('classification', 3), ('residual sample', 2), ('second sample degrees', 4), ('neighbourhoods', 3), ('outer mismatches', 19)) v(stage, scan_no) UNION ALL SELECT 'walk', i::INTEGER FROM range(4, 19) r(i)), (SELECT count(vec_id) AS nodes FROM embeddings)")
def pass_ledger_emb(spark: SparkSession, sf: str) -> DataFrame:
    return metrics.pass_ledger(table(spark, sf, "embeddings").select(F.col("vec_id").alias("id")), 15)

