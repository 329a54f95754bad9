"""Streams give what tables give, however they are cut; late and repeated rows."""

import hashlib
import itertools
import random

import pytest
from pyspark.sql import functions as F

from clustercost.operators.estimator import estimate_cost
from clustercost.operators.ranking import rank_key
from clustercost.sources.graphs import load_graph
from clustercost.streaming import live


@pytest.mark.parametrize("files", [1, 3, 10])
def test_anchors_do_not_depend_on_batches(spark, sf, tmp_path, files):
    events = spark.read.parquet(f"{sf}/events.parquet")
    events.repartition(files).write.parquet(str(tmp_path / "events"))
    sink = live.BottomK(str(tmp_path / "state"), 40, "s1", "s")
    last = live.run_to_end(live.event_stream(spark, str(tmp_path / "events")), sink, str(tmp_path / "offsets"))
    want = events.select(F.col("event_id").alias("id")).withColumn("key", rank_key("s1:s")).orderBy("key", "id").limit(40)
    assert sorted(sink.state(spark, last).collect()) == sorted(want.collect())


def test_window_cost_is_the_brute_force_count():
    users, times, ids = [1, 1, 1, 2, 2], [0, 50, 100, 0, 10], [5, 6, 7, 8, 9]
    for seed in ("a", "b", "c"):
        n, cost = live.pivot_cost_of(users, times, ids, gap=60, seed=seed)
        assert n == 5 and cost == 1  # a path of three costs one in any order, a pair nothing


def test_windows_on_a_table_count_all(spark, sf):
    events = spark.read.parquet(f"{sf}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id")
    assert live.window_cost(events).agg(F.sum("n")).first()[0] == events.count()
    assert live.session_cost(events).agg(F.sum("n")).first()[0] == events.count()
    rows = events.collect()
    per_day = {}
    for r in rows:
        per_day.setdefault((r["ts"].date(), r["user_id"]), []).append(r)
    near = sum(abs((a["ts"] - b["ts"]).total_seconds()) <= 3600 for g in per_day.values() for a, b in itertools.combinations(g, 2))
    assert live.window_cost(events).agg(F.sum("cost")).first()[0] <= near


def test_late_and_repeated_rows(spark, sf, tmp_path):
    events = spark.read.parquet(f"{sf}/events.parquet").orderBy("ts").limit(400)
    twice = events.unionByName(events.where("event_id % 20 = 0"))
    twice.coalesce(1).write.parquet(str(tmp_path / "events"))
    out = live.collected(live.deduplicated(live.event_stream(spark, str(tmp_path / "events"))), str(tmp_path / "out"), str(tmp_path / "offsets"))
    assert out.count() == out.select("event_id").distinct().count() == 400


@pytest.mark.parametrize("seed", ["a", "b", "c"])
def test_pivot_cost_without_listing_pairs(seed):
    rng = random.Random(seed)
    ids = list(range(120))
    users, times = [rng.randrange(4) for _ in ids], [rng.randrange(900) for _ in ids]
    gap = 40
    near = lambda a, b: users[a] == users[b] and abs(times[a] - times[b]) <= gap
    pivot = {}
    for i in sorted(ids, key=lambda i: (hashlib.md5(f"{seed}:{i}".encode()).hexdigest(), i)):
        pivot[i] = next((p for p in pivot if pivot[p] == p and near(p, i)), i)
    cost = sum((pivot[a] == pivot[b]) != near(a, b) for a, b in itertools.combinations(ids, 2))
    assert live.pivot_cost_of(users, times, ids, gap, seed) == (120, cost)


def test_sessions_and_whole_table_cost_the_same(spark, sf):
    """No similar pair crosses a session, so costs of sessions add up to the cost of everything."""
    events = spark.read.parquet(f"{sf}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"), F.lit(1).alias("user_id"))
    rows = [(r["event_id"], int(r["ts"].timestamp() * 1_000_000 + 0.5)) for r in events.collect()]
    whole = live.pivot_cost_of([1] * len(rows), [t for _, t in rows], [i for i, _ in rows])
    assert tuple(live.session_cost(events).agg(F.sum("n"), F.sum("cost")).first()) == whole


def test_replays_give_the_estimate_of_the_table(spark, sf, tmp_path):
    nodes, similarity = load_graph(spark, sf, "evt")
    nodes.repartition(3).write.parquet(str(tmp_path / "log"))
    log = live.table_stream(spark, str(tmp_path / "log"))
    kept = spark.read.parquet(str(tmp_path / "log"))
    assert live.replayed_estimate(log, kept, similarity, str(tmp_path / "at"), nodes.count(), k=2).collect() == estimate_cost(nodes, similarity, k=2).collect()


def test_labels_survive_state_that_expires(spark, sf, tmp_path):
    """Files in order of time: users time out between batches, and every event still has one label within the gap."""
    events = spark.read.parquet(f"{sf}/events.parquet")
    for day in range(3):
        events.where(F.dayofmonth("ts") == 1 + 10 * day).coalesce(1).write.mode("append").parquet(str(tmp_path / "events"))
    out = live.collected(live.assign_labels(live.event_stream(spark, str(tmp_path / "events"))), str(tmp_path / "out"), str(tmp_path / "offsets"))
    kept = spark.read.parquet(str(tmp_path / "events")).select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("at"))
    met = out.join(kept, "event_id").join(kept.select(F.col("event_id").alias("pivot"), F.col("user_id").alias("pu"), F.col("at").alias("pt")), "pivot")
    assert out.count() == met.count() == kept.count()
    assert met.where((F.col("user_id") != F.col("pu")) | (F.abs(F.col("at") - F.col("pt")) > live.HOUR_US)).isEmpty()
