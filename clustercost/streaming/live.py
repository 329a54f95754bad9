"""Streaming forms: live anchors and samples, windowed costs, late and repeated rows, stream-static lookups.

A single sublinear pass cannot estimate the cost, so a stream is either kept in bounded windows or
replayed from its log: the live pass gathers anchors and samples, and the later scans are
batch reads of the same frozen files.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..lineage import checkpointed
from ..operators.estimator import estimate_cost
from ..operators.ranking import rank_key
from ..operators.similarity import Similarity
from ..params import budget_sizes

HOUR_US = 3_600_000_000


def table_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """A folder or file of Parquet as a stream.

    A file source wants a folder; a one-character class makes the path a pattern, which may match a file.
    """
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(f"{path[:-1]}[{path[-1]}]")


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """``event_id, ts (timestamp), user_id`` from a folder or file of Parquet."""
    return table_stream(spark, path, files_per_trigger).select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id")


class BottomK:
    """A mergeable sample over a stream: each batch merges with the state and the k smallest keys stay.

    State is written under the batch's number, and a repeated batch starts from the state before
    it, so replays do not change the result.
    """

    def __init__(self, path: str, k: int, salt: str, seed: str, column: str = "event_id"):
        self.path, self.k, self.seed, self.column = path, k, f"{salt}:{seed}" if salt else seed, column

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        rows = batch.select(F.col(self.column).alias("id")).withColumn("key", rank_key(self.seed))
        before = self.state(batch.sparkSession, batch_id - 1)
        if before is not None:
            rows = rows.unionByName(before)
        rows.distinct().orderBy("key", "id").limit(self.k).write.mode("overwrite").parquet(f"{self.path}/batch={batch_id}")

    def state(self, spark: SparkSession, batch_id: int) -> DataFrame | None:
        """The newest state at or before a batch."""
        from py4j.protocol import Py4JJavaError
        from pyspark.errors import AnalysisException

        for number in range(batch_id, -1, -1):
            try:
                return spark.read.schema("id bigint, key string").parquet(f"{self.path}/batch={number}")
            except (AnalysisException, Py4JJavaError):
                continue
        return None


def run_to_end(stream: DataFrame, sink, checkpoint: str, mode: str = "append") -> int:
    """Run what is available through ``foreachBatch``; returns the last batch's number."""
    query = stream.writeStream.outputMode(mode).foreachBatch(sink).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    progress = query.lastProgress
    return progress["batchId"] if progress else -1


def replayed_estimate(log: DataFrame, nodes: DataFrame, similarity: Similarity, at: str, n: int, k: int = 15, budget: float = 0.04, seed: str = "s") -> DataFrame:
    """The compact estimate of a stream: one live pass, then replays of the log that the stream has kept.

    ``log`` streams the nodes' ``id``; the live pass keeps only the anchors and both first samples, sized for an expected
    ``n``.  ``nodes`` reads the same frozen files as a table: every later scan of the estimate replays them.  A single pass
    alone cannot do, whatever it keeps in sublinear space.  The result equals the estimate of the table.
    """
    sizes = budget_sizes(n, budget)
    sinks = [BottomK(f"{at}/{name}", size, salt, seed, "id") for name, size, salt in (("anchors", sizes.r, ""), ("first", sizes.t1, "s1"), ("again", sizes.t1, "s1b"))]

    def gather(batch: DataFrame, batch_id: int) -> None:
        batch = batch.persist()
        for sink in sinks:
            sink(batch, batch_id)
        batch.unpersist()

    last = max(run_to_end(log, gather, f"{at}/offsets"), 0)
    spark = nodes.sparkSession
    kept = [checkpointed(sink.state(spark, last).select(F.lit(0).alias("trial"), "id", "key")) for sink in sinks]
    return estimate_cost(nodes, similarity, k=k, budget=budget, seed=seed, gathered=(kept[0], kept[1].unionByName(kept[2])))


def collected(stream: DataFrame, path: str, checkpoint: str) -> DataFrame:
    """What a finished append-mode stream wrote, as a batch table."""
    query = stream.writeStream.outputMode("append").format("parquet").option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(path)


def pivot_cost_of(users: list[int], times: list[int], ids: list[int], gap: int = HOUR_US, seed: str = "s") -> tuple[int, int]:
    """(nodes, pivot cost) of one window's events, similar for one user within the gap.

    A user's pivots lie more than the gap apart, so at most two are near an event: each is found by bisection.
    Similar pairs are counted over sorted times, in all and inside each cluster; no pairs are listed.
    """
    import hashlib
    from bisect import bisect_left, insort

    def near_pairs(sorted_times: list[int]) -> int:
        return sum(j - bisect_left(sorted_times, t - gap, 0, j) for j, t in enumerate(sorted_times))

    key = [(hashlib.md5(f"{seed}:{i}".encode()).hexdigest(), i) for i in ids]
    pivots: dict[int, list[tuple[int, int]]] = {}  # by user: (time, place in the order)
    clusters: dict[tuple[int, int], list[int]] = {}
    by_user: dict[int, list[int]] = {}
    for place, i in enumerate(sorted(range(len(ids)), key=key.__getitem__)):
        user, t = users[i], times[i]
        mine = pivots.setdefault(user, [])
        first = bisect_left(mine, (t - gap, -1))
        found = min((p for s, p in mine[first : first + 2] if s <= t + gap), default=None)
        if found is None:
            found = place
            insort(mine, (t, place))
        clusters.setdefault((user, found), []).append(t)
        by_user.setdefault(user, []).append(t)
    similar = sum(near_pairs(sorted(x)) for x in by_user.values())
    together = sum(len(x) * (len(x) - 1) // 2 for x in clusters.values())
    kept = sum(near_pairs(sorted(x)) for x in clusters.values())
    return len(ids), similar + together - 2 * kept


def _costs(gap: int):
    @F.pandas_udf("struct<n:bigint,cost:bigint>")
    def costs(user: pd.Series, rows: pd.Series) -> pd.DataFrame:
        out = [pivot_cost_of([u] * len(r), [x["t"] for x in r], [x["i"] for x in r], gap) for u, r in zip(user, rows, strict=True)]
        return pd.DataFrame(out, columns=["n", "cost"])

    return costs("user_id", "rows")


def _gathered():
    return F.collect_list(F.struct(F.unix_micros("ts").alias("t"), F.col("event_id").alias("i"))).alias("rows")


def window_cost(events: DataFrame, width: str = "1 day", slide: str | None = None, watermark: str = "1 hour", gap: int = HOUR_US) -> DataFrame:
    """Exact pivot cost in each closed tumbling (or sliding) window: ``start, n, cost``.

    Works on streams (append mode, after the watermark) and on tables; a window's events gather by
    user first, and costs of users add up, since only events of one user can be similar.
    """
    marked = events.withWatermark("ts", watermark) if events.isStreaming else events
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    gathered = marked.groupBy(w.alias("w"), "user_id").agg(_gathered())
    return gathered.select(F.col("w.start").alias("start"), _costs(gap).alias("c")).select("start", "c.n", "c.cost")


def session_cost(events: DataFrame, gap: str = "1 hour", watermark: str = "1 hour", gap_us: int = HOUR_US) -> DataFrame:
    """``user_id, start, n, cost``: sessions of a user, the connected runs of the range graph at that gap, each with its exact pivot cost."""
    marked = events.withWatermark("ts", watermark) if events.isStreaming else events
    gathered = marked.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(_gathered())
    return gathered.select("user_id", F.col("w.start").alias("start"), _costs(gap_us).alias("c")).select("user_id", "start", "c.n", "c.cost")


def deduplicated(events: DataFrame, watermark: str = "1 hour") -> DataFrame:
    """Events with repeated ids dropped while the watermark remembers them."""
    if not events.isStreaming:
        return events.dropDuplicates(["event_id"])
    return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def anchored_lookup(events: DataFrame, anchors: DataFrame, gap: int = HOUR_US) -> DataFrame:
    """Stream-static lookup: for each event its earliest-ranked similar anchor pivot, or null.

    ``anchors(id, key, user_id, at)`` are settled pivots; each row folds its user's anchors in order.
    """
    lists = anchors.groupBy("user_id").agg(F.sort_array(F.collect_list(F.struct("key", "id", "at"))).alias("list"))
    at = F.unix_micros("ts")
    met = events.join(lists, "user_id", "left")
    mine = F.struct(rank_key("s", "event_id"), F.col("event_id"))
    near = F.filter(F.coalesce("list", F.array().cast("array<struct<key:string,id:bigint,at:bigint>>")), lambda a: (F.abs(a["at"] - at) <= gap) & (F.struct(a["key"], a["id"]) <= mine))
    return met.select("event_id", F.try_element_at(near, F.lit(1))["id"].alias("pivot"))


def assign_labels(events: DataFrame, gap: int = HOUR_US, watermark: str = "1 hour") -> DataFrame:
    """Stateful labels by user: keep each user's pivots, assign each arriving event or open a cluster.

    Arrival order stands in for the random order, so this is pivot clustering only where arrival
    is random.  Pivots two gaps older than a user's newest event are forgotten, and a user's whole state goes when
    the watermark passes that time.
    """
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        pivots = list(zip(*state.get, strict=True)) if state.exists else []
        newest = max((t for _, t in pivots), default=0)
        for rows in batches:
            out = []
            for i, t in sorted(zip(rows["event_id"], rows["at"], strict=True), key=lambda x: (x[1], x[0])):
                found = next((p for p, s in pivots if abs(s - t) <= gap), None)
                if found is None:
                    pivots.append((int(i), int(t)))
                    found = int(i)
                out.append((int(i), found))
            newest = max(newest, int(rows["at"].max())) if len(rows) else newest
            pivots = [x for x in pivots if x[1] >= newest - 2 * gap]
            yield pd.DataFrame(out, columns=["event_id", "pivot"])
        state.update(([p for p, _ in pivots], [s for _, s in pivots]))
        state.setTimeoutTimestamp(max((newest + 2 * gap) // 1000, state.getCurrentWatermarkMs() + 1))

    rows = events.withWatermark("ts", watermark).withColumn("at", F.unix_micros("ts"))
    return rows.groupBy("user_id").applyInPandasWithState(step, "event_id bigint, pivot bigint", "pivots array<bigint>, times array<bigint>", "append", GroupStateTimeout.EventTimeTimeout)
