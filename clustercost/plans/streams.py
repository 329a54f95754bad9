"""Streaming queries and functions as catalogue entries; each equals its batch form in SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.registered import bottom_k_agg, cosine_sim, register_all
from ..operators import classes, graph
from ..operators.ranking import rank_key
from ..sources import gadget_source
from ..sources.graphs import load_graph, table
from ..streaming import live
from . import oracle as o
from .methods import ORACLES as METHOD_ORACLES
from .surface import _shared

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
AT = "%Y-%m-%d %H:%M:%S"


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def _stamp(c: str = "start"):
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss").alias(c)


def _stream(spark: SparkSession, sf: str) -> DataFrame:
    return live.event_stream(spark, f"{sf}/events.parquet")


def _sampled(spark: SparkSession, sf: str, k: int, salt: str) -> DataFrame:
    at = _shared(spark)
    sink = live.BottomK(f"{at}/state", k, salt, "s")
    last = live.run_to_end(_stream(spark, sf), sink, f"{at}/offsets")
    return sink.state(spark, max(last, 0)).select("id", "key")


@query("stream_anchors_events", "SELECT event_id AS id, md5('s:' || event_id) AS key FROM events ORDER BY 2, 1 LIMIT 100")
def _(spark, sf):
    return _sampled(spark, sf, 100, "")


@query("stream_reservoir_events", "SELECT event_id AS id, md5('s1:s:' || event_id) AS key FROM events ORDER BY 2, 1 LIMIT 100")
def _(spark, sf):
    return _sampled(spark, sf, 100, "s1")


_CLOSED = "closed AS (SELECT max(ts) - INTERVAL 1 HOUR AS mark FROM events)"


@query("stream_window_counts_events", f"WITH {_CLOSED} SELECT strftime(time_bucket(INTERVAL 1 DAY, ts), '{AT}') AS start, count(*) AS n FROM events, closed WHERE time_bucket(INTERVAL 1 DAY, ts) + INTERVAL 1 DAY <= mark GROUP BY 1")
def _(spark, sf):
    at = _shared(spark)
    done = live.collected(live.window_cost(_stream(spark, sf)), f"{at}/out", f"{at}/offsets")
    return done.groupBy(_stamp()).agg(F.sum("n").alias("n"))


def _mismatches(cell: str) -> str:
    """SQL for ``wrong(user_id, cell, ts)``: an entry for each mismatched pair of one user's events in a cell, by a fold in rank order."""
    same = "b.user_id = a.user_id AND b.cell = a.cell AND b.rk < a.rk"
    near = "abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 3600000000"
    return f"""r AS MATERIALIZED (SELECT user_id, event_id AS id, ts, {cell} AS cell, row_number() OVER (PARTITION BY user_id, {cell} ORDER BY md5('s:' || event_id), event_id) AS rk FROM events),
ahead AS MATERIALIZED (SELECT a.user_id, a.cell, a.rk, list(b.rk ORDER BY b.rk) FILTER ({near}) AS l FROM r a LEFT JOIN r b ON {same} GROUP BY ALL),
fold AS (SELECT DISTINCT user_id, cell, 0::BIGINT AS i, []::BIGINT[] AS piv FROM r
         UNION ALL SELECT f.user_id, f.cell, f.i + 1, list_append(f.piv, coalesce(list_filter(coalesce(s.l, []), lambda j: f.piv[j] = j)[1], f.i + 1)) FROM fold f JOIN ahead s ON s.user_id = f.user_id AND s.cell = f.cell AND s.rk = f.i + 1),
done AS MATERIALIZED (SELECT user_id, cell, arg_max(piv, i) AS piv FROM fold GROUP BY ALL),
labelled AS MATERIALIZED (SELECT r.*, d.piv[r.rk] AS pivot FROM r JOIN done d USING (user_id, cell)),
wrong AS MATERIALIZED (SELECT a.user_id, a.cell, a.ts FROM labelled a JOIN labelled b ON {same} WHERE ({near}) = (a.pivot <> b.pivot))"""


_DAY = "time_bucket(INTERVAL 1 DAY, ts)"


@query("stream_window_cost_events", f"WITH RECURSIVE {_CLOSED}, {_mismatches(_DAY)}, c AS (SELECT cell, count(*) AS cost FROM wrong GROUP BY cell) SELECT strftime(n.cell, '{AT}') AS start, n.n, coalesce(c.cost, 0)::BIGINT AS cost FROM (SELECT cell, count(*) AS n FROM r GROUP BY cell) n LEFT JOIN c USING (cell), closed WHERE n.cell + INTERVAL 1 DAY <= mark")
def _(spark, sf):
    at = _shared(spark)
    done = live.collected(live.window_cost(_stream(spark, sf)), f"{at}/out", f"{at}/offsets")
    return done.groupBy(_stamp()).agg(F.sum("n").alias("n"), F.sum("cost").alias("cost"))


@query("stream_sliding_counts_events", f"WITH {_CLOSED} SELECT strftime(s, '{AT}') AS start, count(*) AS n FROM (SELECT ts, unnest([time_bucket(INTERVAL 6 HOUR, ts), time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 6 HOUR, time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 12 HOUR, time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 18 HOUR]) AS s FROM events), closed WHERE s + INTERVAL 1 DAY <= mark GROUP BY 1")
def _(spark, sf):
    at = _shared(spark)
    done = live.collected(live.window_cost(_stream(spark, sf), "1 day", "6 hours"), f"{at}/out", f"{at}/offsets")
    return done.groupBy(_stamp()).agg(F.sum("n").alias("n"))


_SESSIONS = "g AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS run FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= INTERVAL 1 HOUR THEN 0 ELSE 1 END AS fresh FROM events)), s AS (SELECT user_id, min(ts) AS s, max(ts) AS last, count(*) AS n FROM g GROUP BY user_id, run)"


@query("stream_session_cost_events", f"WITH RECURSIVE {_CLOSED}, {_SESSIONS}, {_mismatches('0')} SELECT s.user_id, strftime(s.s, '{AT}') AS start, any_value(s.n) AS n, count(w.ts) AS cost FROM s JOIN closed ON s.last + INTERVAL 1 HOUR <= mark LEFT JOIN wrong w ON w.user_id = s.user_id AND w.ts BETWEEN s.s AND s.last GROUP BY s.user_id, s.s")
def _(spark, sf):
    at = _shared(spark)
    done = live.collected(live.session_cost(_stream(spark, sf)), f"{at}/out", f"{at}/offsets")
    return done.select("user_id", _stamp(), "n", "cost")


@query("stream_replayed_estimate_emb", METHOD_ORACLES["estimate_cost_emb_on_demand"])
def _(spark, sf):
    """Anchors and first samples from one live pass over the vectors, everything else by replays of the kept files."""
    nodes, similarity = load_graph(spark, sf, "emb")
    log = live.table_stream(spark, f"{sf}/embeddings.parquet").select(F.col("vec_id").alias("id"))
    out = live.replayed_estimate(log, nodes, similarity, _shared(spark), nodes.count())
    return out.select(*[F.round(c, 6).alias(c) for c in ("estimate", "m_a", "m_b")], "passes")


@query("stream_deduplicated_events", "SELECT event_id FROM events")
def _(spark, sf):
    """Every event arrives twice in one batch; one copy of each goes on."""
    at = _shared(spark)
    twice = _stream(spark, sf)
    twice = twice.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    return live.collected(live.deduplicated(twice).select("event_id"), f"{at}/out", f"{at}/offsets")


@query("stream_late_events", "SELECT count(*) AS n FROM events")
def _(spark, sf):
    """Rows of the stream that an hour's watermark admits; the table holds no late ones within its only file."""
    at = _shared(spark)
    return live.collected(_stream(spark, sf).withWatermark("ts", "1 hour").select("event_id"), f"{at}/out", f"{at}/offsets").agg(F.count("*").alias("n"))


@query("stream_static_lookup_events", "WITH a AS (SELECT event_id AS id, md5('s:' || event_id) AS key, user_id, ts FROM events ORDER BY 2, 1 LIMIT 500) SELECT e.event_id, coalesce((SELECT min_by(a.id, (a.key, a.id)) FROM a WHERE a.user_id = e.user_id AND abs(epoch_us(a.ts) - epoch_us(e.ts)) <= 3600000000 AND (a.key, a.id) <= (md5('s:' || e.event_id), e.event_id)), -1) AS pivot FROM events e")
def _(spark, sf):
    at = _shared(spark)
    static = table(spark, sf, "events").select(F.col("event_id").alias("id"), rank_key("s", "event_id").alias("key"), "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("at")).orderBy("key", "id").limit(500)
    met = live.anchored_lookup(_stream(spark, sf), static)
    return live.collected(met, f"{at}/out", f"{at}/offsets").select("event_id", F.coalesce("pivot", F.lit(-1)).alias("pivot"))


@query("stream_stateful_labels_events", "SELECT event_id FROM events")
def _(spark, sf):
    """Every event gets exactly one label; which one depends on arrival."""
    at = _shared(spark)
    return live.collected(live.assign_labels(_stream(spark, sf)), f"{at}/out", f"{at}/offsets").select("event_id")


# functions


@query("udf_cosine", "WITH e AS (SELECT vec_id AS id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings) SELECT a.id, round(list_cosine_similarity(a.e, b.e), 9) AS score FROM e a JOIN e b ON b.id = a.id + 1")
def _(spark, sf):
    e = table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), "embedding")
    after = e.select((F.col("id") - 1).alias("id"), F.col("embedding").alias("other"))
    return e.join(after, "id").select("id", F.round(cosine_sim("embedding", "other"), 9).alias("score"))


@query("udaf_bottom_k", "SELECT label, array_to_string(list_slice(list(vec_id ORDER BY md5('s:' || vec_id), vec_id), 1, 3), ',') AS first FROM embeddings GROUP BY label")
def _(spark, sf):
    e = table(spark, sf, "embeddings").select("label", F.col("vec_id").alias("id")).withColumn("key", rank_key("s"))
    return e.groupBy("label").agg(bottom_k_agg("id", "key", F.lit(3)).alias("ids")).select("label", F.array_join("ids", ",").alias("first"))


@query("udtf_estimate", o.query(o.GRAPH["page"], o.trials([("s", 15, 0.04)]), o.fold(), o.costs("exact", "c"), "SELECT n, cost FROM c"))
def _(spark, sf):
    """A row for each class of pages with the same targets, and for each page without any."""
    register_all(spark)
    found = classes.classes_of(*load_graph(spark, sf, "page"))
    near = graph.both_ways(found.pairs).groupBy("id").agg(F.collect_list("near").alias("near"))
    alone = found.ids.join(found.members.select("id"), "id", "left_anti").withColumn("size", F.lit(1).cast("bigint"))
    rows = found.sizes().withColumnRenamed("class", "id").unionByName(alone).withColumn("key", rank_key("s")).join(near, "id", "left")
    return spark.sql("SELECT * FROM estimate_clusters(TABLE(SELECT id, key, near, size FROM {rows}) WITH SINGLE PARTITION)", rows=rows)


@query("udtf_index_gadget", "WITH b AS (SELECT doc_id - doc_id % 100 AS block, quality AS bit, row_number() OVER w AS i, count(*) OVER (PARTITION BY doc_id - doc_id % 100) AS l FROM labels WINDOW w AS (PARTITION BY doc_id - doc_id % 100 ORDER BY doc_id, quality)) SELECT block, i AS id, 'bit' AS kind, (4 * i + bit)::DOUBLE AS place, 0 AS axis FROM b UNION ALL SELECT block, l + i, 'query', 8.0, i::INTEGER FROM b")
def _(spark, sf):
    """A gadget for the quality bits of each hundred ids, queried at the second."""
    register_all(spark)
    block = (F.col("doc_id") - F.col("doc_id") % 100).alias("block")
    held = table(spark, sf, "labels").groupBy(block).agg(F.sort_array(F.collect_list(F.struct("doc_id", "quality")))["quality"].alias("bits"))
    return spark.sql("SELECT block, g.id, g.kind, g.place, coalesce(g.axis, 0) AS axis FROM {held}, LATERAL index_gadget(bits, 2) g", held=held)


_POINTS = "SELECT (i * 4 + o)::BIGINT AS id, h::DOUBLE AS y FROM (SELECT i, unnest([0, 1, 2, 3]) AS o, unnest([x, x - 1, 3 - y, 4 - y]) AS h FROM b)"


@query("gadget_source", f"WITH l AS (SELECT doc_id, (quality = 1 AND quality IS NOT NULL)::INT AS x, (toxic = 1 AND toxic IS NOT NULL)::INT AS y FROM labels), b AS (SELECT row_number() OVER (ORDER BY doc_id, x, y) AS i, x, y FROM l) {_POINTS}")
def _(spark, sf):
    """The source's options hold the bits of all labels, a character each, in the order of the ids."""
    gadget_source.register(spark)
    bit = lambda c: F.when(F.col(c) == 1, "1").otherwise("0")
    rows = F.sort_array(F.collect_list(F.struct("doc_id", bit("quality").alias("x"), bit("toxic").alias("y"))))
    x, y = table(spark, sf, "labels").agg(rows.alias("l")).select(F.array_join("l.x", ""), F.array_join("l.y", "")).first()
    return spark.read.format("disjointness_gadget").option("x", x).option("y", y).load().select("id", "y")


@query("sql_surface", "SELECT vec_id AS id, md5('s:' || vec_id) AS key, vec_id % 3 <> vec_id % 5 AS cut, 9 + 24 / 14 AS factor FROM embeddings")
def _(spark, sf):
    register_all(spark)
    return spark.sql("SELECT vec_id AS id, cc_rank_key('s', vec_id) AS key, cc_is_mismatch(vec_id % 3, vec_id % 5, true) AS cut, cc_budget_factor(15) AS factor FROM {e}", e=table(spark, sf, "embeddings"))
