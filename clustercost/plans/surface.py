"""Queries of the surrounding operators, each with its SQL: what a user of the methods needs around them."""

from __future__ import annotations

import tempfile
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..lineage import checkpointed
from ..operators import classes, dense, graph, pivot, ranking, sampling
from ..operators.mismatch import is_anchored_mismatch
from ..operators.ranking import rank_key
from ..operators.similarity import NearInKey, cosine, sparse_l1
from ..sources.files import read_pairs, write_pairs
from ..sources.graphs import hrefs, load_graph, nodes_and_pairs, shingles, table
from . import oracle as o

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
KEY = "md5('s:' || vec_id)"
EMB = o.GRAPH["emb"]
PAGE = o.GRAPH["page"]
T_ONE = o.trials([("s", 15, 0.04)])


def op(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[f"op_{name}"] = f
        if sql:
            ORACLES[f"op_{name}"] = sql
        return f

    return add


def _emb(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"))


def _keys(spark: SparkSession, sf: str) -> DataFrame:
    return _emb(spark, sf).withColumn("key", rank_key("s"))


def _shared(spark: SparkSession) -> str:
    """A folder that all executors see, for round trips: beside the checkpoints."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if spark.sparkContext.master.split("[")[0] != "local":
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        base = tempfile.mkdtemp(prefix="shared-")
    return f"{base}/roundtrip-{spark.sparkContext.applicationId}-{spark.range(1).select(F.expr('uuid()')).first()[0]}"


# scans


@op("scan_pruned", "SELECT vec_id AS id FROM embeddings")
def _(spark, sf):
    return _emb(spark, sf)


_CLASSES = """sets AS MATERIALIZED (SELECT id, list(t ORDER BY t) AS t FROM target GROUP BY id), named AS MATERIALIZED (SELECT t, min(id) AS rep FROM sets GROUP BY t)"""


@op("scan_csv_json", o.query(PAGE, _CLASSES, "SELECT 'pair' AS kind, u, v, 2::BIGINT AS copies FROM pairs WHERE u IN (SELECT rep FROM named) AND v IN (SELECT rep FROM named) UNION ALL SELECT 'member', rep, id, 2 FROM sets JOIN named USING (t)"))
def _(spark, sf):
    """Pairs between the first pages of each set of targets, and the membership of all others, as CSV and as JSON lines."""
    nodes, similarity = load_graph(spark, sf, "page")
    found, at, out = classes.classes_of(nodes, similarity, first=F.col("id")), _shared(spark), None
    for kind, rows in (("pair", found.pairs), ("member", found.members.select(F.col("class").alias("u"), F.col("id").alias("v")))):
        for form in ("csv", "json"):
            write_pairs(rows, f"{at}/{form}/{kind}", form)
            back = read_pairs(spark, f"{at}/{form}/{kind}", form).select(F.lit(kind).alias("kind"), "u", "v")
            out = back if out is None else out.unionByName(back)
    return out.groupBy("kind", "u", "v").agg(F.count("*").alias("copies"))


@op("scan_partitioned", o.query(PAGE, "SELECT u, v FROM pairs WHERE u % 8 = 3"))
def _(spark, sf):
    _, pairs = nodes_and_pairs(spark, sf, "page")
    at = _shared(spark)
    write_pairs(pairs, at, "parquet", buckets=8)
    return spark.read.parquet(at).where("bucket = 3").select("u", "v")


# filters and projections


@op("filter_theta", o.query(EMB, "SELECT u, v, round(score, 9) AS score FROM scored WHERE score > 0.4"))
def _(spark, sf):
    nodes, similarity = load_graph(spark, sf, "emb")
    return similarity.scored(nodes).where("score > 0.4").select("u", "v", F.round("score", 9).alias("score"))


@op("filter_nullsafe", "WITH d AS (SELECT doc_id, CASE WHEN doc_id % 3 = 0 THEN NULL ELSE lang END AS a, CASE WHEN doc_id % 2 = 0 THEN NULL ELSE lang END AS b FROM documents) SELECT doc_id FROM d WHERE a IS NOT DISTINCT FROM b")
def _(spark, sf):
    d = table(spark, sf, "documents").select("doc_id", F.when(F.col("doc_id") % 3 != 0, F.col("lang")).alias("a"), F.when(F.col("doc_id") % 2 != 0, F.col("lang")).alias("b"))
    return d.where(F.col("a").eqNullSafe(F.col("b"))).select("doc_id")


@op("filter_in_between", "SELECT doc_id FROM documents WHERE lang IN ('en', 'fr') AND n_chars BETWEEN 200 AND 2000")
def _(spark, sf):
    return table(spark, sf, "documents").where(F.col("lang").isin("en", "fr") & F.col("n_chars").between(200, 2000)).select("doc_id")


@op("filter_like", "SELECT page_id, url FROM pages WHERE url LIKE 'https%' AND regexp_matches(url, '/(en|fr)/')")
def _(spark, sf):
    return table(spark, sf, "pages").where(F.col("url").like("https%") & F.col("url").rlike("/(en|fr)/")).select("page_id", "url")


@op("project_case", "SELECT doc_id, CASE WHEN quality = 1 AND toxic = 1 THEN false WHEN quality = 1 OR toxic = 1 THEN doc_id % 2 = 0 WHEN doc_id % 2 = 0 THEN doc_id % 3 <> doc_id % 5 ELSE doc_id % 3 = doc_id % 5 END AS miss FROM labels")
def _(spark, sf):
    a = F.when(F.col("quality") != 1, F.col("doc_id") % 3)
    b = F.when(F.col("toxic") != 1, F.col("doc_id") % 5)
    return table(spark, sf, "labels").select("doc_id", is_anchored_mismatch(a, b, F.col("doc_id") % 2 == 0).alias("miss"))


# joins


@op("join_broadcast", f"WITH a AS (SELECT vec_id AS id FROM embeddings ORDER BY {KEY}, vec_id LIMIT 50) SELECT e.vec_id AS id, e.label FROM embeddings e JOIN a ON a.id = e.vec_id")
def _(spark, sf):
    anchors = sampling.bottom_k(_emb(spark, sf), 50, "", "s")
    return table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), "label").join(F.broadcast(anchors.select("id")), "id")


def _ends(spark: SparkSession, sf: str, hint: str) -> DataFrame:
    """Keys meet the nodes by the hinted join before the nodes meet each other, so that no pair crosses a shuffle."""
    nodes, similarity = load_graph(spark, sf, "page")
    keys = checkpointed(nodes.select("id", rank_key("s").alias("key")))
    found = classes.classes_of(nodes, similarity)
    members = checkpointed(found.members.select("id", "class").join(keys.hint(hint), "id"))
    return classes.node_pairs(found, members, "key").select("u", "v", (F.col("key_u") < F.col("key_v")).alias("u_first"))


for _name, _hint in (("join_sortmerge", "merge"), ("join_shuffle_hash", "shuffle_hash")):
    op(_name, o.query(PAGE, "SELECT u, v, md5('s:' || u) < md5('s:' || v) AS u_first FROM pairs"))(lambda spark, sf, h=_hint: _ends(spark, sf, h))


@op("join_nested_loop", o.query(EMB, f"a AS (SELECT vec_id AS id FROM embeddings ORDER BY {KEY}, vec_id LIMIT 50)", "SELECT a.id, p.y AS near FROM a JOIN (SELECT u AS x, v AS y FROM pairs UNION ALL SELECT v, u FROM pairs) p ON p.x = a.id"))
def _(spark, sf):
    nodes = table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), "embedding")
    anchors = sampling.bottom_k(nodes, 50, "", "s").select(F.col("id").alias("a"), F.col("embedding").alias("e"))
    return nodes.join(F.broadcast(anchors), (F.col("id") != F.col("a")) & (cosine(F.col("embedding"), F.col("e")) > 0.2)).select(F.col("a").alias("id"), F.col("id").alias("near"))


@op("join_range", o.query(o.GRAPH["evt"], "SELECT u, v FROM pairs"))
def _(spark, sf):
    nodes, similarity = load_graph(spark, sf, "evt")
    assert isinstance(similarity, NearInKey)
    return similarity.pairs(nodes)


@op("join_interval", f"WITH k AS (SELECT vec_id AS id, {KEY} AS key FROM embeddings), p AS (SELECT id AS x, key AS hi, lag(key, 40) OVER (ORDER BY key) AS lo FROM k) SELECT p.x, k.id FROM p JOIN k ON k.key > p.lo AND k.key < p.hi")
def _(spark, sf):
    """Every vector probes: an interval meets the cells of the key's first three digits that it touches."""
    cell = lambda key: F.conv(F.substring(key, 1, 3), 16, 10).cast("int")
    k = checkpointed(_keys(spark, sf))
    placed = checkpointed(ranking.places(k))
    p = placed.select(F.col("id").alias("x"), F.col("key").alias("hi"), "place").join(placed.select((F.col("place") + 40).alias("place"), F.col("key").alias("lo")), "place").drop("place")
    touched = p.select("x", "lo", "hi", F.explode(F.sequence(cell(F.col("lo")), cell(F.col("hi")))).alias("cell"))
    return k.withColumn("cell", cell(F.col("key"))).join(touched, "cell").where("key > lo AND key < hi").select("x", "id")


@op("join_asof", "SELECT event_id, coalesce((SELECT max_by(b.event_id, (b.ts, b.event_id)) FROM events b WHERE b.user_id = a.user_id AND (b.ts < a.ts OR b.ts = a.ts AND b.event_id < a.event_id)), -1) AS earlier FROM events a")
def _(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return table(spark, sf, "events").select("event_id", F.coalesce(F.last("event_id", ignorenulls=True).over(w), F.lit(-1)).alias("earlier"))


@op("join_semi", o.query(PAGE, "SELECT id FROM nodes WHERE id IN (SELECT u FROM pairs)"))
def _(spark, sf):
    ids, pairs = nodes_and_pairs(spark, sf, "page")
    return ids.join(pairs.select(F.col("u").alias("id")), "id", "left_semi")


@op("join_anti", o.query(PAGE, "SELECT id FROM nodes WHERE id NOT IN (SELECT u FROM pairs UNION ALL SELECT v FROM pairs)"))
def _(spark, sf):
    ids, pairs = nodes_and_pairs(spark, sf, "page")
    return ids.join(graph.both_ways(pairs).select("id"), "id", "left_anti")


@op("join_left_outer", o.query(PAGE, "SELECT n.id, count(p.u)::BIGINT AS later FROM nodes n LEFT JOIN pairs p ON p.u = n.id GROUP BY n.id"))
def _(spark, sf):
    ids, pairs = nodes_and_pairs(spark, sf, "page")
    return ids.join(pairs.withColumnRenamed("u", "id"), "id", "left").groupBy("id").agg(F.count("v").alias("later"))


@op("join_full_outer", "WITH a AS (SELECT c_nationkey AS k, count(*) AS n FROM customer GROUP BY 1), b AS (SELECT s_nationkey AS k, count(*) AS m FROM supplier GROUP BY 1) SELECT coalesce(a.k, b.k) AS k, coalesce(n, 0)::BIGINT AS n, coalesce(m, 0)::BIGINT AS m FROM a FULL JOIN b ON a.k = b.k")
def _(spark, sf):
    a = table(spark, sf, "customer").groupBy(F.col("c_nationkey").alias("k")).agg(F.count("*").alias("n"))
    b = table(spark, sf, "supplier").groupBy(F.col("s_nationkey").alias("k")).agg(F.count("*").alias("m"))
    return a.join(b, "k", "full").select("k", F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("m", F.lit(0)).alias("m"))


@op("join_self", "SELECT a.l_partkey AS u, b.l_partkey AS v, count(DISTINCT a.l_orderkey) AS orders FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY ALL HAVING count(DISTINCT a.l_orderkey) >= 2")
def _(spark, sf):
    rows = table(spark, sf, "lineitem").select("l_orderkey", "l_partkey").distinct()
    met = rows.withColumnRenamed("l_partkey", "u").join(rows.withColumnRenamed("l_partkey", "v"), "l_orderkey").where("u < v")
    return met.groupBy("u", "v").agg(F.count("*").alias("orders")).where("orders >= 2")


@op("join_star", "SELECT r_name, n_name, count(*) AS lines, sum(l_quantity) AS quantity FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ALL")
def _(spark, sf):
    t = lambda n: table(spark, sf, n)
    dims = t("nation").join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    facts = t("lineitem").select("l_orderkey", "l_quantity").join(t("orders").select("o_orderkey", "o_custkey"), F.col("o_orderkey") == F.col("l_orderkey")).join(t("customer").select("c_custkey", "c_nationkey"), F.col("c_custkey") == F.col("o_custkey"))
    return facts.join(F.broadcast(dims), F.col("n_nationkey") == F.col("c_nationkey")).groupBy("r_name", "n_name").agg(F.count("*").alias("lines"), F.sum("l_quantity").alias("quantity"))


# aggregations


@op("agg_hash", "SELECT l_partkey, count(*) AS n FROM lineitem GROUP BY l_partkey")
def _(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_partkey").agg(F.count("*").alias("n"))


@op("agg_sort", o.query(PAGE, "SELECT v AS id, array_to_string(list(u ORDER BY u), ',') AS near FROM pairs GROUP BY v"))
def _(spark, sf):
    _, pairs = nodes_and_pairs(spark, sf, "page")
    return pairs.groupBy(F.col("v").alias("id")).agg(F.array_join(F.sort_array(F.collect_list("u")), ",").alias("near"))


@op("agg_distinct", "SELECT l_suppkey, count(DISTINCT l_orderkey) AS orders, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY l_suppkey")
def _(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_suppkey").agg(F.countDistinct("l_orderkey").alias("orders"), F.countDistinct("l_partkey").alias("parts"))


@op("agg_conditional", "SELECT lang, count(*) FILTER (n_chars > 1000) AS long, sum(CASE WHEN source = 'src0' THEN 1 ELSE 0 END)::BIGINT AS hot FROM documents GROUP BY lang")
def _(spark, sf):
    return table(spark, sf, "documents").groupBy("lang").agg(F.count_if(F.col("n_chars") > 1000).alias("long"), F.sum(F.when(F.col("source") == "src0", 1).otherwise(0)).alias("hot"))


@op("agg_minmax_by", f"SELECT label, min_by(vec_id, ({KEY}, vec_id)) AS first, max_by(vec_id, ({KEY}, vec_id)) AS last FROM embeddings GROUP BY label")
def _(spark, sf):
    e = table(spark, sf, "embeddings").select("label", F.col("vec_id").alias("id")).withColumn("key", rank_key("s"))
    return e.groupBy("label").agg(F.min_by("id", F.struct("key", "id")).alias("first"), F.max_by("id", F.struct("key", "id")).alias("last"))


@op("agg_stats", "SELECT lang, round(avg(n_chars), 6) AS mean, round(stddev_samp(n_chars), 6) AS sd, median(n_chars)::DOUBLE AS median, quantile_cont(n_chars, 0.9)::DOUBLE AS p90 FROM documents GROUP BY lang")
def _(spark, sf):
    return table(spark, sf, "documents").groupBy("lang").agg(F.round(F.avg("n_chars"), 6).alias("mean"), F.round(F.stddev_samp("n_chars"), 6).alias("sd"), F.median("n_chars").alias("median"), F.percentile("n_chars", 0.9).alias("p90"))


@op("agg_approx")
def _(spark, sf):
    return table(spark, sf, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.01).alias("parts"), F.approx_percentile("l_quantity", 0.5, 10000).alias("median"))


for _name, _sql in (("agg_rollup", "ROLLUP (lang, source)"), ("agg_cube", "CUBE (lang, source)"), ("agg_grouping_sets", "GROUPING SETS ((lang), (source), ())")):

    def _levels(spark, sf, name=_name):
        d = table(spark, sf, "documents")
        agg = [F.grouping_id().cast("bigint").alias("level"), F.count("*").alias("n"), F.sum("n_chars").alias("chars")]
        grouped = d.rollup("lang", "source") if name == "agg_rollup" else d.cube("lang", "source") if name == "agg_cube" else d.groupingSets([["lang"], ["source"], []], "lang", "source")
        return grouped.agg(*agg)

    op(_name, f"SELECT lang, source, grouping(lang, source)::BIGINT AS level, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents GROUP BY {_sql}")(_levels)


@op("agg_pivot", "SELECT source, count(*) FILTER (lang = 'de') AS de, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'es') AS es, count(*) FILTER (lang = 'fr') AS fr FROM documents GROUP BY source")
def _(spark, sf):
    return table(spark, sf, "documents").groupBy("source").pivot("lang", ["de", "en", "es", "fr"]).agg(F.count("doc_id")).na.fill(0)


@op("agg_unpivot", "SELECT doc_id, 'quality' AS kind, quality AS bit FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
def _(spark, sf):
    return table(spark, sf, "labels").unpivot("doc_id", ["quality", "toxic"], "kind", "bit")


@op("agg_having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) >= 15")
def _(spark, sf):
    return table(spark, sf, "orders").groupBy("o_custkey").agg(F.count("*").alias("n")).where("n >= 15")


# windows


@op("win_row_number_k", o.query(PAGE, T_ONE, o.fold(), "SELECT b.id, a.id AS near FROM (SELECT rk, near, row_number() OVER (PARTITION BY rk ORDER BY near) AS place FROM oriented) x JOIN ranked b ON b.rk = x.rk JOIN ranked a ON a.rk = x.near WHERE place <= 3"))
def _(spark, sf):
    ids, pairs = nodes_and_pairs(spark, sf, "page")
    ranked = ids.select(F.lit(0).alias("trial"), "id", rank_key("s").alias("key"))
    return pivot.first_k(pivot.earlier_neighbours(ranked, pairs), 3).select("id", "near")


_DEG = "d AS (SELECT n.id, count(p.u) AS degree FROM nodes n LEFT JOIN (SELECT u, u AS id FROM pairs UNION ALL SELECT u, v FROM pairs) p USING (id) GROUP BY n.id)"
for _name, _f, _s in (
    ("win_rank", F.rank, "rank()"),
    ("win_dense_rank", F.dense_rank, "dense_rank()"),
    ("win_percent_rank", F.percent_rank, "percent_rank()"),
    ("win_ntile", lambda: F.ntile(4), "ntile(4)"),
):

    def _ranking(spark, sf, f=_f, name=_name):
        d = graph.degrees(*nodes_and_pairs(spark, sf, "page")).withColumn("part", F.col("id") % 3)
        w = Window.partitionBy("part").orderBy("degree") if name != "win_ntile" else Window.partitionBy("part").orderBy("degree", "id")
        value = F.round(f().over(w), 9) if name == "win_percent_rank" else f().over(w).cast("bigint")
        return d.select("id", "degree", value.alias("place"))

    _over = f"{_s} OVER (PARTITION BY id % 3 ORDER BY degree{', id' if _name == 'win_ntile' else ''})"
    op(_name, o.query(PAGE, _DEG, f"SELECT id, degree::BIGINT AS degree, {'round(' + _over + ', 9)' if _name == 'win_percent_rank' else '(' + _over + ')::BIGINT'} AS place FROM d"))(_ranking)


@op("win_lag_lead", "SELECT event_id, coalesce(epoch_us(ts) - epoch_us(lag(ts) OVER w), -1) AS before_us, coalesce(epoch_us(lead(ts) OVER w) - epoch_us(ts), -1) AS after_us FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def _(spark, sf):
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    w = Window.partitionBy("user_id").orderBy("at", "event_id")
    e = table(spark, sf, "events").select("event_id", "user_id", at.alias("at"))
    return e.select("event_id", F.coalesce(F.col("at") - F.lag("at").over(w), F.lit(-1)).alias("before_us"), F.coalesce(F.lead("at").over(w) - F.col("at"), F.lit(-1)).alias("after_us"))


@op("win_running", "SELECT l_orderkey, l_linenumber, sum(l_quantity) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity ROWS UNBOUNDED PRECEDING) AS so_far FROM lineitem")
def _(spark, sf):
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_quantity").rowsBetween(Window.unboundedPreceding, 0)
    return table(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", F.sum("l_quantity").over(w).alias("so_far"))


@op("win_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS last_hour FROM events")
def _(spark, sf):
    w = Window.partitionBy("user_id").orderBy("at").rangeBetween(-3_600_000_000, 0)
    return table(spark, sf, "events").withColumn("at", F.unix_micros(F.col("ts").cast("timestamp"))).select("event_id", F.count("*").over(w).alias("last_hour"))


@op("win_first_last", f"SELECT vec_id AS id, first_value(vec_id) OVER w AS first, last_value(vec_id) OVER w AS last, coalesce(nth_value(vec_id, 2) OVER w, -1) AS second FROM embeddings WINDOW w AS (PARTITION BY label ORDER BY {KEY} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def _(spark, sf):
    w = Window.partitionBy("label").orderBy("key").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    e = table(spark, sf, "embeddings").select("label", F.col("vec_id").alias("id")).withColumn("key", rank_key("s"))
    return e.select("id", F.first("id").over(w).alias("first"), F.last("id").over(w).alias("last"), F.coalesce(F.nth_value("id", 2).over(w), F.lit(-1)).alias("second"))


# sort, limits, samples


@op("sort_total", f"SELECT vec_id AS id, row_number() OVER (ORDER BY {KEY}) - 1 AS place FROM embeddings")
def _(spark, sf):
    from ..operators.ranking import dense_rank_order

    return dense_rank_order(_emb(spark, sf), "s").orderBy("key").select("id", (F.col("rank") - 1).alias("place"))


@op("limit_offset", f"SELECT vec_id AS id FROM embeddings ORDER BY {KEY} LIMIT 20 OFFSET 100")
def _(spark, sf):
    return _keys(spark, sf).orderBy("key").offset(100).limit(20).select("id")


@op("topk_global", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 25")
def _(spark, sf):
    return table(spark, sf, "documents").select("doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id").limit(25)


@op("topk_group", "SELECT source, doc_id FROM (SELECT source, doc_id, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) AS place FROM documents) WHERE place <= 3")
def _(spark, sf):
    place = F.row_number().over(Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id"))
    return table(spark, sf, "documents").select("source", "doc_id", "n_chars").withColumn("place", place).where("place <= 3").select("source", "doc_id")


@op("sample_stratified", "SELECT lang, doc_id AS id FROM (SELECT lang, doc_id, row_number() OVER (PARTITION BY lang ORDER BY md5('s:' || doc_id), doc_id) AS place FROM documents) WHERE place <= 10")
def _(spark, sf):
    return sampling.bottom_k_strata(table(spark, sf, "documents").select(F.col("doc_id").alias("id"), "lang"), "lang", 10, "s").select("lang", "id")


@op("sample_bernoulli")
def _(spark, sf):
    return table(spark, sf, "lineitem").select("l_orderkey", "l_linenumber").sample(0.01, 42)


@op("sample_reservoir", "SELECT doc_id AS id FROM documents WHERE n_chars < 1000 ORDER BY md5('s1:s:' || doc_id), doc_id LIMIT 40")
def _(spark, sf):
    low = table(spark, sf, "documents").where("n_chars < 1000").select(F.col("doc_id").alias("id"))
    return sampling.bottom_k(low, 40, "s1", "s").select("id")


# sets

def _two(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    return table(spark, sf, "customer").select(F.col("c_nationkey").alias("k")), table(spark, sf, "supplier").select(F.col("s_nationkey").alias("k"))


for _name, _word, _f in (
    ("set_union", "UNION", lambda a, b: a.union(b).distinct()),
    ("set_union_all", "UNION ALL", lambda a, b: a.unionAll(b)),
    ("set_intersect", "INTERSECT", lambda a, b: a.intersect(b)),
    ("set_except", "EXCEPT", lambda a, b: a.subtract(b)),
    ("set_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
    ("set_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)),
):
    op(_name, f"SELECT c_nationkey AS k FROM customer {_word} SELECT s_nationkey AS k FROM supplier")(lambda spark, sf, f=_f: f(*_two(spark, sf)))


@op("mismatch_set_difference", o.query(o.GRAPH["emb3"], o.trials([("s", 5, 0.1)]), o.fold(), o.BUDGETED, "mp AS (SELECT a.id AS u, b.id AS v FROM exact a JOIN exact b ON a.id < b.id LEFT JOIN pairs p ON p.u = a.id AND p.v = b.id WHERE (p.u IS NOT NULL) = (a.pivot <> b.pivot))", "mb AS (SELECT a.id AS u, b.id AS v FROM labels a JOIN labels b ON a.id < b.id LEFT JOIN pairs p ON p.u = a.id AND p.v = b.id WHERE (p.u IS NOT NULL) = (a.pivot <> b.pivot))", "SELECT u, v FROM mp EXCEPT SELECT u, v FROM mb"))
def _(spark, sf):
    from ..operators.mismatch import mismatch_pairs

    ids, pairs = nodes_and_pairs(spark, sf, "emb3")
    whole = mismatch_pairs(checkpointed(pivot.pivot_cluster(ids, pairs)), pairs).select("u", "v")
    return whole.subtract(mismatch_pairs(checkpointed(pivot.budgeted_pivot(ids, pairs, 5)), pairs).select("u", "v"))


@op("distinct", "SELECT DISTINCT l_partkey, l_suppkey FROM lineitem")
def _(spark, sf):
    return table(spark, sf, "lineitem").select("l_partkey", "l_suppkey").distinct()


@op("drop_duplicates", "SELECT min(doc_id) AS doc_id FROM documents GROUP BY text")
def _(spark, sf):
    d = table(spark, sf, "documents").select("doc_id", F.sha2("text", 256).alias("digest"))
    return d.groupBy("digest").agg(F.min("doc_id").alias("doc_id")).select("doc_id")


# strings, arrays, maps, structs, JSON


@op("str_shingles", "WITH w AS (SELECT doc_id, string_split(lower(text), ' ') AS w FROM documents) SELECT doc_id, len(list_distinct(list_transform(range(1, greatest(len(w) - 3, 1) + 1), lambda i: array_to_string(w[i:i + 3], ' '))))::BIGINT AS n FROM w")
def _(spark, sf):
    return table(spark, sf, "documents").select("doc_id", F.size(shingles(F.col("text"))).cast("bigint").alias("n"))


@op("str_hrefs", "SELECT page_id, array_to_string(list_sort(list_distinct(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1))), ' ') AS targets, regexp_extract(url, '^https?://([^/]+)', 1) AS host FROM pages")
def _(spark, sf):
    return table(spark, sf, "pages").select("page_id", F.array_join(F.sort_array(hrefs(F.col("html"))), " ").alias("targets"), F.regexp_extract("url", "^https?://([^/]+)", 1).alias("host"))


@op("str_hash", f"SELECT vec_id AS id, {KEY} AS key, sha256(vec_id::VARCHAR) AS digest, ('0x' || substr({KEY}, 1, 12))::BIGINT AS number FROM embeddings")
def _(spark, sf):
    return _keys(spark, sf).select("id", "key", F.sha2(F.col("id").cast("string"), 256).alias("digest"), F.conv(F.substring("key", 1, 12), 16, 10).cast("bigint").alias("number"))


@op("arr_cosine", "WITH e AS (SELECT vec_id AS id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings) SELECT a.id, round(list_cosine_similarity(a.e, b.e), 9) AS score FROM e a JOIN e b ON b.id = a.id + 1")
def _(spark, sf):
    e = table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), "embedding")
    after = e.select((F.col("id") - 1).alias("id"), F.col("embedding").alias("other"))
    return e.join(after, "id").select("id", F.round(cosine(F.col("embedding"), F.col("other")), 9).alias("score"))


@op("arr_sets", "WITH t AS (SELECT page_id AS id, list_distinct(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS t FROM pages) SELECT a.id, len(list_intersect(a.t, b.t))::BIGINT AS common, len(list_distinct(list_concat(a.t, b.t)))::BIGINT AS whole, (len(a.t) - len(list_intersect(a.t, b.t)))::BIGINT AS own FROM t a JOIN t b ON b.id = a.id + 1")
def _(spark, sf):
    t = checkpointed(table(spark, sf, "pages").select(F.col("page_id").alias("id"), hrefs(F.col("html")).alias("t")))
    after = t.select((F.col("id") - 1).alias("id"), F.col("t").alias("s"))
    size = lambda c: F.size(c).cast("bigint")
    return t.join(after, "id").select("id", size(F.array_intersect("t", "s")).alias("common"), size(F.array_union("t", "s")).alias("whole"), size(F.array_except("t", "s")).alias("own"))


@op("arr_fold", o.query(PAGE, T_ONE, o.fold(), o.BUDGETED, "SELECT id, calls::INTEGER AS calls FROM labels"))
def _(spark, sf):
    ids, pairs = nodes_and_pairs(spark, sf, "page")
    return pivot.budgeted_pivot(ids, pairs, 15, strategy="rounds").select("id", "calls")


@op("arr_explode", "SELECT vec_id AS id, i - 1 AS place, round(embedding[i]::DOUBLE, 9) AS x FROM (SELECT vec_id, embedding, unnest(range(1, len(embedding) + 1)) AS i FROM embeddings)")
def _(spark, sf):
    return table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), F.posexplode("embedding")).select("id", F.col("pos").cast("bigint").alias("place"), F.round(F.col("col").cast("double"), 9).alias("x"))


@op("map_sparse_l1", "SELECT a.doc_id, (abs(4 * (a.doc_id - b.doc_id) + a.quality - b.quality) + abs(a.toxic - b.toxic))::DOUBLE AS distance FROM labels a JOIN labels b ON b.doc_id > a.doc_id AND b.doc_id <= a.doc_id + 3")
def _(spark, sf):
    points = table(spark, sf, "labels").select("doc_id", F.create_map(F.lit(0), (4 * F.col("doc_id") + F.col("quality")).cast("double"), F.lit(1), F.col("toxic").cast("double")).alias("x"))
    b = points.select(F.explode(F.array(F.col("doc_id") - 1, F.col("doc_id") - 2, F.col("doc_id") - 3)).alias("doc_id"), F.col("x").alias("y"))
    return points.join(b, "doc_id").select("doc_id", sparse_l1(F.col("x"), F.col("y")).alias("distance"))


@op("struct_nested", f"SELECT vec_id AS id, {KEY} AS first_key, vec_id + 1 AS next FROM embeddings")
def _(spark, sf):
    s = _keys(spark, sf).select("id", F.struct("id", F.struct("key").alias("at")).alias("e"))
    wider = s.withColumn("e", F.col("e").withField("next", F.col("e.id") + 1))
    return wider.select("id", F.col("e").getField("at")["key"].alias("first_key"), F.col("e.next").alias("next"))


@op("json_props", "SELECT event_id, (props->>'$.k')::INTEGER AS k, '{\"k\":' || (props->>'$.k') || '}' AS again FROM events")
def _(spark, sf):
    parsed = F.from_json("props", "k INT")
    return table(spark, sf, "events").select("event_id", parsed["k"].alias("k"), F.to_json(F.struct(F.get_json_object("props", "$.k").cast("int").alias("k"))).alias("again"))


# numbers and dates


@op("math_sizes", "SELECT l_suppkey, n, ceil(48 * 15 * pow(n, 0.75) * ln(n))::BIGINT AS r, least(n, ceil(sqrt(n))::BIGINT) AS root, n // 7 AS part FROM (SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY l_suppkey)")
def _(spark, sf):
    n = table(spark, sf, "lineitem").groupBy("l_suppkey").agg(F.count("*").alias("n"))
    return n.select("l_suppkey", "n", F.ceil(48 * 15 * F.pow("n", F.lit(0.75)) * F.ln("n")).alias("r"), F.least("n", F.ceil(F.sqrt("n"))).alias("root"), F.expr("n DIV 7").alias("part"))


@op("date_parts", "SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, quarter(o_orderdate)::INTEGER AS q, month(o_orderdate)::INTEGER AS m, day(o_orderdate)::INTEGER AS d FROM orders")
def _(spark, sf):
    return table(spark, sf, "orders").select("o_orderkey", *[f("o_orderdate").alias(n) for f, n in ((F.year, "y"), (F.quarter, "q"), (F.month, "m"), (F.day, "d"))])


@op("date_arith", "SELECT l_orderkey, l_linenumber, date_diff('day', o_orderdate::DATE, l_shipdate::DATE)::INTEGER AS days, strftime(o_orderdate + INTERVAL 30 DAY, '%Y-%m-%d') AS due FROM lineitem JOIN orders ON o_orderkey = l_orderkey")
def _(spark, sf):
    met = table(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", "l_shipdate").join(table(spark, sf, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_orderdate"), "l_orderkey")
    return met.select("l_orderkey", "l_linenumber", F.datediff("l_shipdate", "o_orderdate").alias("days"), F.date_format(F.col("o_orderdate") + F.expr("INTERVAL 30 DAYS"), "yyyy-MM-dd").alias("due"))


@op("date_trunc", "SELECT strftime(date_trunc('month', ts), '%Y-%m') AS month, event_type, count(*) AS n FROM events GROUP BY ALL")
def _(spark, sf):
    return table(spark, sf, "events").groupBy(F.date_format(F.date_trunc("month", "ts"), "yyyy-MM").alias("month"), "event_type").agg(F.count("*").alias("n"))


@op("cast_decimal", "SELECT o_orderkey, (n * (n - 1) // 2)::VARCHAR AS pairs FROM (SELECT o_orderkey, 100000000000::HUGEINT + o_orderkey AS n FROM orders)")
def _(spark, sf):
    n = table(spark, sf, "orders").select("o_orderkey", (F.lit(100_000_000_000) + F.col("o_orderkey")).cast("decimal(19,0)").alias("n"))
    return n.select("o_orderkey", F.floor(F.col("n") * (F.col("n") - 1) / 2).cast("decimal(38,0)").cast("string").alias("pairs"))


@op("null_handling", "SELECT doc_id, coalesce(nullif(quality, 0), -1) AS q, CASE WHEN toxic = 0 THEN 'none' ELSE 'some' END AS t, coalesce((quality / nullif(toxic, 0))::VARCHAR, 'undefined') AS ratio FROM labels")
def _(spark, sf):
    ratio = F.col("quality") / F.nullif("toxic", F.lit(0))
    return table(spark, sf, "labels").select("doc_id", F.coalesce(F.nullif("quality", F.lit(0)), F.lit(-1)).alias("q"), F.nvl2(F.nullif("toxic", F.lit(0)), F.lit("some"), F.lit("none")).alias("t"), F.coalesce(ratio.cast("string"), F.lit("undefined")).alias("ratio"))


@op("generate_grid", "SELECT 's' || c_custkey AS seed, k, f / 100 AS space FROM customer, (SELECT unnest([2, 5, 15]) AS k), range(2, 17, 2) c(f)")
def _(spark, sf):
    seeds = table(spark, sf, "customer").select(F.concat(F.lit("s"), F.col("c_custkey").cast("string")).alias("seed"))
    return seeds.select("seed", F.explode(F.array(*map(F.lit, (2, 5, 15)))).alias("k")).select("seed", "k", F.explode(F.sequence(F.lit(2), F.lit(16), F.lit(2))).alias("f")).select("seed", "k", (F.col("f") / 100).alias("space"))


# subqueries, CTEs


def _sql(spark: SparkSession, sf: str, text: str, *names: str) -> DataFrame:
    return spark.sql(text, **{n: table(spark, sf, n) for n in names})


@op("subquery_exists", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def _(spark, sf):
    return _sql(spark, sf, "SELECT c_custkey FROM {customer} WHERE EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_totalprice > 300000)", "customer", "orders")


@op("subquery_scalar", "SELECT doc_id FROM documents WHERE n_chars > (SELECT avg(n_chars) FROM documents)")
def _(spark, sf):
    return _sql(spark, sf, "SELECT doc_id FROM {documents} WHERE n_chars > (SELECT avg(n_chars) FROM {documents})", "documents")


@op("subquery_correlated", "SELECT doc_id FROM documents d WHERE n_chars >= (SELECT max(n_chars) FROM documents e WHERE e.source = d.source)")
def _(spark, sf):
    return _sql(spark, sf, "SELECT d.doc_id FROM {documents} d WHERE d.n_chars >= (SELECT max(e.n_chars) FROM {documents} e WHERE e.source = d.source)", "documents")


@op("cte", "WITH n AS (SELECT o_custkey, count(*) AS c FROM orders GROUP BY 1), t AS (SELECT max(c) AS most FROM n) SELECT o_custkey, c FROM n, t WHERE c = most")
def _(spark, sf):
    return _sql(spark, sf, "WITH n AS (SELECT o_custkey, count(*) AS c FROM {orders} GROUP BY 1), t AS (SELECT max(c) AS most FROM n) SELECT o_custkey, c FROM n CROSS JOIN t WHERE c = most", "orders")


@op("cte_recursive", "WITH RECURSIVE r AS (SELECT c_nationkey AS k, count(*) AS x, 0 AS depth FROM customer GROUP BY c_nationkey UNION ALL SELECT k, x * 2, depth + 1 FROM r WHERE depth < 10) SELECT k, x, depth FROM r")
def _(spark, sf):
    return _sql(spark, sf, "WITH RECURSIVE r(k, x, depth) AS (SELECT c_nationkey, count(*), 0 FROM {customer} GROUP BY c_nationkey UNION ALL SELECT k, x * 2, depth + 1 FROM r WHERE depth < 10) SELECT k, x, depth FROM r", "customer")


# graphs


_CC = "cc(id, c) AS (SELECT id, id FROM nodes UNION SELECT p.y, cc.c FROM cc JOIN (SELECT u AS x, v AS y FROM pairs UNION ALL SELECT v, u FROM pairs) p ON p.x = cc.id WHERE cc.c < p.y)"


@op("components", o.query(o.GRAPH["page2"], _CC, "SELECT id, min(c) AS component FROM cc GROUP BY id"))
def _(spark, sf):
    return graph.components(*nodes_and_pairs(spark, sf, "page2"))


@op("triangles", o.query(PAGE, "SELECT a.u AS a, a.v AS b, b.v AS c FROM pairs a JOIN pairs b ON b.u = a.v JOIN pairs c ON c.u = a.u AND c.v = b.v"))
def _(spark, sf):
    return graph.triangles(nodes_and_pairs(spark, sf, "page")[1])


@op("bad_triangles", o.query(o.GRAPH["emb3"], "w AS (SELECT u AS x, v AS y FROM pairs UNION ALL SELECT v, u FROM pairs)", "SELECT l.x AS center, l.y AS a, r.y AS b FROM w l JOIN w r ON l.x = r.x AND l.y < r.y ANTI JOIN pairs p ON p.u = l.y AND p.v = r.y"))
def _(spark, sf):
    return dense.dense_bad_triangles(*load_graph(spark, sf, "emb3"))


@op("induced_subgraph", o.query(EMB, f"a AS (SELECT vec_id AS id FROM embeddings ORDER BY {KEY}, vec_id LIMIT 50)", "SELECT u, v FROM pairs WHERE u IN (SELECT id FROM a) AND v IN (SELECT id FROM a)"))
def _(spark, sf):
    ids, pairs = nodes_and_pairs(spark, sf, "emb")
    return graph.induced(pairs, sampling.bottom_k(ids, 50, "", "s"))


@op("symmetrize", "SELECT DISTINCT least(l_partkey, l_suppkey) AS u, greatest(l_partkey, l_suppkey) AS v FROM lineitem WHERE l_partkey <> l_suppkey")
def _(spark, sf):
    return graph.symmetrize(table(spark, sf, "lineitem"), "l_partkey", "l_suppkey")
