"""The pipeline stage by stage against its operators, and the registered queries with SQL."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from clustercost.llm import decontaminate, minhash, queries, substring_dedup
from tests.compare import connect, rows_of, sql_rows


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_same_rows(spark, sf, name):
    assert rows_of(queries.QUERIES[name](spark, sf)) == sql_rows(connect(sf), queries.ORACLES[name])


def test_stages(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, seen = docs.columns, [docs]
    for i, (_, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, sf)
        out.write.parquet(str(tmp_path / str(i)))
        docs = spark.read.parquet(str(tmp_path / str(i)))
        seen.append(docs)
        assert i == 4 or docs.columns == columns
    before, after, distinct, cut, clean, packed = seen
    assert after.count() < before.count() and after.join(before, columns, "left_anti").isEmpty()
    classes = minhash.near_classes(after)
    assert distinct.count() == classes.select("class_id").distinct().count()
    texts = [(r["doc_id"], r["text"]) for r in distinct.collect()]
    want = {i: x for (i, _), x in zip(texts, substring_dedup.brute_force([t for _, t in texts]), strict=True)}
    import hashlib

    for r in cut.collect():
        assert hashlib.sha256(b" ".join((r["text"] or "").encode().split())).hexdigest() == want[r["doc_id"]][2] and r["n_chars"] == len(r["text"])
    bad = decontaminate.contamination(cut, spark.read.parquet(f"{sf}/benchmark.parquet")).where("contaminated").select("doc_id")
    assert {r["doc_id"] for r in clean.collect()} == {r["doc_id"] for r in cut.join(bad, "doc_id", "left_anti").collect()}
    assert packed.select("doc_id").distinct().count() == clean.count()
    assert rows_of(corpus_pipeline.run(spark, sf).groupBy("doc_id").agg(F.sum("length").alias("n"))) == rows_of(packed.groupBy("doc_id").agg(F.sum("length").alias("n")))


def test_stages_on_an_empty_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, sf)
        assert out.count() == 0
        docs = out if "text" in out.columns else docs


def test_stages_on_odd_rows(spark, sf):
    """Nulls, empty and long texts, repeats, and columns whose names the stages use themselves."""
    long = " ".join(f"w{i % 997}x{i}" for i in range(20_000))
    passage = " ".join(f"p{i}" for i in range(60))
    six, seven = (" ".join(f"{c}{i}" for i in range(90)) for c in "ab")
    toxic = "you are an idiot, a moron and worthless scum."
    rows = [(1, None), (2, ""), (3, " \n"), (4, long), (5, long), (None, "no id at all"), (None, None), (6, six + " " + passage), (7, passage + " " + seven), (7, passage + " " + seven), (8, toxic), (9, "fine words here")]
    schema = "doc_id bigint, text string, lang string, source string, n_chars bigint, spans int, `key of row` string, node bigint, score double, class bigint"
    docs = spark.createDataFrame([(i, t, "en", "s", None if t is None else len(t), 1, "k", 2, 0.5, 3) for i, t in rows], schema)
    columns, kept = docs.columns, []
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, sf).persist()
        assert docs.columns == columns
        kept.append(sorted(((r["doc_id"], r["text"]) for r in docs.collect()), key=str))
        assert all(r["spans"] == 1 and r["class"] == 3 for r in docs.collect())
    toxic_gone, one_of_each, cut, clean = kept
    assert sorted(toxic_gone, key=str) == sorted([r for r in rows if r[0] != 8], key=str)
    assert len(one_of_each) == len({t or "" for _, t in toxic_gone}) and len([t for _, t in one_of_each if t == long]) == 1
    assert dict(cut)[6] == six and dict(cut)[7] == seven and clean == cut
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, sf).collect()
    assert {r["doc_id"] for r in packed} == {i for i, _ in clean} and all(r["length"] <= 1024 for r in packed)
