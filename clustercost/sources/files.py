"""Pairs and labels as files: CSV, JSON lines, Parquet partitioned by a hash bucket."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

PAIRS = StructType([StructField("u", LongType(), False), StructField("v", LongType(), False)])


def write_pairs(pairs: DataFrame, path: str, kind: str = "parquet", buckets: int | None = None, mode: str = "overwrite") -> None:
    """``buckets`` partitions Parquet by ``u mod buckets``, so a reader of few nodes prunes folders."""
    rows = pairs.select("u", "v")
    if buckets:
        rows.withColumn("bucket", F.pmod("u", F.lit(buckets)).cast("int")).repartition(buckets, "bucket").write.mode(mode).partitionBy("bucket").parquet(path)
    elif kind == "csv":
        rows.write.mode(mode).option("header", True).csv(path)
    elif kind == "json":
        rows.write.mode(mode).json(path)
    else:
        rows.write.mode(mode).parquet(path)


def read_pairs(spark: SparkSession, path: str, kind: str = "parquet") -> DataFrame:
    reader = spark.read.schema(PAIRS)
    return reader.option("header", True).csv(path) if kind == "csv" else reader.json(path) if kind == "json" else spark.read.parquet(path).select("u", "v")


def write_labels(labels: DataFrame, path: str, mode: str = "append") -> None:
    labels.write.mode(mode).partitionBy(*[c for c in ("graph", "trial") if c in labels.columns]).parquet(path)


def validated(nodes: DataFrame, schema: StructType) -> DataFrame:
    """The columns of ``schema``, cast to its types; missing columns and repeated ids are errors, others are ignored."""
    missing = [f.name for f in schema.fields if f.name not in nodes.columns]
    if missing:
        raise ValueError(f"nodes lack {', '.join(missing)}")
    rows = nodes.select(*[F.col(f.name).cast(f.dataType).alias(f.name) for f in schema.fields])
    twice = rows.groupBy("id").count().where("count > 1 OR id IS NULL").limit(1).collect()
    if twice:
        raise ValueError(f"node id {twice[0]['id']} is null or repeats")
    return rows
