"""A training-corpus pipeline of five operators, each stage a function of the one before.

Documents that the toxicity grammar rejects go, one document of each near-duplicate class
stays, repeated passages are cut out, contaminated documents go, and the rest is packed.

Rows with null or empty texts or null ids pass through all stages (rows of equal texts, empty ones
too, are one class of the second stage); repeated rows are equal texts; columns beyond doc_id and text are
never read, whatever their names, and all but the last stage return them; an empty table
gives an empty result.  The row that stays of a class is the one with the smallest doc_id.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from clustercost.llm import decontaminate, minhash, packing, substring_dedup, toxicity
from clustercost.llm.exchange import checkpointed, table


def reject_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    grammar = toxicity.fit(docs, table(spark, sf_dir, "labels"))
    return toxicity.without_toxic(docs, grammar)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return minhash.first_of_classes(docs)


def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return substring_dedup.without_repeats(docs)


def decontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.without_contaminated(docs, table(spark, sf_dir, "benchmark"))


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack_documents(docs)


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("toxicity", reject_toxic),
    ("near_dedup", near_dedup),
    ("substring_dedup", cut_repeats),
    ("decontamination", decontaminated),
    ("packing", packed),
]

#: Learned weights and token ids are not expressible in SQL; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = checkpointed(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
