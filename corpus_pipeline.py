"""Corpus pipeline: toxicity, exact deduplication, near-duplicate join, mixing, packing.

Each stage takes and returns a table; all but the last return the columns of documents and keep any others.  A stage works on all rows
it is given.  Null and empty texts pass the filters (one of them, since they are equal); an empty table passes through all stages.
"""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from privsurv.llm import chunk_dedup, jaccard_join, mixing, packing, queries, toxicity
from privsurv.llm.common import cut, one_each, read, ready, unused

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that score 0.5 or more go.  The field learns from labelled documents that aren't held out."""
    held = spark.sparkContext.broadcast(toxicity.train_on(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels")))

    @F.pandas_udf("double")
    def score(text: pd.Series) -> pd.Series:
        return pd.Series(toxicity.score(held.value, text.fillna("").tolist())[0])

    name = unused(docs, "__score")
    return docs.withColumn(name, score(F.col("text").cast("string"))).where(F.col(name) < 0.5).drop(name)


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts one row with the smallest id stays."""
    kept = cut(chunk_dedup.marked(docs).where("kept").select("doc_id", "dh"), "kept-copies")
    return one_each(docs, kept)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents linked by similarity 0.8 or more, directly or not, one row with the smallest id stays."""
    found = jaccard_join.joined(docs).where(F.col("doc_id").eqNullSafe(F.col("class_id")) & (F.col("dh") == F.col("class_dh")))
    return one_each(docs, cut(found.select("doc_id", "dh").distinct(), "kept-classes"))


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeats documents so that domains' tokens come near their target shares.  The budget is the least at which no
    domain has to shrink, and rates are at least one: every document stays."""
    labelled = mixing.domains(read(spark, sf_dir, "labels"))
    found, _ = mixing.fit_mix(docs, labelled, mixing.WEIGHTS, budget="grow", least=1.0)
    rate, copy = unused(docs, "__rate"), unused(docs, "__copy")
    rated = docs.withColumn(rate, mixing.rate_of_text(docs, found))
    times = mixing.copies(F.col(rate), 6, "doc_id")
    return rated.withColumn(copy, F.explode(F.sequence(F.lit(1), F.greatest(F.lit(1), times)))).drop(rate, copy)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs, queries.tokenizer())


def _shipped(stage: Stage) -> Stage:
    """Stages run with the package on the executors."""

    def run(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        return stage(ready(spark), docs, sf_dir)

    return run


STAGES: list[tuple[str, Stage]] = [
    ("toxicity", _shipped(drop_toxic)),
    ("exact_dedup", _shipped(drop_copies)),
    ("jaccard_join", _shipped(drop_near_copies)),
    ("mixing", _shipped(mix)),
    ("packing", _shipped(pack)),
]
#: Classifiers and sampled joins have no SQL; tests/llm/test_pipeline.py holds each stage against a plain computation.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            docs = cut(docs, f"stage-{name}")
    return docs
