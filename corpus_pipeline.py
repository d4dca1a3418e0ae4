"""A corpus pipeline of five stages over ``documents``.

Each stage takes (spark, docs, sf_dir), works on everything its predecessor kept and returns
the columns of ``documents``; the last one returns the token index of the written corpus.
"""

from __future__ import annotations

import functools
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rulemat.llm import decontaminate, mixing, ngram_join, token_ids, toxicity
from rulemat.llm.common import fresh_name, persisted, rest_executors, row_keyed, table

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


def rested(stage: Stage) -> Stage:
    """``stage``, begun on executors whose heaps do not hold on to what the stages before filled."""

    @functools.wraps(stage)
    def run(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        rest_executors(spark)
        return stage(spark, docs, sf_dir)

    return run


@rested
def reject_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents whose toxicity score reaches the threshold."""
    model = toxicity.fit(docs.select("doc_id", "text"), table(spark, sf_dir, "labels"))
    name = fresh_name(docs, "toxic_score")
    return toxicity.score(docs, model, name).where(F.col(name) < toxicity.THRESHOLD).drop(name)


@rested
def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep the first document of every group of near copies: five words, similarity 0.8."""
    rows, key = row_keyed(docs)
    joined = ngram_join.jaccard_components(rows.select(F.col(key).alias("doc_id"), "text"), 5, 80)
    kept = joined.where(F.col("key") == F.col("component")).select(F.col("key").alias(key))
    return rows.join(kept, key, "left_semi").select(*docs.columns)


@rested
def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents that share a window of words with the benchmark."""
    rows, key = row_keyed(docs)
    found = decontaminate.decontaminate(rows.select(F.col(key).alias("doc_id"), "text"), table(spark, sf_dir, "benchmark"))
    hit = persisted(found.where(F.col("n_hit") > 0).select(F.col("doc_id").alias(key)), "contaminated")
    return rows.join(hit, key, "left_anti").select(*docs.columns)


@rested
def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeat documents of small sources up to the repetition limit; none is dropped."""
    return mixing.mixture(docs).select(*docs.columns)


@rested
def write_token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Write the mixture's token ids and return its index as read back from the files."""
    return token_ids.token_ids(docs, lean=True)


STAGES = [
    ("toxicity", reject_toxic),
    ("ngram_join", drop_near_copies),
    ("decontaminate", drop_contaminated),
    ("mixing", mix_sources),
    ("token_ids", write_token_ids),
]

#: SQL cannot express the first and the last stage.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = persisted(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
