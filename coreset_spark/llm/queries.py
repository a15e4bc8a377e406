"""Registered queries of the training-data operators; each applies one operator to its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import oracles as sql
from . import ball_tree, jaccard_join, line_dedup, mixing, packing, pii, quality_bayes, quality_rules, quotations, toxicity
from .common import table


def tokenizer(name: str = "word_bpe_49k.json") -> str:
    """The place of a public tokenizer's file."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_quality_bayes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents have no URL: their source stands for the host, source and language for the path."""
    host, path = F.col("source"), F.concat_ws("/", "source", "lang")
    return quality_bayes.judge(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), host, path)


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.fit(docs, table(spark, sf_dir, "labels")))


def op3_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = jaccard_join.join(table(spark, sf_dir, "documents"), jaccard_join.Join(n=3, percent=90))
    return found.select("doc_id", "n_shingles", "component_id")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def op4_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    """With a fixed demonstration key; users pass their own."""
    return pii.pseudonymise(table(spark, sf_dir, "documents"), b"demonstration key, not a secret")


def op5_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.measure(table(spark, sf_dir, "documents"))


def op6_quotations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quotations.conversations(table(spark, sf_dir, "conversations"))


def op7_ball_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ball_tree.top_k(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 100 == 0)


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.measure(table(spark, sf_dir, "documents"))


def op9_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), packing.Packing(tokenizer()))


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.measure(table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    named = (
        op1_quality_bayes, op2_toxicity, op3_jaccard_join, op4_pii, op5_mixing, op6_quotations, op7_ball_tree,
        op8_quality_rules, op9_packing, op10_line_dedup, pipeline,
    )
    return {f.__name__: f for f in named}


def oracles() -> dict[str, str]:
    return sql.oracles()
