"""A corpus pipeline: quality rules, line and near de-duplication, mixing and packing, each stage written and reread.

STAGES lists (name, function); each function takes (spark, docs, sf_dir) and returns a DataFrame.
All but the last return the columns of docs, whatever others there are.

Defined results: an empty table gives empty ones. Documents whose text is null, empty or without words go in the
first stage, which rejects texts of under fifty words, and any that the second one empties go there. Null ids and sources, and ids that
repeat, are rows of their own in every stage; rows that agree in id and text lose their copies in the third. Texts
of any length are taken whole.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coreset_spark.llm import jaccard_join, line_dedup, mixing, packing, quality_rules
from coreset_spark.llm.common import only
from coreset_spark.llm.queries import tokenizer
from coreset_spark.operators.storage import new_folder, remove


def quality_rules_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops rejected documents, and the lines that failed from the others."""
    return quality_rules.clean(docs)


def line_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops repeated chunks, and documents of which no word is left."""
    return only(line_dedup.dedup(docs), F.col("text").rlike(r"[^\x20\x09-\x0D]"))


def near_duplicates_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each group of near copies: five-word shingles, similarity of 0.8 or more."""
    return jaccard_join.keep_one(docs, jaccard_join.Join(n=5, percent=80, keep_signatures=False))


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeats and drops documents so that sources come near their targets."""
    return mixing.mix(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs the documents' tokens into sequences: one row per piece."""
    return packing.pack(docs, packing.Packing(tokenizer()))


STAGES = [
    ("quality rules", quality_rules_stage),
    ("line dedup", line_dedup_stage),
    ("n-gram jaccard join", near_duplicates_stage),
    ("mixing sources", mixing_stage),
    ("best-fit packing", packing_stage),
]

#: The last two stages draw by hashes and tokenise, which SQL cannot express.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Applies the stages to documents; each result is written as Parquet in the shared folder and read again, and goes when the next one is there."""
    docs, folder = spark.read.parquet(f"{sf_dir}/documents.parquet"), new_folder(spark, "pipeline")
    for number, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(path := f"{folder}/{number}")
        docs = spark.read.parquet(path)
        if number:
            remove(spark, f"{folder}/{number - 1}")
    return docs
