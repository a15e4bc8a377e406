"""Helpers shared by the training-data operators."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.storage import cut

#: One word is a run of characters other than ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"
SPACE = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def words(text: Column) -> Column:
    """Words of a text; none for null and for empty texts."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), SPACE), "")


def n_words(text: Column) -> Column:
    """Number of words, without keeping the words; where blanks alone part them, without a regular expression."""
    text = F.coalesce(text, F.lit(""))
    bare = F.length(F.translate(F.regexp_replace(text, WORD, "x"), " \t\n\x0b\x0c\r", ""))
    return F.when(text.rlike(r"[\x09-\x0D]"), bare).otherwise(F.size(F.array_remove(F.split(text, " "), ""))).cast("long")


def keyed(value: Column) -> Column:
    """Bytes equal for equal values, nulls included, for joins on nullable keys."""
    return F.coalesce(F.concat(F.lit("="), value.cast("string")), F.lit("0"))


def only(df: DataFrame, condition: Column) -> DataFrame:
    """Rows for which the condition holds, with every expression below evaluated once.

    A plain filter is pushed below the projections it reads, so their array expressions would be
    evaluated again, inside lambdas even once per element. A filter on what a generator makes stays.
    """
    one = F.explode_outer(F.when(condition, F.array(F.lit(1))).otherwise(F.array(F.lit(0))))
    return df.withColumn("_holds", one).filter("_holds = 1").drop("_holds")


__all__ = ["SPACE", "WORD", "cut", "keyed", "n_words", "only", "table", "words"]
