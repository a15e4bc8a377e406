"""Input tables, and the frames derived from them that the methods work on. All draws are by md5, which any engine repeats."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import expressions as X

DIMS = 64


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """sample_id, vec, label of embeddings; rows without a usable vector or label are left to :func:`rejected`."""
    rows = table(spark, sf_dir, "embeddings").filter(F.col("embedding").isNotNull() & F.col("label").isNotNull())
    return rows.select(F.col("vec_id").alias("sample_id"), F.transform("embedding", lambda x: x.cast("double")).alias("vec"), "label")


def rejected(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "embeddings")
    reason = F.when(F.col("embedding").isNull(), "no vector").when(F.col("label").isNull(), "no label")
    return rows.withColumn("reason", reason).filter("reason is not null").select(F.col("vec_id").alias("sample_id"), "reason")


def draw_key(sample_id: Column, seed: int, turn: int) -> Column:
    return F.md5(F.concat(F.lit(f"{seed}:{turn}:"), sample_id.cast("string")))


def draw_pool(rows: DataFrame, n: int, seed: int = 42, turn: int = 0) -> DataFrame:
    """n rows without replacement, fresh for each turn: the n smallest keys.

    For large n only rows below a threshold that leaves a few more than n are ordered.
    """
    keyed = rows.withColumn("_key", draw_key(F.col("sample_id"), seed, turn))
    if n > 100_000:
        share = min(1.0, 1.05 * n / max(1, rows.count()) + 1e-6)
        keyed = keyed.filter(F.conv(F.substring("_key", 1, 8), 16, 10).cast("long") <= int(share * 2**32))
    return keyed.orderBy("_key", "sample_id").limit(n).drop("_key")


def tokens(text: Column) -> Column:
    return F.array_remove(F.split(F.lower(F.coalesce(text, F.lit(""))), " "), "")


def token_signs(token: Column) -> Column:
    """A token's vector: +1 or -1 by the 64 leading bits of its md5."""
    bits = F.concat(*[F.lpad(F.conv(F.substring(F.md5(token), 1 + 8 * i, 8), 16, 2), 32, "0") for i in range(2)])
    return F.transform(F.sequence(F.lit(1), F.lit(DIMS)), lambda i: F.when(F.substring(bits, i, F.lit(1)) == "1", 1.0).otherwise(-1.0))


def history(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Score readings: a user is a row, the order of its events the step, the running mean of value the score."""
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, sf_dir, "events").select(
        F.col("user_id").alias("sample_id"), (F.row_number().over(order) - 1).cast("long").alias("step"), F.avg("value").over(order.rowsBetween(Window.unboundedPreceding, 0)).alias("score"), "ts"
    )


def pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User turns with the assistant turn that follows; nine of ten conversations train, by the md5 of the id."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text", F.lead("role").over(w).alias("next_role"), F.lead("text").over(w).alias("next_text"))
    test = F.conv(F.substring(F.md5(F.col("conv_id").cast("string")), 1, 8), 16, 10).cast("long") % 10 == 0
    return rows.filter((F.col("role") == "user") & (F.col("next_role") == "assistant")).select("conv_id", "turn", F.col("text").alias("prompt"), F.col("next_text").alias("completion"), F.when(test, "test").otherwise("train").alias("split"))


def dialogues(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each conversation's last assistant turn, and what was said before it."""
    rows = table(spark, sf_dir, "conversations")
    last = rows.filter("role = 'assistant'").groupBy("conv_id").agg(F.max("turn").alias("last"))
    both = rows.join(last, "conv_id").filter("turn <= last")
    lines = F.array_sort(F.collect_list(F.when(F.col("turn") < F.col("last"), F.struct("turn", "text"))))
    out = both.groupBy("conv_id").agg(F.array_join(F.transform(lines, lambda x: x["text"]), "\n").alias("history"), F.max(F.when(F.col("turn") == F.col("last"), F.col("text"))).alias("reference"))
    test = F.conv(F.substring(F.md5(F.col("conv_id").cast("string")), 1, 8), 16, 10).cast("long") % 10 == 0
    return out.withColumn("split", F.when(test, "test").otherwise("train"))


def domains(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents by use: sources 0-14 train, one in ten held out as three in-domain tests, sources 15-19 three tests out of domain."""
    n = F.regexp_extract("source", r"(\d+)$", 1).cast("int")
    held = F.conv(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 8), 16, 10).cast("long") % 10 == 0
    inside = F.when(n < 5, "in_a").when(n < 10, "in_b").otherwise("in_c")
    outside = F.when(n < 17, "out_a").when(n < 19, "out_b").otherwise("out_c")
    return table(spark, sf_dir, "documents").select("doc_id", "source", "lang", "text", F.when(n >= 15, outside).when(held, inside).otherwise("train").alias("domain"))


def line_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four standardised columns of lineitem; the class is the return flag. Keys repeat, so rows are told apart by all columns."""
    rows = table(spark, sf_dir, "lineitem")
    names = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]
    stats = rows.agg(*[F.avg(c).alias(f"{c}_m") for c in names], *[F.stddev_pop(c).alias(f"{c}_s") for c in names])
    z = [(F.col(c) - F.col(f"{c}_m")) / F.col(f"{c}_s") for c in names]
    label = F.when(F.col("l_returnflag") == "A", 0).when(F.col("l_returnflag") == "N", 1).otherwise(2)
    return rows.crossJoin(F.broadcast(stats)).select(F.xxhash64(*rows.columns).alias("sample_id"), F.array(*z).alias("vec"), label.alias("label"))


def unit(rows: DataFrame) -> DataFrame:
    return rows.withColumn("vec", X.normalise(F.col("vec")))
