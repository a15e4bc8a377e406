"""What is handed to a trainer: shards by column values, graphs in buckets of the id that they are joined by."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def by_columns(rows: DataFrame, path: str, columns: list[str], per_file: int = 1_000_000, parts: int = 8, mode: str = "errorifexists") -> None:
    """A folder for each value; rows are dealt by value and a salt, so that a value that holds many rows is written by several tasks in files of a bounded number of rows."""
    salt = F.pmod(F.xxhash64(*rows.columns), F.lit(parts))
    rows.repartition(*[F.col(c) for c in columns], salt).write.partitionBy(*columns).option("maxRecordsPerFile", per_file).mode(mode).parquet(path)


def in_buckets(rows: DataFrame, table: str, column: str, buckets: int = 8, path: str | None = None, mode: str = "errorifexists") -> None:
    """A table of sorted buckets, of which joins and groupings on the column need no shuffle."""
    out = rows.write.bucketBy(buckets, column).sortBy(column).mode(mode).format("parquet")
    (out.option("path", path) if path else out).saveAsTable(table)
