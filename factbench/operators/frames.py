"""Evenly spaced frames of ordered sequences, and transcripts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def even(df: DataFrame, key: str, order: list[str], n: int = 5) -> DataFrame:
    """The rows at places floor((2i + 1) * length / (2n)) for i below n; all rows of sequences no longer than n."""
    by = Window.partitionBy(key)
    placed = df.withColumn("place", F.row_number().over(by.orderBy(*order)) - 1).withColumn("length", F.count(F.lit(1)).over(by))
    wanted = F.array(*[F.floor((2 * i + 1) * F.col("length") / (2 * n)) for i in range(n)])
    return placed.filter(F.array_contains(wanted, F.col("place").cast("long")))


def transcript(df: DataFrame, key: str, order: str, text: str = "text", speaker: str = "role") -> DataFrame:
    """(key, n, transcript): the texts of a sequence in order, a line each, with their speakers."""
    items = F.array_sort(F.collect_list(F.struct(F.col(order).alias("o"), F.col(speaker).alias("s"), F.col(text).alias("t"))))
    lines = F.transform(items, lambda x: F.concat(x["s"], F.lit(": "), x["t"]))
    return df.groupBy(key).agg(F.count(F.lit(1)).alias("n"), F.array_join(lines, "\n").alias("transcript"))
