"""Statistics of a benchmark and its trends by quarter."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def shares(df: DataFrame, col: str, min_share: float = 0.0, other: str = "other") -> DataFrame:
    """(col, n, percent) of each value; values under ``min_share`` per cent fold into ``other``."""
    counts = df.groupBy(col).agg(F.count(F.lit(1)).alias("n"))
    total = F.broadcast(counts.agg(F.sum("n").alias("total")))
    named = counts.crossJoin(total).withColumn(col, F.when(100.0 * F.col("n") / F.col("total") >= min_share, F.col(col)).otherwise(F.lit(other)))
    return named.groupBy(col).agg(F.sum("n").alias("n"), F.round(100.0 * F.sum("n") / F.first("total"), 6).alias("percent"))


def distinct_sketches(df: DataFrame, by: str, col: str, lg: int = 12) -> DataFrame:
    """(by, sketch): a mergeable sketch of the distinct values of each group; store it, and later totals need no second scan."""
    return df.groupBy(by).agg(F.hll_sketch_agg(col, lg).alias("sketch"))


def merged_distinct(sketches: DataFrame) -> DataFrame:
    """(n_distinct, n_groups): distinct values over all groups out of their sketches; exact for a few hundred, within 2 % beyond."""
    return sketches.agg(F.hll_sketch_estimate(F.hll_union_agg("sketch")).alias("n_distinct"), F.count(F.lit(1)).alias("n_groups"))


def frequent(df: DataFrame, col: str, least: int = 50) -> DataFrame:
    """How many values there are, and how many occur at least ``least`` times."""
    counts = df.groupBy(col).agg(F.count(F.lit(1)).alias("n"))
    return counts.agg(F.count(F.lit(1)).alias("n_values"), F.sum((F.col("n") >= least).cast("int")).alias("n_frequent"))


def trend(df: DataFrame, date: str, cat: str) -> DataFrame:
    """(quarter, cat, n, percent, change): the share of each category in its quarter, and its change in points."""
    counts = df.groupBy(F.trunc(date, "quarter").alias("quarter"), cat).agg(F.count(F.lit(1)).alias("n"))
    share = counts.withColumn("percent", F.round(100.0 * F.col("n") / F.sum("n").over(Window.partitionBy("quarter")), 6))
    before = F.lag("percent").over(Window.partitionBy(cat).orderBy("quarter"))
    return share.withColumn("change", F.round(F.col("percent") - before, 6))


def volume(df: DataFrame, date: str) -> DataFrame:
    """(quarter, n, change, peak): reviews per quarter, the change to the one before, and whether it is the peak."""
    counts = df.groupBy(F.trunc(date, "quarter").alias("quarter")).agg(F.count(F.lit(1)).alias("n"))
    order = Window.orderBy("quarter")
    return counts.withColumn("change", F.col("n") - F.lag("n").over(order)).withColumn("peak", F.col("n") == F.max("n").over(Window.partitionBy()))


def class_share(df: DataFrame, flag: Column) -> DataFrame:
    return df.agg(F.round(100.0 * F.avg(flag.cast("double")), 6).alias("percent"), F.count(F.lit(1)).alias("n"))


def spread_quantiles(df: DataFrame, col: str = "spread", accuracy: int = 10000) -> DataFrame:
    """Quartiles of score spreads by a mergeable sketch."""
    return df.agg(*[F.percentile_approx(col, q, accuracy).alias(f"q{int(100 * q)}") for q in (0.25, 0.5, 0.75)])
