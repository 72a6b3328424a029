"""What each stage keeps, drops and leaves pending, and what it costs in model calls."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def report(stages: DataFrame) -> DataFrame:
    """(stage, reason, n, entered, processed, rate_entered, rate_processed) from a row per record.

    ``stages`` has (stage, status, reason) with status kept, dropped or pending. Rates are per cent of what
    entered a stage and of what it has processed, as a stage may have a backlog.
    """
    counts = stages.groupBy("stage", "status", F.coalesce("reason", F.lit("")).alias("reason")).agg(F.count(F.lit(1)).alias("n"))
    by = Window.partitionBy("stage")
    out = counts.withColumn("entered", F.sum("n").over(by)).withColumn("processed", F.sum(F.when(F.col("status") != "pending", F.col("n")).otherwise(0)).over(by))
    rate = lambda base: F.when(F.col(base) > 0, F.round(100.0 * F.col("n") / F.col(base), 6))
    return out.withColumn("rate_entered", rate("entered")).withColumn("rate_processed", F.when(F.col("status") != "pending", rate("processed")))


def marked(df: DataFrame, stage: str, status, reason=None) -> DataFrame:
    """A narrow (stage, status, reason) row per record."""
    return df.select(F.lit(stage).alias("stage"), status.alias("status"), (reason if reason is not None else F.lit(None)).cast("string").alias("reason"))


def union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def cumulative(kept: DataFrame) -> DataFrame:
    """End-to-end yield from (step, stage, entered, kept): the product of stage yields so far."""
    over = Window.orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    return kept.withColumn("stage_yield", F.round(F.try_divide("kept", "entered"), 6)).withColumn("total_yield", F.round(F.exp(F.sum(F.log(F.try_divide("kept", "entered"))).over(over)), 6))


def calls(kept: DataFrame, per_record: dict[str, int]) -> DataFrame:
    """Model calls at each stage given its filters so far, against calls without any earlier filter."""
    cost = F.create_map(*[x for k, v in per_record.items() for x in (F.lit(k), F.lit(v))])
    first = F.first("entered").over(Window.orderBy("step"))
    out = kept.withColumn("calls", F.col("entered") * F.coalesce(cost[F.col("stage")], F.lit(0)))
    return out.withColumn("calls_unfiltered", first * F.coalesce(cost[F.col("stage")], F.lit(0)))
