"""Rankings of systems: ranks inside search arms, gaps to the best, gains from search."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def rank(table: DataFrame, metric: str = "mse", block: str = "search", lower_is_better: bool = True) -> DataFrame:
    """Dense rank of systems in each block, the best marked, then the second best."""
    order = F.col(metric).asc() if lower_is_better else F.col(metric).desc()
    out = table.withColumn("rank", F.dense_rank().over(Window.partitionBy(block).orderBy(order)))
    return out.withColumn("mark", F.when(F.col("rank") == 1, "best").when(F.col("rank") == 2, "second").otherwise(""))


def gaps(table: DataFrame, metric: str = "mse", block: str = "search") -> DataFrame:
    """Distance of each system to the best of its block, and of the best to the second."""
    by = Window.partitionBy(block)
    ranked = table.withColumn("_r", F.dense_rank().over(by.orderBy(metric)))
    best, second = F.min(metric).over(by), F.min(F.when(F.col("_r") == 2, F.col(metric))).over(by)
    return ranked.select("system", block, metric, F.round(F.col(metric) - best, 6).alias("gap"), F.round(second - best, 6).alias("lead"))


def search_gain(table: DataFrame, metric: str = "mse") -> DataFrame:
    """Error without search less error with it, by system."""
    arm = lambda s: F.max(F.when(F.col("search") == s, F.col(metric)))
    return table.groupBy("system").agg(F.round(arm(False), 6).alias("without"), F.round(arm(True), 6).alias("with"), F.round(arm(False) - arm(True), 6).alias("gain"))
