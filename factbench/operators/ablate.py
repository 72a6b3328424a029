"""Comparing two runs of the pipeline over the same claims."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from factbench.functions import text
from factbench.operators.metrics import mae, mse


def compare_runs(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: claims in both, squared and absolute difference, correlation, share of equal decisions.

    Both have (claim_id, score).
    """
    both = a.select("claim_id", F.col("score").alias("sa")).join(b.select("claim_id", F.col("score").alias("sb")), "claim_id")
    from factbench.functions.scores import decide

    return both.agg(
        F.count(F.lit(1)).alias("n"), F.round(mse("sa", "sb"), 6).alias("mse"), F.round(mae("sa", "sb"), 6).alias("mae"), F.round(F.corr("sa", "sb"), 6).alias("correlation"),
        F.round(F.avg((decide("sa") == decide("sb")).cast("double")), 6).alias("same_decision"),
    )


def compare_texts(a: DataFrame, b: DataFrame) -> DataFrame:
    """(claim_id, jaccard, distance): word overlap and edit distance of two versions of each claim's text."""
    both = a.select("claim_id", F.col("text").alias("ta")).join(b.select("claim_id", F.col("text").alias("tb")), "claim_id")
    return both.select("claim_id", F.round(text.jaccard(text.words("ta"), text.words("tb")), 6).alias("jaccard"), F.levenshtein("ta", "tb").alias("distance"))
