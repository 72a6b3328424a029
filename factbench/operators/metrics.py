"""Errors of scores: squared, absolute, binned; subsets, confusions, class bias. All are mergeable sums in one pass."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from factbench.functions.scores import bin_index, clip


def _c(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def mse(pred: Column | str, truth: Column | str) -> Column:
    return F.avg((_c(pred) - _c(truth)) * (_c(pred) - _c(truth)))


def mae(pred: Column | str, truth: Column | str) -> Column:
    return F.avg(F.abs(_c(pred) - _c(truth)))


def bin_accuracy(pred: Column | str, truth: Column | str, n: int) -> Column:
    """Per cent of scores in their truth's bin."""
    return 100.0 * F.avg((bin_index(pred, n) == bin_index(truth, n)).cast("double"))


def measures(pred: str = "score", truth: str = "truth") -> list[Column]:
    return [
        F.count(_c(pred) - _c(truth)).alias("n"),
        F.round(mse(pred, truth), 6).alias("mse"),
        F.round(mae(pred, truth), 6).alias("mae"),
        F.round(bin_accuracy(pred, truth, 7), 6).alias("acc7"),
        F.round(bin_accuracy(pred, truth, 3), 6).alias("acc3"),
    ]


def evaluate(df: DataFrame, by: list[str] | None = None, pred: str = "score", truth: str = "truth") -> DataFrame:
    """n, mse, mae, acc7 and acc3, overall or by columns, in one aggregation."""
    return df.groupBy(*(by or [])).agg(*measures(pred, truth))


def sanitize(pred: DataFrame, score: str = "score") -> DataFrame:
    """Scores clipped to [-1, 1], NaN as null."""
    return pred.withColumn(score, clip(F.when(~F.isnan(score), F.col(score))))


def repeated_predictions(pred: DataFrame, keys: list[str]) -> DataFrame:
    """Violations: keys with more than one prediction."""
    return pred.groupBy(*keys).agg(F.count(F.lit(1)).alias("n")).filter("n > 1")


def align(pred: DataFrame, truth: DataFrame, by: list[str], missing: str = "exclude") -> DataFrame:
    """A row for every (by, claim of ``truth``): unanswered claims count as 0, or are left null and so excluded.

    ``covered`` tells them apart, for the coverage that goes with any error.
    """
    asked = truth
    if by:  # the systems, few as they are, come as one array; each claim is expanded in place
        systems = pred.select(F.struct(*by).alias("s")).distinct().agg(F.collect_list("s").alias("_systems"))
        asked = truth.crossJoin(F.broadcast(systems)).select(*truth.columns, F.inline("_systems"))
    out = asked.join(pred.withColumn("covered", F.lit(True)), [*by, "claim_id"], "left").withColumn("covered", F.coalesce("covered", F.lit(False)))
    return out.withColumn("score", F.coalesce("score", F.lit(0.0))) if missing == "zero" else out


def confusion(df: DataFrame, n: int, pred: str = "score", truth: str = "truth") -> DataFrame:
    """(truth_bin, pred_bin, count, row_percent) for all n x n cells."""
    half = (n - 1) // 2
    spark = df.sparkSession
    bins = spark.createDataFrame([(t, p) for t in range(-half, half + 1) for p in range(-half, half + 1)], "truth_bin int, pred_bin int")
    counts = df.groupBy(bin_index(truth, n).alias("truth_bin"), bin_index(pred, n).alias("pred_bin")).agg(F.count(F.lit(1)).alias("count"))
    dense = F.broadcast(bins).join(counts, ["truth_bin", "pred_bin"], "left").withColumn("count", F.coalesce("count", F.lit(0)))
    total = F.sum("count").over(Window.partitionBy("truth_bin"))
    return dense.withColumn("row_percent", F.when(total > 0, F.round(100.0 * F.col("count") / total, 6)))


def confusion_wide(df: DataFrame, n: int) -> DataFrame:
    half = (n - 1) // 2
    return confusion(df, n).groupBy("truth_bin").pivot("pred_bin", list(range(-half, half + 1))).agg(F.first("count"))


#: Subsets of claims: name and the condition for being in it. A claim with both kinds of media is in both.
SUBSETS = (
    ("images", "has_image"), ("videos", "has_video"), ("text_only", "not has_image and not has_video"),
    ("english", "english"), ("other_language", "not english"), ("intact", "truth > 1.0/3"), ("compromised", "truth <= 1.0/3"), ("all", "true"),
)


def subsets(df: DataFrame, by: list[str]) -> DataFrame:
    """mse and n by subset: each row is expanded into the subsets it is in, then aggregated once."""
    names = F.filter(F.array(*[F.when(F.expr(where), F.lit(name)) for name, where in SUBSETS]), lambda s: s.isNotNull())
    return df.withColumn("subset", F.explode(names)).groupBy(*by, "subset").agg(F.count(F.lit(1)).alias("n"), F.round(mse("score", "truth"), 6).alias("mse"))


def subset_cube(df: DataFrame, by: list[str]) -> DataFrame:
    """The same by grouping sets over language and class: one scan, map-side combined."""
    return df.cube(*by).agg(F.count(F.lit(1)).alias("n"), F.round(mse("score", "truth"), 6).alias("mse"), F.grouping_id().alias("level"))


def subset_rollup(df: DataFrame, by: list[str]) -> DataFrame:
    """Totals of a hierarchy, such as quarter and system: one scan, fewer groups than the cube."""
    return df.rollup(*by).agg(F.count(F.lit(1)).alias("n"), F.round(mse("score", "truth"), 6).alias("mse"), F.grouping_id().alias("level"))


def by_property(long: DataFrame) -> DataFrame:
    """Measures for each low-level property of (property, score, truth) rows."""
    return evaluate(long, ["property"])


def class_bias(df: DataFrame, by: list[str]) -> DataFrame:
    """Bias toward one class: MSE by class and their difference, mean signed error, share predicted negative."""
    good = F.col("truth") > 1.0 / 3
    err = (F.col("score") - F.col("truth")) * (F.col("score") - F.col("truth"))
    return df.groupBy(*by).agg(
        F.round(F.avg(F.when(good, err)), 6).alias("mse_intact"), F.round(F.avg(F.when(~good, err)), 6).alias("mse_compromised"),
        F.round(F.avg(F.when(good, err)) - F.avg(F.when(~good, err)), 6).alias("difference"),
        F.round(F.avg(F.col("score") - F.col("truth")), 6).alias("signed_error"), F.round(F.avg((F.col("score") < -1.0 / 3).cast("double")), 6).alias("negative_share"),
    )
