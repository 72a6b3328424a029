"""Knowledge cutoffs: error before and after, smoothed curves, the margin to knowing nothing."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def squared():
    return (F.col("score") - F.col("truth")) * (F.col("score") - F.col("truth"))


def daily(pred: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Mergeable partials: (…, day, n, sse). All curves and inflations follow from these few rows."""
    return pred.groupBy(*(by or ["system"]), F.to_date("claim_ts").alias("day")).agg(F.count(squared()).alias("n"), F.sum(squared()).alias("sse"))


def inflation(pred: DataFrame) -> DataFrame:
    """MSE before and after each system's cutoff, and the rise; from unsmoothed errors."""
    before = F.col("claim_ts") < F.col("cutoff")
    out = pred.groupBy("system").agg(F.avg(F.when(before, squared())).alias("b"), F.avg(F.when(~before, squared())).alias("a"))
    return out.select("system", F.round("b", 6).alias("mse_before"), F.round("a", 6).alias("mse_after"), F.round(F.col("a") - F.col("b"), 6).alias("inflation"))


def curve(pred: DataFrame, half_width: int = 45, mode: str = "centred", where: str | None = None) -> DataFrame:
    """(system, day, mse, after): moving average of the squared error by claim date, as a ratio of sums over days.

    ``centred`` takes ``half_width`` days on both sides, ``trailing`` twice as many before. ``after`` tells the
    part past the cutoff.
    """
    rows = pred.filter(where) if where else pred
    days = rows.groupBy("system", "cutoff", F.to_date("claim_ts").alias("day")).agg(F.count(squared()).alias("n"), F.sum(squared()).alias("sse"))
    days = days.withColumn("_day", F.datediff("day", F.lit("1970-01-01").cast("date")))
    low, high = (-half_width, half_width) if mode == "centred" else (-2 * half_width, 0)
    over = Window.partitionBy("system").orderBy("_day").rangeBetween(low, high)
    return days.select("system", "day", F.round(F.sum("sse").over(over) / F.sum("n").over(over), 6).alias("mse"), (F.col("day") >= F.to_date("cutoff")).alias("after"))


def margin(pred: DataFrame, constant: float = 0.0) -> DataFrame:
    """Each system's margin to always answering ``constant``, before and after its cutoff."""
    before = F.col("claim_ts") < F.col("cutoff")
    base = (F.col("truth") - constant) * (F.col("truth") - constant)
    out = pred.groupBy("system").agg(*[F.avg(F.when(cond, base - squared())).alias(name) for name, cond in (("b", before), ("a", ~before))])
    return out.select("system", F.round("b", 6).alias("margin_before"), F.round("a", 6).alias("margin_after"))
