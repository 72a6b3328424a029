"""Verdicts: four properties in order, early stopping, integrity, the compromising property, labels.

Property 1, authenticity, and 2, contextualization, belong to media; 3, veracity, and 4, context coverage, to
the claim. Integrity is the least of 2 to 4. Claims without media begin at veracity.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from factbench.functions.scores import EDGE
from factbench.sources.io import small

#: Properties that bear on integrity, in evaluation order.
ORDER = ("contextualization", "veracity", "coverage")


def map_rating(df: DataFrame, raw: str, table: DataFrame, out: str = "score") -> DataFrame:
    """Heterogeneous rating strings to scores through a small table (raw, score), compared trimmed and lower-cased."""
    key = F.lower(F.trim(F.col(raw)))
    known = small(table.select(F.lower(F.trim("raw")).alias("_raw"), F.col("score").alias(out)))
    return df.join(known, key == F.col("_raw"), "left").drop("_raw")


def over_media(media: DataFrame, how: str = "min", order: Sequence[str] = ()) -> DataFrame:
    """Media scores of a claim: the least (or, as an ablation, the mean) over its items.

    The last bit of a mean of doubles depends on which are added first, and a mean at a bound of the labels turns on it;
    columns in ``order`` settle that, where without them it is up to the splits of the scan.
    """
    if how == "mean" and order:
        w = Window.partitionBy("claim_id").orderBy(*order)
        so_far = w.rowsBetween(Window.unboundedPreceding, Window.currentRow)
        means = [F.avg(c).over(so_far).alias(c) for c in ("authenticity", "contextualization")]
        run = media.select("claim_id", *means, F.row_number().over(w).cast("long").alias("n_media"), F.lead(F.lit(True)).over(w).alias("_more"))
        return run.filter(F.col("_more").isNull()).drop("_more")
    agg = {"min": F.min, "mean": F.avg}[how]
    return media.groupBy("claim_id").agg(agg("authenticity").alias("authenticity"), agg("contextualization").alias("contextualization"), F.count(F.lit(1)).alias("n_media"))


def evaluated(ctx: Column, ver: Column, cov: Column, early_stop: bool = True) -> tuple[Column, Column, Column]:
    """The properties that get evaluated; a negative decision ends evaluation."""
    if not early_stop:
        return ctx, ver, cov
    first = F.coalesce(ctx, F.lit(1.0)) < -EDGE
    ver = F.when(~first, ver)
    return ctx, ver, F.when(~first & ~(F.coalesce(ver, F.lit(1.0)) < -EDGE), cov)


def integrity(*scores: Column) -> Column:
    return F.least(*scores)


def compromising(scores: dict[str, Column], latest: bool = False) -> Column:
    """The property with the least score; ties go to the earliest (or the latest) in evaluation order."""
    low, out = F.least(*scores.values()), F.lit(None).cast("string")
    for name, score in scores.items() if latest else reversed(scores.items()):
        out = F.when(score == low, name).otherwise(out)
    return out


def label(score: Column | str, mode: str = "three") -> Column:
    """intact above 1/3; compromised below -1/3, or (mode ``two``) whenever not intact; else uncertain."""
    s = F.col(score) if isinstance(score, str) else score
    if mode == "two":
        return F.when(s > EDGE, "intact").when(s.isNotNull(), "compromised")
    return F.when(s > EDGE, "intact").when(s < -EDGE, "compromised").when(s.isNotNull(), "uncertain")


def verdicts(claims: DataFrame, media: DataFrame | None, early_stop: bool = True, how: str = "min", mode: str = "three", order: Sequence[str] = ()) -> DataFrame:
    """Claims with evaluated properties, integrity, compromising property and label. One shuffle of narrow media rows."""
    if media is None:
        joined = claims.withColumns({"authenticity": F.lit(None).cast("double"), "contextualization": F.lit(None).cast("double"), "n_media": F.lit(0).cast("long")})
    else:
        joined = claims.join(over_media(media, how, order), "claim_id", "left").withColumn("n_media", F.coalesce("n_media", F.lit(0)))
    ctx, ver, cov = evaluated(*[F.col(c) for c in ORDER], early_stop)
    out = joined.withColumns({"contextualization": ctx, "veracity": ver, "coverage": cov})
    out = out.withColumn("integrity", integrity(*[F.col(c) for c in ORDER]))
    return out.withColumn("compromising", compromising({c: F.col(c) for c in ORDER})).withColumn("label", label("integrity", mode))


def call_savings(claims: DataFrame, media: DataFrame, members: int = 4) -> DataFrame:
    """Scorer calls with and without early stopping: one row (with_stop, without_stop, ratio)."""
    per = claims.join(over_media(media), "claim_id", "left")
    ctx, ver, _ = evaluated(*[F.col(c) for c in ORDER])
    m = F.coalesce("n_media", F.lit(0))
    second, third = ~(F.coalesce(ctx, F.lit(1.0)) < -EDGE), F.coalesce(ver >= -EDGE, F.lit(False))
    calls = members * (2 * m + second.cast("int") + (second & third).cast("int"))
    sums = per.agg(F.sum(calls).alias("with_stop"), F.sum(members * (2 * m + 2)).alias("without_stop"))
    return sums.withColumn("ratio", F.round(F.col("with_stop") / F.col("without_stop"), 6))
