"""Agreement with human annotators: truths, the table of ablations, flags, agreement between annotators."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from factbench.operators.ensemble import combine_wide
from factbench.operators.metrics import measures


def annotations(labels: DataFrame) -> DataFrame:
    """(claim_id, annotator, property, score) of two annotators out of the given labels."""
    wide = labels.select(F.col("doc_id").alias("claim_id"), (2.0 * F.col("quality") - 1).alias("H1"), (1 - 2.0 * F.col("toxic")).alias("H2"))
    long = wide.unpivot(["claim_id"], ["H1", "H2"], "annotator", "score")
    return long.withColumn("property", F.when(F.col("annotator") == "H1", "quality").otherwise("toxicity"))


def truth(ann: DataFrame, min_annotators: int = 2, how: str = "mean") -> DataFrame:
    """(claim_id, truth) over annotators, for claims with enough of them: mean, min or median."""
    agg = {"mean": F.avg, "min": F.min, "median": F.median}[how]("score")
    return ann.groupBy("claim_id").agg(agg.alias("truth"), F.count_distinct("annotator").alias("_n")).filter(F.col("_n") >= min_annotators).drop("_n")


def ablations(votes: DataFrame, human: DataFrame, max_spread: float = 1.0) -> DataFrame:
    """Six rows: the filtered ensemble, the unfiltered one, and each member alone, with n and all measures.

    ``votes`` are wide: a row per claim with a column per member. They meet the truth once; every claim is then
    expanded into the settings it counts for and aggregated once.
    """
    names = [c for c in votes.columns if c != "claim_id"]
    wide = combine_wide(votes, names)
    settings = [F.when(F.col("spread") <= max_spread, F.struct(F.lit("filtered").alias("setting"), F.col("mean").alias("score"))), F.struct(F.lit("unfiltered").alias("setting"), F.col("mean").alias("score"))]
    settings += [F.struct(F.lit(name).alias("setting"), F.col(name).alias("score")) for name in names]
    rows = wide.join(human, "claim_id").select("truth", F.inline(F.array_compact(F.array(*settings))))
    return rows.groupBy("setting").agg(*measures())


def sweep(votes: DataFrame, human: DataFrame, spreads: tuple[float, ...] = (0.25, 0.5, 0.75, 1.0, 1.25, 1.5, 1.75, 2.0)) -> DataFrame:
    """Error against the share of claims kept, for several agreement thresholds. ``votes`` are wide."""
    per = combine_wide(votes, [c for c in votes.columns if c != "claim_id"]).select("claim_id", F.col("mean").alias("score"), "spread").join(human, "claim_id")
    each = per.withColumn("threshold", F.explode(F.array(*[F.lit(s) for s in spreads])))
    inside = F.col("spread") <= F.col("threshold")
    err = (F.col("score") - F.col("truth")) * (F.col("score") - F.col("truth"))
    return each.groupBy("threshold").agg(F.round(F.avg(inside.cast("double")), 6).alias("kept_share"), F.round(F.avg(F.when(inside, err)), 6).alias("mse"))


def flag_rate(df: DataFrame, flag: str) -> DataFrame:
    """Per cent of claims that annotators flagged."""
    return df.agg(F.round(100.0 * F.avg(F.col(flag).cast("double")), 6).alias("flagged_percent"), F.count(F.lit(1)).alias("n"))


def pair_agreement(ann: DataFrame) -> DataFrame:
    """The same measures between each pair of annotators of a claim."""
    a = ann.select("claim_id", F.col("annotator").alias("first"), F.col("score"))
    b = ann.select("claim_id", F.col("annotator").alias("second"), F.col("score").alias("truth"))
    return a.join(b, "claim_id").filter("first < second").groupBy("first", "second").agg(*measures())


def weighted_kappa(pairs: DataFrame, a: str, b: str, n: int = 3) -> DataFrame:
    """Quadratic-weighted kappa between two bin columns (0 to n - 1), as a grouped aggregate over Arrow."""

    @F.pandas_udf("double")
    def kappa(x: pd.Series, y: pd.Series) -> float:
        table = pd.crosstab(x, y).reindex(index=range(n), columns=range(n), fill_value=0).to_numpy(float)
        weights = [[(i - j) ** 2 / (n - 1) ** 2 for j in range(n)] for i in range(n)]
        expected = table.sum(1)[:, None] * table.sum(0)[None, :] / max(1.0, table.sum())
        below = (expected * weights).sum()
        return float(1 - (table * weights).sum() / below) if below else 1.0

    return pairs.agg(kappa(a, b).alias("kappa"))


def kappa_by_counts(counts: DataFrame, n: int = 3) -> DataFrame:
    """The same from (a, b, n) counts with built-in functions: the form for large tables."""
    rows = counts.groupBy(F.col("a").alias("ra")).agg(F.sum("n").alias("rn"))
    cols = counts.groupBy(F.col("b").alias("cb")).agg(F.sum("n").alias("cn"))
    w = lambda x, y: (F.col(x) - F.col(y)) * (F.col(x) - F.col(y)) / float((n - 1) ** 2)
    seen = counts.agg(F.sum(F.col("n") * w("a", "b")).alias("o"), F.sum("n").alias("t"))
    due = F.broadcast(rows).crossJoin(F.broadcast(cols)).agg(F.sum(F.col("rn") * F.col("cn") * w("ra", "cb")).alias("e"))
    return seen.crossJoin(due).select(F.round(F.when(F.col("e") > 0, 1 - F.col("o") * F.col("t") / F.col("e")).otherwise(1.0), 6).alias("kappa"))
