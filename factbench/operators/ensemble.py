"""Ensembles: mean and spread of members' votes, the agreement filter, single members, justifications."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from factbench.functions.scores import rounded
from factbench.operators import verdict


def combine(votes: DataFrame, by: list[str], members: int = 4) -> DataFrame:
    """Mean, least, greatest and spread of scores in one pass with map-side combination; ``complete`` if all members voted."""
    return (
        votes.groupBy(*by)
        .agg(F.avg("score").alias("mean"), F.min("score").alias("low"), F.max("score").alias("high"), F.count("score").alias("n_votes"))
        .withColumn("mean", F.round("mean", 9))  # four scores of six places: no ties
        .withColumn("spread", F.round(F.col("high") - F.col("low"), 6))
        .withColumn("complete", F.col("n_votes") >= members)
    )


def combine_wide(wide: DataFrame, members: list[str]) -> DataFrame:
    """The same from a row per claim with a column per member: in place, no shuffle. Null votes count as not given."""
    votes = F.array_compact(F.array(*members))
    told = wide.withColumn("_votes", votes)
    total = F.aggregate("_votes", F.lit(0.0), lambda s, x: s + x)
    out = told.withColumns({"mean": F.round(F.try_divide(total, F.size("_votes")), 9), "low": F.array_min("_votes"), "high": F.array_max("_votes"), "n_votes": F.size("_votes").cast("long")})
    return out.drop("_votes").withColumn("spread", F.round(F.col("high") - F.col("low"), 6)).withColumn("complete", F.col("n_votes") >= len(members))


def _where(df: DataFrame, keep, in_place: bool) -> DataFrame:
    """A filter; in place as a generator, through which the optimizer doesn't push the condition, so that scorers run once."""
    return df.select(F.inline(F.array_compact(F.array(F.when(keep, F.struct(*df.columns)))))) if in_place else df.filter(keep)


def filter_agreement(df: DataFrame, max_spread: float = 1.0, in_place: bool = False) -> DataFrame:
    """Rows whose members differ by no more than ``max_spread``; a spread of exactly that stays. ``in_place`` for scores still to be computed."""
    return _where(df, F.col("spread") <= max_spread, in_place)


def dropped_by_spread(df: DataFrame, max_spread: float = 1.0, in_place: bool = False) -> DataFrame:
    return _where(df, F.col("spread") > max_spread, in_place)


def single(votes: DataFrame, member: str) -> DataFrame:
    return votes.filter(F.col("member") == member)


def justify(votes: DataFrame, by: list[str]) -> DataFrame:
    """The justification of the member nearest to the mean (earliest by name on ties), and all members' texts in order."""
    means = votes.groupBy(*by).agg(F.avg("score").alias("_mean"))
    near = votes.join(means, by).withColumn("_far", rounded(F.abs(F.col("score") - F.col("_mean")), 6))
    return near.groupBy(*by).agg(
        F.min_by("justification", F.struct("_far", "member")).alias("justification"),
        F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("member", "justification"))), lambda v: v["justification"]), " | ").alias("all_justifications"),
    )


def justify_properties(votes: DataFrame, summarizer=None) -> DataFrame:
    """(claim_id, one justification per property) from (claim_id, member, property, score, justification) votes.

    ``summarizer`` is a column binding of an array of the members' texts and one of their scores, both in the order of
    members; the local one takes the text of the member nearest to the mean, the earliest of several.
    """
    given = votes.filter("score is not null").groupBy("claim_id", "property").agg(F.array_sort(F.collect_list(F.struct("member", "score", "justification"))).alias("_v"), F.avg("score").alias("_mean"))
    if summarizer is None:
        near = F.array_min(F.transform("_v", lambda v: F.struct(F.round(F.abs(v["score"] - F.col("_mean")), 6).alias("far"), v["member"].alias("member"), v["justification"].alias("text"))))
        text = near["text"]
    else:
        text = summarizer(F.transform("_v", lambda v: v["justification"]), F.transform("_v", lambda v: v["score"]))
    one = given.select("claim_id", "property", text.alias("_text"))
    return one.groupBy("claim_id").agg(*[F.max(F.when(F.col("property") == p, F.col("_text"))).alias(f"{p}_justification") for p in verdict.ORDER])


def justify_integrity(verdicts: DataFrame, justifications: DataFrame) -> DataFrame:
    """Verdicts with the justification of each property and, as that of the integrity, the compromising property's."""
    told = verdicts.join(justifications, "claim_id", "left")
    chosen = F.coalesce(*[F.when(F.col("compromising") == p, F.col(f"{p}_justification")) for p in verdict.ORDER])
    return told.withColumn("justification", chosen)


def integrity_votes(votes: DataFrame, order: str = "mean_then_min", gate: str = "ensemble") -> DataFrame:
    """Integrity of claims from wide votes (claim_id, member, contextualization, veracity, coverage).

    ``mean_then_min`` averages each property over members, then takes the least; ``min_then_mean`` averages the
    members' own integrity. ``gate`` says whose decision ends evaluation: the ensemble's or each member's.
    """
    cols = [F.col(c) for c in verdict.ORDER]
    ctx, ver, cov = verdict.evaluated(*cols, early_stop=gate == "member")
    own = votes.withColumns(dict(zip(verdict.ORDER, (ctx, ver, cov), strict=True))).withColumn("own", verdict.integrity(*[F.col(c) for c in verdict.ORDER]))
    sums = own.groupBy("claim_id").agg(
        *[F.avg(c).alias(c) for c in verdict.ORDER], F.avg("own").alias("mean_of_mins"), (F.max("own") - F.min("own")).alias("spread")
    )
    ctx, ver, cov = verdict.evaluated(*[F.col(c) for c in verdict.ORDER], early_stop=gate == "ensemble")
    out = sums.withColumn("min_of_means", verdict.integrity(ctx, ver, cov))
    chosen = F.col("min_of_means") if order == "mean_then_min" else F.col("mean_of_mins")
    return out.withColumn("integrity", F.round(chosen, 9)).withColumn("spread", F.round("spread", 6))  # means of scores of six places: no ties


def standardize(votes: DataFrame) -> DataFrame:
    """Stage 6 from members' property votes: (claim_id, the evaluated properties, integrity, spread, compromising, label).

    Means over members, early stopping by the ensemble's own decisions, the least property as integrity. ``spread`` is
    the difference of the members' own integrities, for ``filter_agreement``.
    """
    sums = integrity_votes(votes).select("claim_id", *[F.round(c, 9).alias(c) for c in verdict.ORDER], "integrity", "spread")
    cols = dict(zip(verdict.ORDER, verdict.evaluated(*[F.col(c) for c in verdict.ORDER]), strict=True))
    out = sums.withColumns(cols)
    return out.withColumn("compromising", verdict.compromising({c: F.col(c) for c in verdict.ORDER})).withColumn("label", verdict.label("integrity"))


def property_spread(votes: DataFrame) -> DataFrame:
    """The largest spread of any evaluated property, for the stricter scope of the agreement filter."""
    spreads = votes.groupBy("claim_id").agg(*[(F.max(c) - F.min(c)).alias(c) for c in verdict.ORDER])
    return spreads.select("claim_id", F.round(F.greatest(*[F.col(c) for c in verdict.ORDER]), 6).alias("spread"))
