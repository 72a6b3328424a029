"""Baselines: constants, local systems with and without evidence, and stand-ins for two kinds of agents.

Neither the hosted models nor the agents can be run here; the stand-ins have their shape, not their skill.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from factbench.functions import text
from factbench.functions.scores import clip
from factbench.operators.judges import wide_votes


def constant(truth: DataFrame, value: float = 0.0, name: str = "constant") -> DataFrame:
    """The same score for every claim; 0 is always-uncertain."""
    return truth.withColumn("system", F.lit(name)).withColumn("score", F.lit(float(value)))


def prior_mean(truth: DataFrame) -> DataFrame:
    """The mean truth of all claims as every claim's score."""
    mean = truth.agg(F.avg("truth").alias("score"))
    return truth.crossJoin(F.broadcast(mean)).withColumn("system", F.lit("prior_mean"))


def parametric(documents: DataFrame, family=text.raw_scorers) -> DataFrame:
    """Local systems that see the claim alone: (claim_id, system, score)."""
    wide = wide_votes(documents, family)
    return wide.unpivot(["claim_id"], wide.columns[1:], "system", "score")


def with_evidence(scores: DataFrame, support: DataFrame, weight: float = 0.5) -> DataFrame:
    """The same systems with search: a score moves toward 1 with retrieved support in [0, 1], toward -1 without."""
    joined = scores.join(support, "claim_id", "left").withColumn("support", F.coalesce("support", F.lit(0.0)))
    return joined.withColumn("score", F.round(moved(F.col("score"), F.col("support"), weight), 6))


def moved(score: Column, support: Column, weight: float = 0.5) -> Column:
    """A score moved toward 1 by retrieved support in [0, 1], toward -1 without."""
    return clip((1 - weight) * score + weight * (2 * F.coalesce(support, F.lit(0.0)) - 1) * F.abs(score))


#: Ends of sentences: the mark stays with its sentence. A pattern without lookbehind, for engines that lack it.
SENTENCE = r"[^.!?]*[.!?]+|[^.!?]+$"


def sentences(documents: DataFrame) -> DataFrame:
    """(claim_id, part_id, text): the sentences of each claim that hold more than blanks; ``part_id`` is claim and place in one number."""
    parts = documents.select(F.col("doc_id").alias("claim_id"), F.posexplode(F.regexp_extract_all("text", F.lit(SENTENCE), F.lit(0))).alias("place", "text"))
    return parts.filter("trim(translate(text, '\n\t\r', '   ')) != ''").select("claim_id", F.concat_ws(":", "claim_id", "place").alias("part_id"), "text")


def backbones(family: dict[str, Column]) -> dict[str, Column]:
    """Three local backbones of agents: the mean of all members, the last member, and the least of the last two."""
    names = list(family)
    return {"b1": sum((F.col(n) for n in names[1:]), F.col(names[0])) / len(names), "b2": F.col(names[-1]), "b3": F.least(F.col(names[-1]), F.col(names[-2]))}


def stepwise(documents: DataFrame, found: Callable[[DataFrame], DataFrame], name: str = "stepwise") -> DataFrame:
    """(claim_id, system, score): an agent that checks a claim sentence by sentence, with evidence for each, and keeps the worst.

    ``found`` maps (claim_id, text) queries, which are the sentences, to (claim_id, support) in [0, 1]. One row for each of three
    backbones; claims without a sentence have none.
    """
    parts = sentences(documents)
    support = found(parts.select(F.col("part_id").alias("claim_id"), "text")).withColumnsRenamed({"claim_id": "part_id", "support": "_support"})
    scored = text.with_scores(parts, "text").join(support, "part_id", "left")
    each = [F.round(F.min(moved(score, F.col("_support"))), 6).alias(f"{name}_{b}") for b, score in backbones(text.raw_scorers()).items()]
    wide = scored.groupBy("claim_id").agg(*each)
    return wide.unpivot(["claim_id"], wide.columns[1:], "system", "score")


def multi_check(documents: DataFrame, found: Callable[[DataFrame], DataFrame], name: str = "multi_check") -> DataFrame:
    """(claim_id, system, score): an agent that runs several checks on a whole claim, each with its evidence, and averages them.

    The checks are its backbone's own view, the view of every member moved by the claim's evidence, and the worst of
    these. One row for each of three backbones.
    """
    claims = documents.select(F.col("doc_id").alias("claim_id"), "text")
    support = found(claims).withColumnRenamed("support", "_support")
    scored = text.with_scores(claims, "text").join(support, "claim_id", "left")
    members = list(text.raw_scorers())
    checks = [moved(F.col(m), F.col("_support")) for m in members]
    wide = scored.select("claim_id", *[F.round((score + sum(checks[1:], checks[0]) / len(checks) + F.least(*checks)) / 3, 6).alias(f"{name}_{b}") for b, score in backbones(text.raw_scorers()).items()])
    return wide.unpivot(["claim_id"], wide.columns[1:], "system", "score")
