"""Pluggable model interfaces: where hosted models would be called, and their local stand-ins.

A column binding stays in code generation. Every interface also has a batch binding, ``in_batches``: it runs over pandas
frames in ``mapInPandas`` with a declared schema; a failed batch is tried again and then marked in a failure column, not
raised.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from typing import Protocol

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from factbench.functions import text as texts
from factbench.functions.scores import rounded


class Scorer(Protocol):
    """Scores of claims: a frame in, the same rows with ``score`` in [-1, 1] and ``justification`` out."""

    def __call__(self, frame: pd.DataFrame) -> pd.DataFrame: ...


class Rewriter(Protocol):
    """Texts of claims rewritten: a column binding from the raw text and, if asked for, article, appearance, claimant and date."""

    def __call__(self, raw: Column, *context: Column) -> Column: ...


class Validator(Protocol):
    """Reasons against a claim: an array column, empty if it is valid."""

    def __call__(self, text: Column, n_media: Column) -> Column: ...


class Summarizer(Protocol):
    """One text out of several justifications and their scores."""

    def __call__(self, justifications: Column, scores: Column) -> Column: ...


class RelevanceJudge(Protocol):
    """Whether a media item belongs to its claim: a boolean column."""

    def __call__(self, claim: Column, media: Column) -> Column: ...


class SpanDetector(Protocol):
    """The (start, end) of the article in a page's source: a struct column."""

    def __call__(self, html: Column) -> Column: ...


class LinkExtractor(Protocol):
    """URLs of appearances in an article: an array column."""

    def __call__(self, text: Column, html: Column) -> Column: ...


def wide_votes(documents: DataFrame, family: Callable[[], dict[str, Column]] = texts.raw_scorers) -> DataFrame:
    """(claim_id, J1, ..., J4) of the local members, by column expressions: no shuffle, no Python."""
    told = texts.with_scores(documents.select(F.col("doc_id").alias("claim_id"), "text"), "text", family)
    return told.drop("text")


def justified(member: Column, score: Column) -> Column:
    """What a local member says for itself."""
    return F.concat_ws(" ", member, F.lit("scores"), rounded(score, 3).cast("string"))


def local_votes(documents: DataFrame, family: Callable[[], dict[str, Column]] = texts.raw_scorers) -> DataFrame:
    """(claim_id, member, score, justification) of the local members: the long form of ``wide_votes``."""
    wide = wide_votes(documents, family)
    long = wide.unpivot(["claim_id"], wide.columns[1:], "member", "score")
    return long.withColumn("justification", justified(F.col("member"), F.col("score")))


def attempted(work: Callable[[pd.DataFrame], pd.DataFrame], out: dict[str, str], attempts: int = 2, calls=None):
    """A batch of a hosted model as a function for ``mapInPandas``: tried again when it fails, then marked in ``failure``, not raised."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            result = frame.copy()
            for name in out:
                result[name] = None
            result["failure"] = None
            for attempt in range(attempts):
                try:
                    if calls is not None:
                        calls.add(len(frame))
                    told = work(frame)
                    for name in out:
                        result[name] = told[name].to_numpy() if told[name].dtype != object else told[name].tolist()
                    result["failure"] = None
                    break
                except Exception as error:  # any failure of a model is a result, not the end of the job
                    result["failure"] = f"attempt {attempt + 1}: {error}"
            for name, kind in out.items():
                if kind == "double":
                    result[name] = result[name].astype("float64")
            yield result

    return run


def in_batches(df: DataFrame, model: Callable[[pd.DataFrame], pd.DataFrame], out: dict[str, str], needs: list[str], key: str = "claim_id", attempts: int = 2, calls=None) -> DataFrame:
    """The batch binding of any interface here: (key, new columns, failure).

    ``model`` gets a frame of ``key`` and the columns it ``needs``, in Arrow batches, and returns a frame with the columns
    of ``out`` (name to SQL type): ``claim`` from a rewriter, ``reasons`` from a validator, ``summary`` from a
    summarizer, ``relevant`` from a relevance judge, ``start`` and ``end`` from a span detector, ``urls`` from a link
    extractor, ``score`` and ``justification`` from a scorer.
    """
    rows = df.select(key, *needs)
    kinds = [f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields] + [f"`{n}` {k}" for n, k in out.items()] + ["failure string"]
    return rows.mapInPandas(attempted(model, out, attempts, calls), ", ".join(kinds)).drop(*needs)


def judged(media: DataFrame, judge: RelevanceJudge, needs: list[str], key: str = "media_id", **options) -> tuple[DataFrame, DataFrame]:
    """(kept, failed): media that a batch relevance judge keeps, and those it could not judge, with the failure."""
    told = in_batches(media, judge, {"relevant": "boolean"}, needs, key, **options)
    return media.join(told.filter("relevant").select(key), key, "left_semi"), told.filter("failure is not null").select(key, "failure")


def scored(df: DataFrame, scorer: Scorer, member: str, key: str = "claim_id", attempts: int = 2, calls=None) -> DataFrame:
    """Run a batch scorer: (key, member, score, justification, failure). ``calls`` is an accumulator of rows sent to it."""
    told = in_batches(df, scorer, {"score": "double", "justification": "string"}, [c for c in df.columns if c != key], key, attempts, calls)
    return told.select(key, F.lit(member).alias("member"), "score", "justification", "failure")


def staged(df: DataFrame, steps: list[tuple[str, Scorer]], key: str, store: Callable[[DataFrame], DataFrame], edge: float = -1 / 3, calls=None) -> DataFrame:
    """Scorers in order, each called for survivors alone: rows leave at the first negative decision.

    ``store`` writes and rereads a step's result (or persists it), so that no step runs twice. Wide result: key
    and a score column for each step, null where evaluation had ended.
    """
    rows, done = df, df.select(key)
    for name, scorer in steps:
        step = store(scored(rows, scorer, name, key, calls=calls))
        done = done.join(step.select(key, F.col("score").alias(name)), key, "left")
        rows = rows.join(step.filter(F.col("score") >= edge).select(key), key, "left_semi")
    return done


def rating_table(spark: SparkSession) -> DataFrame:
    """The rating strings of the given orders as scores. Fixed values."""
    pairs = [("1-URGENT", 1.0), ("2-HIGH", 0.5), ("3-MEDIUM", 0.0), ("4-NOT SPECIFIED", -0.5), ("5-LOW", -1.0)]
    return spark.createDataFrame(pairs, "raw string, score double")
