"""Structured Streaming forms: the benchmark as claims arrive.

All take and give streaming DataFrames unless they say otherwise; on static ones most give the batch result.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from factbench.operators.splits import CLASSES, draw, quarter
from factbench.sources.io import small


def files(spark: SparkSession, folder: str, schema: T.StructType | str, files_per_trigger: int | None = None) -> DataFrame:
    """Parquet files of a folder as a stream, in declared columns."""
    reader = spark.readStream.schema(schema)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.parquet(folder)


def run_once(df: DataFrame, sink: Callable[[DataFrame, int], None] | str, checkpoint: str, mode: str = "append"):
    """Process all there is and stop: the quarterly job as a stream. ``sink`` is a batch function or a Parquet folder."""
    writer = df.writeStream.trigger(availableNow=True).option("checkpointLocation", checkpoint).outputMode(mode)
    query = (writer.foreachBatch(sink) if callable(sink) else writer.format("parquet").option("path", sink)).start()
    query.awaitTermination()
    return query


def dedup(df: DataFrame, keys: list[str], ts: str, delay: str) -> DataFrame:
    """The first of equal reviews that arrive within the delay."""
    return df.withWatermark(ts, delay).dropDuplicatesWithinWatermark(keys)


def earliest(df: DataFrame, keys: list[str], ts: str, key: str) -> DataFrame:
    """(keys, ``key``) of the first of equal reviews by time, the least ``key`` of several, in whatever order they arrive.

    One row of state for each of the equal ones; an earlier row that comes late takes the place, so the output mode is
    ``complete`` or ``update``. Rows without a time come last.
    """
    first = F.min(F.struct(F.col(ts).isNull().alias("_untimed"), F.col(ts).alias("_ts"), F.col(key).alias("_key")))
    return df.groupBy(*keys).agg(first.alias("_first")).select(*keys, F.col("_first._key").alias(key))


def volume(df: DataFrame, ts: str, width: str = "1 day", delay: str = "0 seconds") -> DataFrame:
    """Rows per tumbling window."""
    return df.withWatermark(ts, delay).groupBy(F.window(ts, width)).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "n")


def sliding_mse(pred: DataFrame, ts: str, width: str = "7 days", step: str = "1 day", delay: str = "0 seconds") -> DataFrame:
    """Squared error per sliding window, as sums that merge."""
    err = (F.col("score") - F.col("truth")) * (F.col("score") - F.col("truth"))
    sums = pred.withWatermark(ts, delay).groupBy(F.window(ts, width, step)).agg(F.count(err).alias("n"), F.sum(err).alias("sse"))
    return sums.select(F.col("window.start").alias("start"), "n", F.round(F.col("sse") / F.col("n"), 6).alias("mse"))


def sessions(df: DataFrame, key: str, ts: str, gap: str, delay: str = "0 seconds") -> DataFrame:
    """Spells of a claim's spread: rows of a key no further apart than the gap."""
    grouped = df.withWatermark(ts, delay).groupBy(key, F.session_window(ts, gap)).agg(F.count(F.lit(1)).alias("n"))
    return grouped.select(key, F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n")


def evidence(claims: DataFrame, found: DataFrame, key: str, days: int, delay: str = "0 seconds", how: str = "inner") -> DataFrame:
    """Claims with evidence of their key from the ``days`` before: an interval join of two watermarked streams.

    With ``how`` as ``left_outer``, claims without evidence come with a null ``evidence_id`` once the watermark shows that
    none can arrive any more; those of the newest moments stay in the state until then.
    """
    c = claims.withWatermark("claim_ts", delay).alias("c")
    e = found.withWatermark("pub_ts", delay).alias("e")
    when = F.expr(f"c.{key} = e.{key} AND e.pub_ts <= c.claim_ts AND e.pub_ts >= c.claim_ts - INTERVAL {int(days)} DAYS")
    return c.join(e, when, how).select("c.claim_id", "e.evidence_id")


def credible(reviews: DataFrame, listed: DataFrame, by: str = "publisher") -> DataFrame:
    """A stream against a static list, broadcast while it is short."""
    return reviews.join(small(listed), by, "left_semi")


def _sink_quota(folder: str, per_class: int, seed: str):
    def merge(batch: DataFrame, _: int) -> None:
        from factbench.operators.splits import ranked
        from factbench.plans.update import _exists
        from factbench.sources.io import write_split

        spark = batch.sparkSession
        rows = batch.filter(F.col("label").isin(*CLASSES)).withColumn("quarter", quarter("claim_ts")).select("claim_id", "claim_ts", "quarter", "label")
        if _exists(spark, f"{folder}/split"):
            touched = F.broadcast(rows.select("quarter").distinct())
            old = spark.read.parquet(f"{folder}/split").select(rows.columns).join(touched, "quarter", "left_semi").select(rows.columns)
            rows = old.unionByName(rows)
        kept = ranked(rows.dropDuplicates(["claim_id"]), seed).filter(F.col("rank") <= per_class).select("claim_id", "claim_ts", "quarter", "label")
        kept.write.mode("overwrite").parquet(f"{folder}/staged")
        write_split(spark.read.parquet(f"{folder}/staged"), f"{folder}/split")

    return merge


def quota_sink(df: DataFrame, folder: str, checkpoint: str, per_class: int, seed: str = "split-1"):
    """Keep the ``per_class`` claims of least hash for each (quarter, class) in a stored split, batch by batch.

    Calendar quarters have no window function, so each batch upserts the quarters it touches. The rank is by hash,
    so the members don't depend on the order of arrival: they equal the batch split's.
    """
    return run_once(df, _sink_quota(folder, per_class, seed), checkpoint, mode="append")


QUOTA = "quarter date, label string, claim_id long, draw string, added boolean"


def quota(df: DataFrame, per_class: int, seed: str = "split-1") -> DataFrame:
    """The same as a stateful operator: emits claims that enter a quota (added) and those they push out (not added)."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = dict(zip(*state.get, strict=True)) if state.exists else {}
        before = set(held)
        for frame in frames:
            held.update(zip(frame["claim_id"].tolist(), frame["draw"].tolist(), strict=True))
        kept = dict(sorted(held.items(), key=lambda x: (x[1], x[0]))[:per_class])
        state.update((list(kept), list(kept.values())))
        changes = [(k, held[k], True) for k in kept if k not in before] + [(k, held[k], False) for k in before if k not in kept]
        yield pd.DataFrame([(key[0], key[1], c, d, a) for c, d, a in changes], columns=["quarter", "label", "claim_id", "draw", "added"])

    rows = df.filter(F.col("label").isin(*CLASSES)).select(quarter("claim_ts").alias("quarter"), "label", "claim_id", draw(seed).alias("draw"))
    return rows.groupBy("quarter", "label").applyInPandasWithState(step, QUOTA, "ids array<long>, draws array<string>", "append", GroupStateTimeout.NoTimeout)


def late_rows(query) -> int:
    """Rows that arrived after the watermark and were dropped, over all batches of a query."""
    return sum(int(op.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for op in (p["stateOperators"] if isinstance(p, dict) else p.stateOperators or []))
