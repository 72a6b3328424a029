"""Quarterly updates: only new claims are processed; a rerun changes nothing; what isn't processed stays pending."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from factbench.sources.io import write_split


def _exists(spark: SparkSession, path: str) -> bool:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(p)


def _of(rows: DataFrame, quarter: str | list[str]) -> DataFrame:
    some = [quarter] if isinstance(quarter, str) else quarter
    return rows.filter(F.col("quarter").isin(*[F.lit(q).cast("date") for q in some]))


def pending(feed: DataFrame, state_dir: str, quarter: str | list[str], key: str = "claim_id") -> DataFrame:
    """Claims of a quarter, or of several, that no earlier run has processed."""
    rows = _of(feed, quarter)
    done = f"{state_dir}/processed"
    if not _exists(feed.sparkSession, done):
        return rows
    seen = _of(feed.sparkSession.read.parquet(done), quarter).select(key)
    return rows.join(seen, key, "left_anti")


def append_quarter(state_dir: str, feed: DataFrame, quarter: str | list[str], process: Callable[[DataFrame], DataFrame], limit: int | None = None, key: str = "claim_id") -> int:
    """Process the pending claims of a quarter, or of several, and add them to its partition; how many remain as a backlog.

    ``process`` maps claims to result rows with the key and the quarter. ``limit`` bounds a run: the claims of least
    key first. The quarter's partition is replaced by old and new rows together, so a repeated run is harmless.
    """
    spark = feed.sparkSession
    todo = pending(feed, state_dir, quarter, key)
    # only keys are gathered for the limit, which is what a run may process
    batch = todo.join(todo.select(key).orderBy(key).limit(limit), key, "left_semi") if limit is not None else todo
    out, done = f"{state_dir}/claims", f"{state_dir}/processed"
    fresh = process(batch)
    columns = fresh.columns
    if _exists(spark, out):
        old = _of(spark.read.parquet(out), quarter).select(columns)
        fresh = old.join(fresh.select(key), key, "left_anti").unionByName(fresh)
    staged = f"{state_dir}/staged"
    fresh.write.mode("overwrite").parquet(f"{staged}/claims")  # the partition is read and replaced, so results settle first
    ids = batch.select(key, "quarter")
    if _exists(spark, done):
        ids = _of(spark.read.parquet(done), quarter).select(key, "quarter").unionByName(ids).distinct()
    ids.write.mode("overwrite").parquet(f"{staged}/processed")
    write_split(spark.read.parquet(f"{staged}/claims"), out)
    write_split(spark.read.parquet(f"{staged}/processed"), done)
    return pending(feed, state_dir, quarter, key).count()
