"""Quarterly splits: balanced by class, longitudinal, newest, frozen. Order by hash, so every run draws the same claims."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

CLASSES = ("intact", "compromised")


def quarter(ts: Column | str) -> Column:
    return F.trunc(ts if isinstance(ts, Column) else F.col(ts), "quarter")


def draw(seed: str, key: str = "claim_id") -> Column:
    return F.md5(F.concat(F.lit(f"{seed}:"), F.col(key).cast("string")))


def ranked(df: DataFrame, seed: str = "split-1") -> DataFrame:
    """Claims of the two classes with their place in (quarter, class) by hash, ties by id."""
    order = Window.partitionBy("quarter", "label").orderBy("_draw", "claim_id")
    return df.filter(F.col("label").isin(*CLASSES)).withColumn("_draw", draw(seed)).withColumn("rank", F.row_number().over(order)).drop("_draw")


def eligible(df: DataFrame, min_per_class: int) -> DataFrame:
    """(quarter, n_intact, n_compromised, eligible): quarters with enough claims of both classes."""
    n = lambda c: F.sum((F.col("label") == c).cast("int"))
    counts = df.groupBy("quarter").agg(*[F.coalesce(n(c), F.lit(0)).alias(f"n_{c}") for c in CLASSES])
    return counts.withColumn("eligible", F.least(*[F.col(f"n_{c}") for c in CLASSES]) >= min_per_class)


def balanced(df: DataFrame, per_quarter: int = 1000, seed: str = "split-1") -> DataFrame:
    """Half of ``per_quarter`` claims of each class in every quarter that has them.

    The rank limit reaches below the shuffle, so that each task ships no more than the quota per group.
    """
    half = per_quarter // 2
    taken = ranked(df, seed).filter(F.col("rank") <= half)
    full = taken.groupBy("quarter").agg(F.count(F.lit(1)).alias("_n")).filter(F.col("_n") == 2 * half).select("quarter")
    return taken.join(F.broadcast(full), "quarter", "left_semi")


def longitudinal(df: DataFrame, per_quarter: int = 100, seed: str = "split-1") -> DataFrame:
    """A small balanced split over all quarters; with the same seed a part of any larger one."""
    return balanced(df, per_quarter, seed)


def latest(df: DataFrame) -> DataFrame:
    """Claims of the newest quarter."""
    newest = df.agg(F.max("quarter").alias("_newest"))
    return df.join(F.broadcast(newest), F.col("quarter") == F.col("_newest")).drop("_newest")


def static(df: DataFrame, until: str) -> DataFrame:
    """A frozen benchmark: claims up to a date."""
    return df.filter(F.col("claim_ts") < F.lit(until).cast("timestamp_ntz"))


def overlap(a: DataFrame, b: DataFrame, key: str = "claim_id") -> DataFrame:
    """One row on two splits or runs: keys in both, in the first alone, in the second alone, and repeated in either."""
    left, right = a.select(key), b.select(key)
    parts = [left.intersect(right), left.distinct().exceptAll(right.distinct()), right.distinct().exceptAll(left.distinct()), left.exceptAll(left.distinct()).unionByName(right.exceptAll(right.distinct()))]
    names = ("both", "first_only", "second_only", "repeated")
    rows = [p.select(F.lit(n).alias("_part")) for n, p in zip(names, parts, strict=True)]
    every = rows[0].unionByName(rows[1]).unionByName(rows[2]).unionByName(rows[3])
    return every.agg(*[F.coalesce(F.sum((F.col("_part") == n).cast("long")), F.lit(0)).alias(n) for n in names])


def sample_by_class(df: DataFrame, key: str, by: str, shares: dict, seed: str = "sample-1") -> DataFrame:
    """A stratified sample, the same on every run: of each class its share of rows by hash; classes not named give none."""
    share = F.coalesce(*[F.when(F.col(by) == c, F.lit(int(s * 2**32))) for c, s in shares.items()], F.lit(0))
    return df.filter(F.conv(F.substring(draw(seed, key), 1, 8), 16, 10).cast("long") < share)


def sample_by_hash(df: DataFrame, key: str, share: float, seed: str = "sample-1") -> DataFrame:
    """A deterministic sample: rows whose hash falls below the share."""
    return df.filter(F.conv(F.substring(draw(seed, key), 1, 8), 16, 10).cast("long") < int(share * 2**32))
