"""Stage 2: who published a review, and whether that publisher is credible."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from factbench.functions.url import host, registrable_domain
from factbench.sources.io import small


def with_publisher(df: DataFrame, url: str = "url") -> DataFrame:
    return df.withColumn("host", host(url)).withColumn("publisher", registrable_domain(url))


def census(df: DataFrame, by: str = "publisher") -> DataFrame:
    """Reviews of each publisher."""
    return df.groupBy(by).agg(F.count(F.lit(1)).alias("n_reviews"))


def n_publishers(df: DataFrame, by: str = "publisher", approximate: bool = False) -> DataFrame:
    return df.agg((F.approx_count_distinct(by) if approximate else F.count_distinct(by)).alias("n_publishers"))


def retain_credible(df: DataFrame, credible: DataFrame, by: str = "publisher") -> DataFrame:
    """Reviews of listed publishers; the list is a dimension table, broadcast while it is short."""
    return df.join(small(credible.select(F.col(credible.columns[0]).alias(by))), by, "left_semi")


def dropped(df: DataFrame, credible: DataFrame, by: str = "publisher") -> DataFrame:
    return df.join(small(credible.select(F.col(credible.columns[0]).alias(by))), by, "left_anti")


def derive_credible(df: DataFrame, min_reviews: int, min_valid: float = 0.0, valid: str | None = None, by: str = "publisher") -> DataFrame:
    """A list derived from evidence: enough reviews, and a large enough share of valid ones."""
    share = F.avg(F.col(valid).cast("double")) if valid else F.lit(1.0)
    return df.groupBy(by).agg(F.count(F.lit(1)).alias("n"), share.alias("share")).filter((F.col("n") >= min_reviews) & (F.col("share") >= min_valid)).select(by)


def by_suffix(df: DataFrame, suffixes: tuple[str, ...]) -> DataFrame:
    """The alternative rule: hosts under given suffixes."""
    return df.filter(host("url").rlike("(?:" + "|".join(s.replace(".", r"\.") for s in suffixes) + ")$"))
