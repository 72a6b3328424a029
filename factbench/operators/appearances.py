"""Stage 4: where claims appeared."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from factbench.functions import html
from factbench.functions.url import canonical, unwrap_archive


def given(reviews: DataFrame, col: str = "appearances") -> DataFrame:
    """Appearances that the feed names, one row each; reviews without any keep a row with null."""
    return reviews.select("review_id", F.posexplode_outer(col).alias("place", "url"))


def lacking(reviews: DataFrame, col: str = "appearances") -> DataFrame:
    return reviews.filter(F.coalesce(F.size(col), F.lit(0)) <= 0)


def extract(pages: DataFrame, html_col: str = "html", url_col: str = "url") -> DataFrame:
    """(page_id, place, url): links of pages without any given appearance, absolute and canonical, each once.

    Relative links take the page's scheme and host. Archived originals are unwrapped. Links that are equal in
    canonical form are one, at the place of the first.
    """
    root = F.regexp_extract(url_col, r"^([a-zA-Z]+://[^/?#]+)", 1)
    found = pages.select("page_id", root.alias("root"), F.array_distinct(F.concat(html.hrefs(html_col), html.bare_urls(html_col))).alias("hrefs"))
    full = lambda h: F.when(h.rlike("^[a-zA-Z]+://"), h).otherwise(F.concat(F.col("root"), F.when(h.startswith("/"), h).otherwise(F.concat(F.lit("/"), h))))
    return found.select("page_id", F.posexplode(F.array_distinct(F.transform("hrefs", lambda h: canonical(unwrap_archive(full(h)))))).alias("place", "url"))


def choose(candidates: DataFrame, fetched: DataFrame) -> DataFrame:
    """One copy per appearance: the original if its download worked, else the archived one; none if neither did.

    ``candidates`` has (claim_id, place, url, archived_url), ``fetched`` has (url, ok).
    """
    ok = fetched.filter("ok").select("url").distinct()
    original = ok.select(F.col("url").alias("_u"), F.lit(True).alias("_original"))
    archived = ok.select(F.col("url").alias("_a"), F.lit(True).alias("_archived"))
    out = candidates.join(original, F.col("url") == F.col("_u"), "left").join(archived, F.col("archived_url") == F.col("_a"), "left")
    out = out.withColumn("chosen", F.when(F.col("_original"), F.col("url")).when(F.col("_archived"), F.col("archived_url")))
    return out.filter("chosen is not null").withColumn("from_archive", F.col("chosen") != F.col("url")).drop("_u", "_original", "_a", "_archived")


def cap(df: DataFrame, by: str, order: list[str], k: int = 2) -> DataFrame:
    """The first ``k`` of each group; a limit on groups reaches below the shuffle."""
    first = Window.partitionBy(by).orderBy(*order)
    return df.withColumn("rank", F.row_number().over(first)).filter(F.col("rank") <= k)


def retrieved(candidates: DataFrame, fetched: DataFrame, by: str = "claim_id", k: int = 2) -> DataFrame:
    """The first ``k`` appearances of each review that could be fetched, the archived copy standing in for a lost original."""
    return cap(choose(candidates, fetched), by, ["place"], k)


def require(reviews: DataFrame, appearances: DataFrame, key: str) -> DataFrame:
    return reviews.join(appearances.select(key).distinct(), key, "left_semi")


def without(reviews: DataFrame, appearances: DataFrame, key: str) -> DataFrame:
    return reviews.join(appearances.select(key).distinct(), key, "left_anti")
