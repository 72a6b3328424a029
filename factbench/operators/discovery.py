"""Stage 1: parsing review markup, filling languages, dropping repeated reviews."""

from __future__ import annotations

import datetime

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from factbench.functions import html, text
from factbench.sources.io import REVIEW


def parse_reviews(raw: DataFrame, json_col: str = "raw", since: datetime.date | None = None, until: datetime.date | None = None) -> DataFrame:
    """Reviews from a markup feed of one JSON text a row: an object, or an array of reviews of one claim.

    Malformed texts give a row with ``malformed`` true and nothing else, so that they can be counted. Reviews
    outside [since, until] go.
    """
    several = F.from_json(F.when(F.col(json_col).rlike(r"^\s*\["), F.col(json_col)).otherwise(F.concat(F.lit("["), F.col(json_col), F.lit("]"))), T.ArrayType(REVIEW), {"mode": "PERMISSIVE"})
    rows = raw.select(F.explode_outer(several).alias("r"))
    urls = F.filter(F.transform(F.col("r.itemReviewed.appearance"), lambda a: a["url"]), lambda u: u.isNotNull())
    out = rows.select(
        F.col("r.claimReviewed").alias("claim"), F.col("r.reviewRating.alternateName").alias("rating"), F.col("r.url").alias("url"),
        F.col("r.datePublished").alias("date"), F.col("r.inLanguage").alias("lang"), F.col("r.author.name").alias("publisher_name"), urls.alias("appearances"),
        (F.col("r").isNull() | (F.col("r.claimReviewed").isNull() & F.col("r.url").isNull())).alias("malformed"),
    )
    inside = F.lit(True)
    if since:
        inside = inside & (F.col("date") >= F.lit(since))
    if until:
        inside = inside & (F.col("date") <= F.lit(until))
    return out.filter(F.col("malformed") | inside)


def markup_from_html(pages: DataFrame, html_col: str = "html") -> DataFrame:
    """(page_id, raw): the linked-data blocks of pages, ready for ``parse_reviews``."""
    return pages.select("page_id", F.explode(html.ld_json(html_col)).alias("raw"))


def fill_language(df: DataFrame, text_col: str = "text", lang: str = "lang") -> DataFrame:
    """Detect a language only where none is given."""
    return df.withColumn(lang, F.coalesce(F.col(lang), F.when(F.col(lang).isNull(), text.language(text_col))))


def dedup_reviews(df: DataFrame, keys: list[str], order: list[str]) -> DataFrame:
    """The first row of each key in the given order; reviews repeat in a feed across quarters."""
    first = Window.partitionBy(*keys).orderBy(*order)
    return df.withColumn("_n", F.row_number().over(first)).filter(F.col("_n") <= 1).drop("_n")
