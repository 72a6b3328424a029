"""Stage 3: article text out of pages, and which articles are usable."""

from __future__ import annotations

import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from factbench.functions import html, text


def with_article(pages: DataFrame, html_col: str = "html") -> DataFrame:
    return pages.withColumn("article", html.main_text(html_col))


def body_span(pages: DataFrame, detector=None, html_col: str = "html") -> DataFrame:
    """(…, start, end, body): offsets from 0 of the article body in the source; ``body`` is a verbatim substring.

    ``detector`` takes the html column and gives struct(start, end); the local one finds the article element.
    """
    if detector is None:
        body = F.regexp_extract(html_col, r"(?s)<article[^>]*>(.*?)</article>", 1)
        at = F.when(body != "", F.locate("<article", F.col(html_col)))
        start = at + F.length(F.regexp_extract(html_col, r"(?s)(<article[^>]*>)", 1)) - 1
        span = F.struct(start.alias("start"), (start + F.length(body)).alias("end"))
    else:
        span = detector(F.col(html_col))
    out = pages.withColumn("_span", span)
    return out.withColumns({"start": F.col("_span.start"), "end": F.col("_span.end")}).drop("_span").withColumn("body", F.expr(f"substr({html_col}, start + 1, end - start)"))


_BLOCK = re.compile(r"(?is)<(?:p|h[1-6]|li|div|td|blockquote)\b[^>]*>(.*?)(?=<(?:p|h[1-6]|li|div|td|blockquote|/article|/body|/nav|/footer)\b|$)")


def html_blocks(source: str) -> list[tuple[int, int, int, str, float]]:
    """(block_no, start, end, text, link_share) of the block elements of a page."""
    out = []
    for no, m in enumerate(_BLOCK.finditer(source or "")):
        inner = m.group(1)
        plain = re.sub(r"<[^>]*>", "", inner)
        linked = sum(len(re.sub(r"<[^>]*>", "", a)) for a in re.findall(r"(?is)<a\b[^>]*>(.*?)</a>", inner))
        out.append((no, m.start(1), m.end(1), plain.strip(), linked / max(1, len(plain))))
    return out


def blocks(pages: DataFrame, html_col: str = "html") -> DataFrame:
    """A row per block, through a Python table function joined laterally; nothing is registered in the session."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="block_no int, start int, end int, text string, link_share double")
    class Blocks:
        def eval(self, source: str):
            yield from html_blocks(source)

    return pages.lateralJoin(Blocks(F.col(html_col).outer())).select("page_id", "block_no", "start", "end", "text", "link_share")


def density_span(pages: DataFrame, html_col: str = "html", least: int = 40, most_links: float = 0.3) -> DataFrame:
    """(page_id, start, end, body): from the first to the last block of enough text and few links; null where no block is good. No model."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            rows = []
            for page, source in zip(frame["page_id"], frame[html_col], strict=True):
                good = [b for b in html_blocks(source) if len(b[3]) >= least and b[4] <= most_links]
                rows.append((page, good[0][1], good[-1][2], source[good[0][1] : good[-1][2]]) if good else (page, None, None, None))
            yield pd.DataFrame(rows, columns=["page_id", "start", "end", "body"]).astype({"start": "Int64", "end": "Int64"})

    return pages.select("page_id", html_col).mapInPandas(run, "page_id long, start long, end long, body string")


def drop_inaccessible(df: DataFrame, col: str = "article") -> DataFrame:
    return df.filter(F.coalesce(F.trim(col), F.lit("")) != "")


def drop_short(df: DataFrame, min_chars: int = 200, min_words: int = 0, col: str = "article") -> DataFrame:
    kept = df.filter(F.length(col) >= min_chars)
    return kept.filter(text.n_words(col) >= min_words) if min_words else kept
