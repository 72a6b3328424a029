"""Stage 5, claims: local rewriting rules and validation."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from factbench.functions import text

#: Openings that say who spread a claim, not what it says. Fixed value.
LEAD_IN = r"(?i)^(?:(?:social media |viral |online )?(?:posts?|videos?|images?|users?|articles?)[a-z ]*(?:claim|claiming|claims|say|saying|shows?|showing)(?: that)?[: ]+)"
#: Words that give a verdict away, by language. Fixed values.
VERDICT_WORDS = (
    "false", "fake", "hoax", "debunked", "misleading", "untrue", "fact-check", "faux", "trompeur", "intox", "falsch", "irreführend", "falschmeldung", "falso", "engañoso", "bulo",
)
#: Words that refer to media. Fixed values.
MEDIA_WORDS = ("image", "photo", "picture", "video", "footage", "clip", "bild", "foto", "vidéo", "imagen", "vídeo")


def _any(words: tuple[str, ...]) -> str:
    return r"(?i)(?:^|[^\p{L}])(?:" + "|".join(words) + r")(?:$|[^\p{L}])"


def first_sentence(c: Column) -> Column:
    """Up to the first full stop, exclamation or question mark that blank space or the end follows."""
    found = F.regexp_extract(c, r"(?s)^(.*?[.!?])(?:\s|$)", 1)
    return F.when(found != "", found).otherwise(c)


def rewritten(raw: Column | str) -> Column:
    """Lead-in removed, blanks squeezed, first sentence kept; the language is untouched."""
    c = F.col(raw) if isinstance(raw, str) else raw
    c = F.regexp_replace(F.regexp_replace(c, r"[ \t\n\r]+", " "), r"^ | $", "")
    return first_sentence(F.regexp_replace(c, LEAD_IN, ""))


def in_context(raw: Column, article: Column, appearance: Column, claimant: Column, date: Column) -> Column:
    """The local rewriter with context: who said it and when, before the claim; the article's first sentence stands in for a claim that has no text.

    Parts that are null leave nothing behind. ``appearance`` tells the place, as a short text.
    """
    said = rewritten(F.when(F.coalesce(F.trim(raw), F.lit("")) == "", article).otherwise(raw))
    where = F.concat(F.lit("on "), appearance)
    when = F.concat(F.lit("in "), F.date_format(date, "yyyy-MM"))
    lead = F.array_join(F.array_compact(F.array(claimant, where, when)), " ")
    return F.when(lead == "", said).otherwise(F.concat(lead, F.lit(": "), said))


def reformulate(df: DataFrame, raw: str = "text", kinds: str | None = None, rewriter=None, context: tuple[str, str, str, str] | None = None, video_rewriter=None) -> DataFrame:
    """Add ``claim``: concise and self-contained, naming the media in ``kinds`` (an array such as [video, image]).

    ``rewriter`` is a column binding that may replace the local rules; claims with a video go to ``video_rewriter``
    if there is one. With ``context``, the names of the columns of the article, the appearance, the claimant and the
    date, a rewriter gets these after the raw text.
    """
    given = [F.col(raw), *[F.col(c) for c in context or ()]]
    first = rewriter or (in_context if context else rewritten)
    claim = first(*given)
    if kinds and video_rewriter:
        claim = F.when(F.array_contains(kinds, "video"), video_rewriter(*given)).otherwise(claim)
    if kinds:
        claim = F.when(F.size(kinds) > 0, F.concat(claim, F.lit(" ["), F.array_join(kinds, ", "), F.lit("]"))).otherwise(claim)
    return df.withColumn("claim", claim)


def exposes_verdict(c: Column | str) -> Column:
    return (F.col(c) if isinstance(c, str) else c).rlike(_any(VERDICT_WORDS))


def lacks_media(c: Column | str, n_media: Column | str) -> Column:
    """The text refers to media, but none is attached."""
    c, n = (F.col(x) if isinstance(x, str) else x for x in (c, n_media))
    return c.rlike(_any(MEDIA_WORDS)) & (F.coalesce(n, F.lit(0)) == 0)


def too_long(c: Column | str, most: int = 70) -> Column:
    return text.n_words(c) > most


def reasons(c: str, n_media: str) -> Column:
    """Reasons against a claim, several if they apply; a null or blank claim has one of its own."""
    blank = F.coalesce(F.trim(c), F.lit("")) == ""
    return F.array_compact(
        F.array(F.when(blank, "empty"), F.when(exposes_verdict(c), "verdict exposed"), F.when(lacks_media(c, n_media), "media missing"), F.when(too_long(c), "too long"))
    )


def with_reasons(df: DataFrame, c: str = "claim", n_media: str = "n_media") -> DataFrame:
    """All claims with the reasons against them, an empty array for valid ones."""
    return df.withColumn("reasons", reasons(c, n_media))


def validate(df: DataFrame, c: str = "claim", n_media: str = "n_media") -> tuple[DataFrame, DataFrame]:
    """(kept, dropped): the dropped ones with their reasons."""
    told = with_reasons(df, c, n_media)
    return told.filter(F.size("reasons") == 0).drop("reasons"), told.filter(F.size("reasons") > 0)
