"""Texts: words, shares, the local language test and the four local scorers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from factbench.functions.scores import clip, rounded

#: Stop words by language, in the order that decides ties. Fixed values.
STOP_WORDS = {
    "en": ("the", "and", "of", "to", "in", "is", "was", "for", "that", "with", "on", "by", "are", "this", "from"),
    "fr": ("le", "la", "les", "des", "et", "un", "une", "du", "dans", "pour", "que", "qui", "est", "sur", "par"),
    "de": ("der", "die", "das", "und", "den", "von", "zu", "mit", "ist", "ein", "eine", "nicht", "auf", "im", "für"),
    "es": ("el", "los", "las", "y", "en", "un", "una", "del", "que", "es", "por", "con", "para", "se", "su"),
}


def _c(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def words(text: Column | str) -> Column:
    """Words of a text cut at white space; an empty array for null or blank texts."""
    return F.coalesce(F.filter(F.split(_c(text), r"[ \t\n\r]+"), lambda w: w != ""), F.expr("cast(array() as array<string>)"))


def n_words(text: Column | str) -> Column:
    return F.size(words(text))


def lines(text: Column | str) -> Column:
    return F.split(_c(text), "\n")


def _among(own: tuple[str, ...]):
    return lambda t: t.isin(*own)


def language_scores(text: Column | str) -> dict[str, Column]:
    tokens = F.filter(F.split(F.lower(_c(text)), r"[^\p{L}]+"), lambda t: t != "")
    total = F.greatest(F.lit(1), F.size(tokens))
    return {lang: F.size(F.filter(tokens, _among(own))) / total for lang, own in STOP_WORDS.items()}


def language(text: Column | str) -> Column:
    """The language with the largest share of stop words, earlier ones first; null if no share is above 0."""
    scores = language_scores(text)
    best = F.greatest(*scores.values())
    out = F.lit(None).cast("string")
    for lang, score in reversed(scores.items()):
        out = F.when(score == best, lang).otherwise(out)
    return F.when(best > 0, out)


def symbol_share(text: Column | str) -> Column:
    c = _c(text)
    return F.length(F.regexp_replace(c, r"[\p{L}\p{N} \t\n\r]+", "")) / F.greatest(F.lit(1), F.length(c))


def distinct_share(items: Column) -> Column:
    return F.size(F.array_distinct(items)) / F.greatest(F.lit(1), F.size(items))


def parts(text: Column | str) -> dict[str, Column]:
    """What the scorers look at, each computed once."""
    return {"_words": words(text), "_lines": lines(text), "_symbols": symbol_share(text)}


def raw_scorers() -> dict[str, Column]:
    """Four deterministic stand-ins for hosted models over ``parts``, before clipping."""
    return {
        "J1": 2 * distinct_share(F.col("_lines")) - 1,
        "J2": 1 - 30 * F.abs(F.col("_symbols") - 0.02),
        "J3": (F.size("_words") - 50) / 100,
        "J4": 2 * distinct_share(F.col("_words")) - 1,
    }


def second_raw_scorers() -> dict[str, Column]:
    """Another family of scorers, for comparing regenerated pipelines: the mean length of words in place of J4."""
    mean = F.aggregate("_words", F.lit(0), lambda n, w: n + F.length(w)) / F.greatest(F.lit(1), F.size("_words"))
    return raw_scorers() | {"J4": 1 - F.abs(mean - 5.0) / 4}


def with_scores(df: DataFrame, text: str = "text", family=raw_scorers) -> DataFrame:
    """Add a column per scorer, in [-1, 1], rounded at the source.

    Each text is split and scanned once: parts, raw scores and clipped scores are projections of their own, which
    the optimizer doesn't merge as they are used several times.
    """
    raw = family()
    out = df.withColumns(parts(text)).withColumns(raw).drop(*parts(text))
    return out.withColumns({name: rounded(clip(F.col(name)), 6) for name in raw})


def jaccard(a: Column, b: Column) -> Column:
    """Of two word arrays taken as sets; 1 for two empty ones."""
    union = F.size(F.array_union(a, b))
    return F.when(union == 0, 1.0).otherwise(F.size(F.array_intersect(a, b)) / union)
