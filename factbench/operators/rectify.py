"""Stage 7: corrected twins of compromised claims: made, checked, scored again, and swapped in."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from factbench.functions import text
from factbench.functions.scores import EDGE, clip
from factbench.operators import ensemble, verdict


def candidates(verdicts: DataFrame) -> DataFrame:
    return verdicts.filter(F.col("label") == "compromised")


def lifted(key: Column | str, score: Column | str) -> Column:
    """The local corrector of scores: a value in (1/3, 1] by integer hash; for one id in 40 a failing one."""
    k = F.col(key) if isinstance(key, str) else key
    s = F.col(score) if isinstance(score, str) else score
    good = F.round(0.334 + ((k * 7919) % 667) / 1001.0, 6)
    return F.when((k * 31) % 40 == 0, F.round(s / 2, 6)).otherwise(good)


#: How the local corrector opens a corrected text, by what compromised the claim. Fixed values.
OPENINGS = (("contextualization", "Seen in its context: "), ("veracity", "In fact: "), ("coverage", "With what was left out: "))


def corrected(text_col: Column, justification: Column, compromising: Column) -> Column:
    """The local corrector of texts: repeated lines and lines of mostly symbols go, and the justification of what compromised the claim guides the rest."""
    kept = F.array_join(F.filter(F.array_distinct(text.lines(text_col)), lambda line: text.symbol_share(line) < 0.15), "\n")
    opening = F.coalesce(*[F.when(compromising == p, F.lit(o)) for p, o in OPENINGS], F.lit(""))
    return F.concat(opening, kept, F.when(compromising == "coverage", F.concat(F.lit(" ("), F.coalesce(justification, F.lit("")), F.lit(")"))).otherwise(""))


def generate(cands: DataFrame, corrector=corrected, col: str = "text") -> DataFrame:
    """Twins of compromised claims: same media, and ``twin_text`` from a corrector, a column binding of text, justification and compromising property."""
    return cands.withColumn("twin_text", corrector(F.col(col), F.col("justification"), F.col("compromising")))


def checked(twins: DataFrame, n_media: str = "n_media", consistency=None, shareability=None) -> DataFrame:
    """Add ``consistent`` and ``shareable``, by the local rules or by column bindings."""
    agrees = (consistency or (lambda t, n: consistent(twins, "twin_text", n_media)))(F.col("twin_text"), F.col(n_media))
    return twins.withColumns({"consistent": agrees, "shareable": (shareability or shareable)(F.col("twin_text"))})


def passing(twins: DataFrame) -> DataFrame:
    """Twins that go on to be scored."""
    return twins.filter("consistent and shareable")


def revote(twins: DataFrame, votes: DataFrame) -> DataFrame:
    """The local members' votes on twins: (claim_id, member, the three properties).

    Every property that was not positive is lifted, as each needs its correction, or the next worst would compromise
    the twin; members differ by integer hash, and on one twin in 11 the second member disagrees altogether.
    """
    own = votes.join(twins.select("claim_id"), "claim_id", "left_semi")
    off = ((F.col("claim_id") * 13 + F.ascii(F.substring("member", -1, 1)) * 29) % 41 - 20) / 400.0
    against = (F.col("claim_id") % 11 == 3) & (F.col("member") == "J2")
    new = lambda c: F.when(F.col(c).isNull(), None).when(against, F.lit(-0.9)).when(F.col(c) <= EDGE, F.round(clip(lifted("claim_id", c) + off), 6)).otherwise(F.col(c))
    return own.select("claim_id", "member", *[new(c).alias(c) for c in verdict.ORDER])


def rescore(twins: DataFrame, votes: DataFrame) -> DataFrame:
    """Stage 6 again, on the members' votes for the twins that passed the checks: ``twin_integrity`` and ``twin_spread``, null for the others."""
    told = ensemble.standardize(votes).select("claim_id", F.col("integrity").alias("twin_integrity"), F.col("spread").alias("twin_spread"))
    return twins.join(told, "claim_id", "left")


def generate_text(df: DataFrame, col: str = "text") -> DataFrame:
    """The local corrector of texts: lines that repeat and lines of mostly symbols go."""
    kept = F.filter(F.array_distinct(text.lines(col)), lambda line: text.symbol_share(line) < 0.15)
    return df.withColumn("twin_text", F.array_join(kept, "\n"))


def consistent(df: DataFrame, claim: str, n_media: str) -> Column:
    """Text and media agree: a text that names media has some."""
    from factbench.operators.claims import lacks_media

    return ~lacks_media(claim, n_media)


def shareable(claim: Column | str, least: int = 4, most: int = 70, digits: float = 0.25) -> Column:
    """What a reader would pass on: not too short, long or detailed."""
    c = F.col(claim) if isinstance(claim, str) else claim
    share = F.length(F.regexp_replace(c, "[^0-9]", "")) / F.greatest(F.lit(1), F.length(c))
    n = text.n_words(c)
    return (n >= least) & (n <= most) & (share <= digits)


def decided(twins: DataFrame, max_spread: float = 1.0) -> DataFrame:
    """Add ``outcome``: inconsistent, not shareable, low agreement, not intact, or accepted (integrity above 1/3, which is stricter than not negative)."""
    good = F.coalesce(F.col("twin_integrity") > EDGE, F.lit(False))
    return twins.withColumn(
        "outcome",
        F.when(~F.col("consistent"), "inconsistent").when(~F.col("shareable"), "not shareable").when(F.col("twin_spread") > max_spread, "low agreement").when(~good, "not intact").otherwise("accepted"),
    )


def report(decided_twins: DataFrame) -> DataFrame:
    """Counts and per cent of each outcome."""
    counts = decided_twins.groupBy("outcome").agg(F.count(F.lit(1)).alias("n"))
    total = counts.agg(F.sum("n").alias("total"))
    return counts.crossJoin(F.broadcast(total)).select("outcome", "n", F.round(100.0 * F.col("n") / F.col("total"), 6).alias("percent"))


def replace(originals: DataFrame, decided_twins: DataFrame) -> DataFrame:
    """Accepted twins replace their originals; every claim id stays once, with the integrity and label it now has."""
    good = decided_twins.filter("outcome = 'accepted'").select(F.col("claim_id").alias("_id"), F.col("twin_integrity").alias("_integrity"))
    out = originals.join(good, F.col("claim_id") == F.col("_id"), "left").withColumn("rectified", F.col("_id").isNotNull())
    out = out.withColumn("integrity", F.coalesce("_integrity", "integrity")).drop("_id", "_integrity")
    return out.withColumn("label", verdict.label("integrity"))
