"""Inputs derived from the given tables by column expressions that SQL states alike: claims, media, predictions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from factbench.functions.scores import clip
from factbench.sources.io import load

#: Planted systems: name, number, fit before and after the cutoff, fit with search, noise, cutoff date. Fixed values.
SYSTEMS = (
    ("V1", 1, 0.70, 0.45, 0.85, 0.40, "1999-01-01"),
    ("V2", 2, 0.90, 0.30, 0.75, 0.35, "2000-01-01"),
    ("V3", 3, 0.80, 0.60, 0.95, 0.25, "2000-07-01"),
    ("V4", 4, 0.50, 0.30, 0.35, 0.60, "1997-01-01"),
    ("V5", 5, 0.60, 0.40, 0.80, 0.50, "2001-04-01"),
    ("V6", 6, 0.40, 0.20, 0.30, 0.70, "1998-07-01"),
    ("V7", 7, 0.65, 0.45, 0.78, 0.45, "2000-01-01"),
    ("V8", 8, 0.55, 0.35, 0.80, 0.55, "1999-07-01"),
)

#: Planted agents, always with search: name, number, fit, noise, lean to the bad class. Fixed values.
AGENTS = (("A1", 9, 0.75, 0.45, 0.05), ("A2", 10, 0.85, 0.35, 0.05), ("A3", 11, 0.72, 0.45, 0.05), ("X1", 12, 0.15, 0.5, 0.6), ("X2", 13, 0.1, 0.5, 0.7), ("X3", 14, 0.2, 0.6, -0.2))


def claims(spark: SparkSession, folder: str) -> DataFrame:
    """Dated claims from orders, with planted veracity and coverage."""
    o = load(spark, folder, "orders", ["o_orderkey", "o_custkey", "o_orderdate", "o_orderpriority", "o_orderstatus"])
    return o.select(
        F.col("o_orderkey").alias("claim_id"),
        F.col("o_orderdate").alias("claim_ts"),
        F.trunc("o_orderdate", "quarter").alias("quarter"),
        (((F.col("o_custkey") * 7919) % 2001 - 1000) / 1000.0).alias("veracity"),
        (((F.col("o_orderkey") * 104729) % 2001 - 1000) / 1000.0).alias("coverage"),
        (F.col("o_custkey") % 5 < 2).alias("english"),
        F.col("o_orderpriority").alias("raw_rating"),
        F.col("o_orderstatus").alias("status"),
    )


def claim_texts(spark: SparkSession, folder: str) -> DataFrame:
    """(claim_id, text, n_media): short texts for the claims; some name a video, some are mostly digits."""
    o = load(spark, folder, "orders", ["o_orderkey", "o_custkey", "o_orderpriority"])
    said = F.concat(
        F.lit("Customer "), (F.col("o_custkey") % 100).cast("string"), F.lit(" ordered goods with priority "), F.lower(F.expr("substr(o_orderpriority, 3)")),
        F.when(F.col("o_orderkey") % 3 == 0, ", as a video shows").otherwise(""), F.when(F.col("o_orderkey") % 13 == 0, ": " + "123456789 " * 5).otherwise(""),
    )
    counts = load(spark, folder, "lineitem", ["l_orderkey"]).groupBy(F.col("l_orderkey").alias("claim_id")).agg(F.count(F.lit(1)).alias("n_media"))
    return o.select(F.col("o_orderkey").alias("claim_id"), said.alias("text")).join(counts, "claim_id", "left").withColumn("n_media", F.coalesce("n_media", F.lit(0)))


#: Where a row lies in its table: columns that `claim_media` adds on request.
PLACE = ("file_path", "row_index")


def claim_media(spark: SparkSession, folder: str, placed: bool = False) -> DataFrame:
    """Media items of claims from line items; an item returned is a video. No key: only for aggregation by claim. ``placed`` adds `PLACE`."""
    place = [f"_metadata.{c}" for c in PLACE] if placed else []
    li = load(spark, folder, "lineitem", ["l_orderkey", "l_discount", "l_tax", "l_returnflag", *place])
    return li.select(
        F.col("l_orderkey").alias("claim_id"),
        F.round(1 - 25 * F.col("l_tax"), 6).alias("authenticity"),
        F.round(1 - 20 * F.col("l_discount"), 6).alias("contextualization"),
        (F.col("l_returnflag") == "R").alias("is_video"),
        *(PLACE if placed else ()),
    )


def media(spark: SparkSession, folder: str) -> DataFrame:
    """Media vectors with a planted copy of every fifth one."""
    e = load(spark, folder, "embeddings", ["vec_id", "embedding"])
    vector = F.transform("embedding", lambda x: x.cast("double"))
    first = e.select(F.col("vec_id").alias("media_id"), F.expr("vec_id div 10").alias("claim_id"), (F.col("vec_id") % 3 == 0).alias("is_video"), F.expr("cast((vec_id div 3) % 3 as int)").alias("origin"), vector.alias("embedding"))
    moved = F.concat(F.array(F.element_at(vector, 1) + 0.01), F.slice(vector, 2, 1000))
    copies = e.filter("vec_id % 5 = 0").select((F.col("vec_id") + 1_000_000).alias("media_id"), F.expr("vec_id div 10").alias("claim_id"), ((F.col("vec_id") + 1_000_000) % 3 == 0).alias("is_video"), F.lit(2).alias("origin"), moved.alias("embedding"))
    return first.unionByName(copies)


def media_chains(spark: SparkSession, folder: str) -> DataFrame:
    """Media whose similarity doesn't carry over: copies of every fifth vector turned by steps toward another one. Half of the first copies are in a second claim too."""
    e = load(spark, folder, "embeddings", ["vec_id", "embedding"])
    vector = F.transform("embedding", lambda x: x.cast("double"))
    own, toward = e.select("vec_id", vector.alias("u")), e.select((F.col("vec_id") - 1).alias("vec_id"), vector.alias("v"))
    steps = own.filter("vec_id % 5 = 0").join(toward, "vec_id").withColumn("k", F.explode(F.array(*[F.lit(k) for k in range(4)])))
    cos, sin = F.cos(F.col("k") * 0.4), F.sin(F.col("k") * 0.4)
    turned = F.zip_with("u", "v", lambda x, y: x * cos + y * sin)
    claim = F.expr("vec_id div 5")
    chain = steps.select((F.col("vec_id") * 100 + F.col("k")).alias("media_id"), claim.alias("claim_id"), ((F.col("vec_id") + F.col("k")) % 3).cast("int").alias("origin"), turned.alias("embedding"))
    again = steps.filter("k = 0 and vec_id % 10 = 0").select((F.col("vec_id") * 100).alias("media_id"), (claim + 1).alias("claim_id"), F.lit(0).alias("origin"), F.col("u").alias("embedding"))
    return chain.unionByName(again).withColumn("is_video", F.lit(False))


def predictions(spark: SparkSession, folder: str) -> DataFrame:
    """(system, search, claim_id, claim_ts, quarter, truth, english, cutoff, score): a row per claim, system and arm.

    Truth goes by parity, noise by integer hash, and fit drops at a planted cutoff. Each claim is expanded into the
    few systems in place, without a join.
    """
    o = load(spark, folder, "orders", ["o_orderkey", "o_custkey", "o_orderdate"])
    arms = F.array(
        *[
            F.struct(
                F.lit(name).alias("system"), F.lit(number).alias("number"), F.lit(before).alias("before"), F.lit(after).alias("after"), F.lit(searched).alias("searched"),
                F.lit(noise).alias("noise"), F.lit(cutoff).cast("timestamp_ntz").alias("cutoff"), F.lit(search).alias("search"),
            )
            for name, number, before, after, searched, noise, cutoff in SYSTEMS
            for search in (False, True)
        ]
    )
    base = o.select(
        F.col("o_orderkey").alias("claim_id"), F.col("o_orderdate").alias("claim_ts"), F.trunc("o_orderdate", "quarter").alias("quarter"),
        F.when((F.col("o_orderkey") * 104729) % 2 == 0, 1.0).otherwise(-1.0).alias("truth"), (F.col("o_custkey") % 5 < 2).alias("english"), F.inline(arms),
    )
    fit = F.when(F.col("search"), F.col("searched")).when(F.col("claim_ts") < F.col("cutoff"), F.col("before")).otherwise(F.col("after"))
    turn = F.col("number") * 31 + F.when(F.col("search"), 17).otherwise(0)
    noise = (((F.col("claim_id") + turn) * 7919) % 2001 - 1000) / 997.0 * F.col("noise")
    # a score leans to the bad class, as most systems' scores do; odd fractions, so that means have no rounding ties
    score = F.round(clip(F.col("truth") * fit + noise - 0.05), 9)
    return base.select("system", "search", "claim_id", "claim_ts", "quarter", "truth", "english", "cutoff", score.alias("score"))


def agent_predictions(spark: SparkSession, folder: str) -> DataFrame:
    """The same columns but for the cutoff, from the planted agents: two kinds with three backbones each."""
    o = load(spark, folder, "orders", ["o_orderkey", "o_custkey", "o_orderdate"])
    arms = F.array(*[F.struct(F.lit(s).alias("system"), F.lit(n).alias("number"), F.lit(f).alias("fit"), F.lit(e).alias("noise"), F.lit(b).alias("lean")) for s, n, f, e, b in AGENTS])
    base = o.select(
        F.col("o_orderkey").alias("claim_id"), F.col("o_orderdate").alias("claim_ts"), F.trunc("o_orderdate", "quarter").alias("quarter"),
        F.when((F.col("o_orderkey") * 104729) % 2 == 0, 1.0).otherwise(-1.0).alias("truth"), (F.col("o_custkey") % 5 < 2).alias("english"), F.inline(arms),
    )
    noise = (((F.col("claim_id") + F.col("number") * 31 + 17) * 7919) % 2001 - 1000) / 997.0 * F.col("noise")
    score = F.round(clip(F.col("truth") * F.col("fit") + noise - F.col("lean")), 9)
    return base.select("system", F.lit(True).alias("search"), "claim_id", "claim_ts", "quarter", "truth", "english", score.alias("score"))


def memberships(spark: SparkSession, folder: str) -> DataFrame:
    """(claim_id, has_image, has_video) for claims with media."""
    return claim_media(spark, folder).groupBy("claim_id").agg(F.bool_or(~F.col("is_video")).alias("has_image"), F.bool_or("is_video").alias("has_video"))
