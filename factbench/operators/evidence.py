"""Evidence: what was published by a claim's date, the newest of it, and lexical search."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from factbench.sources.io import small


def admissible(claims: DataFrame, evidence: DataFrame, key: str, lag_days: int = 0, strict: bool = False) -> DataFrame:
    """Claims with the evidence of their key published no later than the claim (``lag_days`` earlier, if given).

    An equi-join on the key with a residual on time: hot keys are split by adaptive execution.
    """
    limit = F.col("claim_ts") - F.make_dt_interval(days=F.lit(lag_days)) if lag_days else F.col("claim_ts")
    ok = F.col("pub_ts") < limit if strict else F.col("pub_ts") <= limit
    return claims.join(evidence, key).filter(ok)


def admissible_within(claims: DataFrame, evidence: DataFrame, days: int) -> DataFrame:
    """Without a key: evidence from the ``days`` before the claim. Days become buckets, so the join stays an equi-join.

    Each claim looks at its own bucket and the one before, each as wide as the interval.
    """
    bucket = lambda ts: F.floor(F.datediff(F.to_date(ts), F.lit("1970-01-01").cast("date")) / days)
    looks = claims.withColumn("_b", F.explode(F.array(bucket("claim_ts"), bucket("claim_ts") - 1)))
    met = looks.join(evidence.withColumn("_b", bucket("pub_ts")), "_b").drop("_b")
    return met.filter((F.col("pub_ts") <= F.col("claim_ts")) & (F.col("pub_ts") > F.col("claim_ts") - F.make_dt_interval(days=F.lit(days))))


def count_within(claims: DataFrame, evidence: DataFrame, days: int) -> DataFrame:
    """(claim_id, n) of ``admissible_within`` for claims that have any, without making its pairs.

    What was published up to a claim, less what was published up to ``days`` before it: running counts over both in one
    sorted pass. Equal moments are combined before the shuffle, a day is sorted on its own, and counts of earlier days come
    from one row a day.
    """
    ends = F.array(F.struct(F.col("claim_ts").alias("at"), F.lit(1).alias("sign")), F.struct((F.col("claim_ts") - F.make_dt_interval(days=F.lit(days))).alias("at"), F.lit(-1).alias("sign")))
    asked = claims.filter("claim_ts is not null").select("claim_id", F.inline(ends)).withColumn("found", F.lit(0).cast("long"))
    moments = evidence.filter("pub_ts is not null").groupBy(F.col("pub_ts").alias("at")).agg(F.count(F.lit(1)).alias("found"))
    both = asked.unionByName(moments, allowMissingColumns=True).withColumn("_day", F.to_date("at"))
    earlier = Window.orderBy("_day").rowsBetween(Window.unboundedPreceding, -1)
    days_before = both.groupBy("_day").agg(F.sum("found").alias("_found")).select("_day", F.coalesce(F.sum("_found").over(earlier), F.lit(0)).alias("_before"))
    within = Window.partitionBy("_day").orderBy("at", F.col("sign").isNotNull()).rowsBetween(Window.unboundedPreceding, 0)
    seen = both.withColumn("_own", F.sum("found").over(within)).filter("sign is not null").join(days_before, "_day")
    return seen.groupBy("claim_id").agg(F.sum(F.col("sign") * (F.col("_before") + F.col("_own"))).alias("n")).filter("n > 0")


def newest(claims: DataFrame, evidence: DataFrame, key: str) -> DataFrame:
    """As-of: each claim with its newest admissible evidence. Both sides in one sorted pass, no pairs are made.

    At equal times evidence comes before claims and counts; of several, the one with the largest id. A key is sorted
    day by day, and what earlier days leave comes from one row a day, so that a hot key is no single task.
    """
    c = claims.select(key, F.col("claim_ts").alias("ts"), F.lit(1).alias("kind"), F.col("claim_id").alias("id"), F.lit(None).cast("struct<pub_ts:timestamp_ntz,evidence_id:bigint>").alias("e"))
    e = evidence.select(key, F.col("pub_ts").alias("ts"), F.lit(0).alias("kind"), F.col("evidence_id").alias("id"), F.struct(F.col("pub_ts").cast("timestamp_ntz").alias("pub_ts"), F.col("evidence_id").cast("long").alias("evidence_id")).alias("e"))
    both = c.unionByName(e).withColumn("_day", F.to_date("ts"))
    earlier = Window.partitionBy(key).orderBy("_day").rowsBetween(Window.unboundedPreceding, -1)
    days = both.groupBy(key, "_day").agg(F.max("e").alias("_last")).select(key, "_day", F.max("_last").over(earlier).alias("_before"))
    within = Window.partitionBy(key, "_day").orderBy("ts", "kind", "id").rowsBetween(Window.unboundedPreceding, 0)
    seen = both.withColumn("_own", F.last("e", ignorenulls=True).over(within)).filter("kind = 1").join(days, [key, "_day"])
    return seen.withColumn("last", F.coalesce("_own", "_before")).select(F.col("id").alias("claim_id"), key, F.col("ts").alias("claim_ts"), F.col("last.evidence_id").alias("evidence_id"), F.col("last.pub_ts").alias("pub_ts"))


def tokens(df: DataFrame, key: str, col: str = "text") -> DataFrame:
    """(key, tokens) of each row."""
    return df.select(F.col(key), _cut(col).alias("tokens"))


def _cut(text: str = "text") -> Column:
    """Lower-case runs of letters and digits."""
    return F.filter(F.split(F.lower(F.col(text)), r"[^\p{L}\p{N}]+"), lambda t: t != "")


def _dealt(df: DataFrame, key: str, more: list[str]) -> DataFrame:
    """(key, more, tokens): one exchange deals texts by key, and all that follows by key needs no other."""
    return df.select(key, "text", *more).repartition(key).select(key, *more, _cut().alias("tokens"))


def _counted(dealt: DataFrame, key: str, more: list[str]) -> DataFrame:
    """(key, more, len, token, tf)"""
    each = dealt.select(key, *more, F.size("tokens").alias("len"), F.explode("tokens").alias("token"))
    return each.groupBy(key, *more, "len", "token").agg(F.count(F.lit(1)).alias("tf"))


def postings(docs: DataFrame, wanted: DataFrame | None = None, k1: float = 1.2, b: float = 0.75, more: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, more, token, part): what each token adds to a document's BM25 score; only for ``wanted`` tokens, if given.

    Lengths and document counts are of all documents with a token; rows of one document stay in one partition.
    """
    dealt = _dealt(docs, "doc_id", list(more))
    counted = _counted(dealt, "doc_id", list(more))
    lengths = dealt.select(F.size("tokens").alias("len")).filter("len > 0")
    corpus = lengths.agg(F.count(F.lit(1)).alias("n"), F.avg("len").alias("mean"))
    listed = small(wanted) if wanted is not None else None
    near = counted.join(listed, "token", "left_semi") if wanted is not None else counted
    df = near.groupBy("token").agg(F.count(F.lit(1)).alias("df"))
    idf = F.log(1 + (F.col("n") - F.col("df") + 0.5) / (F.col("df") + 0.5))
    known = df.crossJoin(F.broadcast(corpus)).select(F.col("token").alias("_token"), idf.alias("_idf"), "mean")
    # as many rows as wanted tokens at most, so no need to count them when those are few
    few = F.broadcast(known) if listed is not None and listed is not wanted else small(known)
    weighted = near.join(few, F.col("token") == F.col("_token"))
    part = F.col("_idf") * F.col("tf") * (k1 + 1) / (F.col("tf") + k1 * (1 - b + b * F.col("len") / F.col("mean")))
    return weighted.select("doc_id", *more, "token", part.alias("part"))


def scores(claims: DataFrame, docs: DataFrame, k1: float = 1.2, b: float = 0.75, before: bool = False, side: str = "claims", block: int = 2_000_000) -> DataFrame:
    """(claim_id, doc_id, score): BM25 of every claim and document that share a token, without a shuffle of these pairs.

    ``side`` names the one whose token lists are sent to all executors, block by block if they are longer than
    ``block`` rows; the other side is dealt by its key once, and sums of a (claim, document) pair form where its row is. With
    ``before`` only documents with ``pub_ts`` up to the claim's ``claim_ts`` are scored.
    """
    c_time, d_time = (("claim_ts",), ("pub_ts",)) if before else ((), ())
    if side == "claims":
        asked = tokens_of(claims, c_time)
        sent, held = asked, postings(docs, asked.select("token").distinct(), k1, b, d_time)
    else:
        held = _counted(_dealt(claims, "claim_id", list(c_time)), "claim_id", list(c_time)).select("claim_id", *c_time, "token")
        sent = postings(docs, None, k1, b, d_time)
    key = "claim_id" if side == "claims" else "doc_id"
    n = sent.count()
    blocks = max(1, -(-n // block))
    out = None
    for at in range(blocks):
        some = sent if blocks == 1 else sent.filter(F.pmod(F.xxhash64(key), F.lit(blocks)) == at)
        met = held.join(F.broadcast(some.withColumnRenamed("token", "_token")), F.col("token") == F.col("_token"))
        if before:
            met = met.filter(F.col("pub_ts") <= F.col("claim_ts"))
        sums = met.groupBy("claim_id", "doc_id").agg(F.round(F.sum("part"), 6).alias("score"))
        out = sums if out is None else out.unionByName(sums)
    return out


def tokens_of(claims: DataFrame, more: tuple[str, ...] = ()) -> DataFrame:
    """(claim_id, more, token): the distinct tokens of each claim."""
    return claims.select("claim_id", *more, F.explode(F.array_distinct(_cut())).alias("token")).distinct()


def search(claims: DataFrame, docs: DataFrame, k: int = 3, before: bool = False, side: str = "claims", **bm25) -> DataFrame:
    """(claim_id, doc_id, score, rank): the ``k`` documents of largest BM25 score for each claim.

    Pairs are scored where the documents are, and each partition passes on no more than its ``k`` best for a claim.
    With ``before`` the time cut comes before ranking, as later documents would leak through ranks. ``side`` as in ``scores``:
    ``claims`` for many documents, ``docs`` for many claims and a small collection of evidence.
    """
    best = Window.partitionBy("claim_id").orderBy(F.desc("score"), "doc_id")
    return scores(claims, docs, before=before, side=side, **bm25).withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= k)


def support(claims: DataFrame, docs: DataFrame, full: float = 100.0, **options) -> DataFrame:
    """(claim_id, support): how well the best document backs a claim: its score as a share of ``full``, 1 at most."""
    best = scores(claims, docs, **options).groupBy("claim_id").agg(F.max("score").alias("_best"))
    return best.select("claim_id", F.least(F.lit(1.0), F.col("_best") / full).alias("support"))
