"""Stage 5, media: limits, relevance, duplicates by cosine, precedence, the cap with videos first."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from factbench.functions.vectors import cosine, plane
from factbench.sources.io import checkpointed

#: Origins in order of precedence. Fixed values.
ORIGINS = ("original", "archived", "article")


def precedence(origin: Column | str) -> Column:
    """0 for the original appearance, 1 for an archived one, 2 for article media; the last for anything else."""
    c = F.col(origin) if isinstance(origin, str) else origin
    out = F.lit(len(ORIGINS))
    for n, name in reversed(list(enumerate(ORIGINS))):
        out = F.when(c == name, n).otherwise(out)
    return out


def within_limits(df: DataFrame, max_seconds: float = 300, max_mb: float = 128, seconds: str = "seconds", mb: str = "mb") -> DataFrame:
    """Videos of at most five minutes and 128 MB."""
    return df.filter((F.col(seconds) <= max_seconds) & (F.col(mb) <= max_mb))


def retain_relevant(df: DataFrame, judge, claim: str = "claim_label", media: str = "label") -> DataFrame:
    """Media that a relevance judge (a column binding of two columns) keeps; ``judges.judged`` is the batch form."""
    return df.filter(judge(F.col(claim), F.col(media)))


def similar_pairs(media: DataFrame, threshold: float) -> DataFrame:
    """(claim_id, kept_id, dropped_id, similarity) of pairs inside a claim above the threshold, precedence first."""
    a = media.select("claim_id", *[F.col(c).alias(f"a_{c}") for c in ("media_id", "origin", "embedding")])
    b = media.select("claim_id", *[F.col(c).alias(f"b_{c}") for c in ("media_id", "origin", "embedding")])
    earlier = F.struct("a_origin", "a_media_id") < F.struct("b_origin", "b_media_id")
    sim = cosine("a_embedding", "b_embedding")
    pairs = a.join(b, "claim_id").filter(earlier).withColumn("similarity", sim).filter(F.col("similarity") > threshold)
    return pairs.select("claim_id", F.col("a_media_id").alias("kept_id"), F.col("b_media_id").alias("dropped_id"), F.round("similarity", 6).alias("similarity"))


def dedup(media: DataFrame, threshold: float = 0.85, mode: str = "pairwise") -> DataFrame:
    """Media without near duplicates inside their claim (similarity above the threshold).

    ``pairwise`` drops an item similar to any of higher precedence; ``greedy`` compares with items kept so far;
    ``components`` keeps the best of each connected group. An item may belong to several claims, and is judged in
    each on its own.
    """
    both = ["claim_id", "media_id"]
    if mode == "pairwise":
        gone = similar_pairs(media, threshold).select("claim_id", F.col("dropped_id").alias("media_id")).distinct()
        return media.join(gone, both, "left_anti")
    if mode == "greedy":
        items = F.array_sort(F.collect_list(F.struct("origin", "media_id", "embedding")))
        start = F.expr("cast(array() as array<struct<media_id:bigint,embedding:array<double>>>)")
        kept = F.aggregate(
            items, start,
            lambda done, x: F.when(F.exists(done, lambda k: cosine(k["embedding"], x["embedding"]) > threshold), done).otherwise(F.concat(done, F.array(F.struct(x["media_id"].alias("media_id"), x["embedding"].alias("embedding"))))),
        )
        ids = media.groupBy("claim_id").agg(F.transform(kept, lambda k: k["media_id"]).alias("ids")).select("claim_id", F.explode("ids").alias("media_id"))
        return media.join(ids, both, "left_semi")
    if mode == "components":
        node = lambda c: F.struct("claim_id", F.col(c).alias("media_id"))
        group = components(similar_pairs(media, threshold).select(node("kept_id").alias("a"), node("dropped_id").alias("b")))
        best = Window.partitionBy("_group").orderBy("origin", "media_id")
        marked = media.join(group, F.struct(*both) == F.col("node"), "left").withColumn("_group", F.coalesce("component", F.struct(*both)))
        return marked.withColumn("_n", F.row_number().over(best)).filter(F.col("_n") <= 1).select(*media.columns)
    raise ValueError(f"no mode {mode}")


def components(pairs: DataFrame) -> DataFrame:
    """(node, component): the least node that (a, b) pairs reach, of any type that has an order.

    Each round takes the least label of the neighbours, then that label's own label, so that rounds grow with the
    logarithm of the longest chain; it ends when no label changes. Lineage is cut each round.
    """
    both = checkpointed(pairs.select("a", "b").unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    labels = checkpointed(both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("label")).select(F.col("a").alias("node"), "label"))
    while True:
        near = both.join(labels, F.col("b") == F.col("node")).groupBy("a").agg(F.min("label").alias("near"))
        lower = labels.join(near, F.col("node") == F.col("a"), "left").select("node", F.col("label").alias("was"), F.least("label", "near").alias("label"))
        ahead = labels.select(F.col("node").alias("_at"), F.col("label").alias("_jump"))
        nxt = checkpointed(lower.join(ahead, F.col("label") == F.col("_at"), "left").select("node", "was", F.least("label", "_jump").alias("label")))
        changed = nxt.filter("label < was").limit(1).count()
        labels = nxt.select("node", "label")
        if not changed:
            return labels.select("node", F.col("label").alias("component"))


def lsh_shape(n: int, threshold: float, recall: float) -> tuple[int, int]:
    """(bits, tables) of random-hyperplane buckets: about 16 vectors a bucket, and tables enough for the recall at the threshold."""
    bits = max(4, round(np.log2(max(2, n))) - 4)
    together = (1 - np.arccos(np.clip(threshold, -1, 1)) / np.pi) ** bits
    return bits, max(1, int(np.ceil(np.log(1 - recall) / np.log1p(-together))))


def _bucket_rows(bits: int, tables: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weights = 1 << np.arange(bits, dtype=np.int64)
        for batch in batches:
            if not batch.num_rows:
                continue
            vectors = np.asarray(batch.column(1).flatten(), dtype=np.float64).reshape(batch.num_rows, -1)
            for table in range(tables):
                planes = np.array([plane(table, bit, vectors.shape[1]) for bit in range(bits)])
                keys = (vectors @ planes.T > 0).astype(np.int64) @ weights
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(keys), table, np.int32)), pa.array(keys), batch.column(0)], names=["table", "bucket", "media_id"])

    return run


def near_pairs(media: DataFrame, threshold: float, recall: float = 0.999) -> DataFrame:
    """(a, b, similarity) of similar media in the whole corpus: random-hyperplane buckets, then exact comparison.

    The number of vectors sets the bits, so that buckets stay as small as the table grows, and the target recall
    of pairs at exactly the threshold sets the number of tables; more similar pairs are found more surely. Narrow rows
    (table, bucket, id) meet first; vectors join distinct candidates only. All vectors must have one length; null ones
    take no part.
    """
    known = media.filter("embedding is not null")
    lengths = known.agg(F.count(F.lit(1)), F.min(F.size("embedding")), F.max(F.size("embedding"))).first()
    if lengths[1] != lengths[2]:
        raise ValueError(f"vectors have {lengths[1]} to {lengths[2]} components")
    rows = known.select("media_id", F.transform("embedding", lambda x: x.cast("double")).alias("v")).mapInArrow(_bucket_rows(*lsh_shape(lengths[0], threshold, recall)), "table int, bucket long, media_id long")
    a, b = rows.withColumnRenamed("media_id", "a"), rows.withColumnRenamed("media_id", "b")
    met = a.join(b, ["table", "bucket"]).filter("a < b").select("a", "b").distinct()
    left, right = known.select(F.col("media_id").alias("a"), F.col("embedding").alias("va")), known.select(F.col("media_id").alias("b"), F.col("embedding").alias("vb"))
    sim = met.join(left, "a").join(right, "b").withColumn("similarity", F.round(cosine("va", "vb"), 6))
    return sim.filter(F.col("similarity") > threshold).select("a", "b", "similarity")


def exact_pairs(media: DataFrame, threshold: float, block: int = 1024) -> DataFrame:
    """The same by comparing all vectors, for recall measurements: block against block as matrix products.

    Only pairs above the threshold become rows. Time grows with the square of the table.
    """
    blocks = max(1, -(-media.count() // block))
    own = media.select("media_id", F.transform("embedding", lambda x: x.cast("double")).alias("v"), F.pmod(F.xxhash64("media_id"), F.lit(blocks)).cast("int").alias("home"))
    a = own.select(F.col("media_id").alias("a"), F.col("v").alias("va"), F.col("home").alias("i"), F.explode(F.sequence(F.col("home"), F.lit(blocks - 1))).alias("j"))
    b = own.select(F.col("media_id").alias("b"), F.col("v").alias("vb"), F.explode(F.sequence(F.lit(0), F.col("home"))).alias("i"), F.col("home").alias("j"))

    def compare(left: pa.Table, right: pa.Table) -> pa.Table:
        out = {"a": np.empty(0, np.int64), "b": np.empty(0, np.int64), "similarity": np.empty(0)}
        if left.num_rows and right.num_rows:
            x, y = (np.asarray(t.combine_chunks().flatten()).reshape(len(t), -1) for t in (left["va"], right["vb"]))
            sims = np.round((x @ y.T) / np.linalg.norm(x, axis=1)[:, None] / np.linalg.norm(y, axis=1)[None, :], 6)
            i, j = np.nonzero(sims > threshold)
            p, q = left["a"].to_numpy()[i], right["b"].to_numpy()[j]
            keep = (p < q) if left["i"][0] == left["j"][0] else (p != q)
            out = {"a": np.minimum(p, q)[keep], "b": np.maximum(p, q)[keep], "similarity": sims[i, j][keep]}
        return pa.table(out)

    return a.groupBy("i", "j").cogroup(b.groupBy("i", "j")).applyInArrow(compare, "a long, b long, similarity double")


def cap(media: DataFrame, k: int = 4) -> DataFrame:
    """At most ``k`` items per claim: videos first, then by origin, then by id."""
    first = Window.partitionBy("claim_id").orderBy(F.desc("is_video"), "origin", "media_id")
    return media.withColumn("rank", F.row_number().over(first)).filter(F.col("rank") <= k)
