"""Mixing sources to target weights: hash-random order in each source, distributed prefix sums, exact cuts.

The target of a source is its weight times one water level, or ``most`` times its own size where that is less:
what resharing the excess by weight, again and again, ends at. The level follows in closed form from the few
source totals. Documents get keys that depend on the seed and their id alone, so reruns agree.
"""

from __future__ import annotations

import math

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from factbench.llm.common import stored

SPACE = r"[\x20\x09-\x0D]+"


def count_words(text: str | Column) -> Column:
    """Number of runs without ASCII white space; 0 for null and empty texts."""
    text = F.col(text) if isinstance(text, str) else text
    ends = F.when(text.rlike(r"^[\x20\x09-\x0D]"), 1).otherwise(0) + F.when(text.rlike(r"[\x20\x09-\x0D]\z"), 1).otherwise(0)
    return F.coalesce(F.when(text != "", F.size(F.split(text, SPACE)) - ends), F.lit(0)).cast("long")


def targets(sizes: DataFrame, source: str = "source", size: str = "source_size", weights: tuple[float, ...] = (5, 2, 1), share: float = 1.5, most: float = 2.0) -> DataFrame:
    """Add ``target`` to a table of source sizes.

    Sources in code-point order, null last, take ``weights`` in turn; all targets together are ``share`` of all
    sizes (``most`` bounds it too), and none is above ``most`` times its source's size.
    """
    everything = Window.partitionBy()
    kinds = F.array(*[F.lit(float(w)) for w in weights])
    ranked = sizes.withColumn("_at", F.row_number().over(Window.orderBy(F.col(source).asc_nulls_last())))
    ranked = ranked.withColumn("_w", F.element_at(kinds, ((F.col("_at") - 1) % len(weights) + 1).cast("int"))).withColumn("_cap", most * F.col(size))
    rising = Window.orderBy(F.col("_cap") / F.col("_w"), "_at").rowsBetween(Window.unboundedPreceding, 0)
    ranked = ranked.select("*", F.sum("_cap").over(rising).alias("_caps"), (F.sum("_w").over(everything) - F.sum("_w").over(rising)).alias("_rest"), (share * F.sum(size).over(everything)).alias("_all"))
    ranked = ranked.withColumn("_full", F.col("_caps") + F.col("_cap") / F.col("_w") * F.col("_rest") <= F.col("_all"))
    spent = F.sum(F.when(F.col("_full"), F.col("_cap")).otherwise(0.0)).over(everything)
    open_weight = F.sum(F.when(F.col("_full"), 0.0).otherwise(F.col("_w"))).over(everything)
    level = F.try_divide(F.col("_all") - spent, open_weight)
    return ranked.withColumn("target", F.when(F.col("_full"), F.col("_cap")).otherwise(level * F.col("_w"))).drop("_at", "_w", "_cap", "_caps", "_rest", "_all", "_full")


def mix(docs: DataFrame, size: str | Column, key: str = "doc_id", source: str = "source", seed: str = "mix-1", out: str = "size", most_broadcast: int = 2_000_000, **shares) -> DataFrame:
    """Add ``out`` (the ``size``), ``source_size``, ``target`` and ``taken`` to documents.

    ``taken`` counts what the mix takes of a document, repeats included: whole epochs of its source first, then
    documents in hash-random order up to the exact budget, the last one in part. The budget is the target
    rounded down. Empty documents take nothing; a null source is a source; a null id has a key of its own, and
    rows with equal keys follow each other by size. Repeated rows are rows of their own; an empty table gives an
    empty table; an input column with the name of a new one gives way to it.

    Sums are taken by source and hash bucket. A bucket that the budget takes whole or not at all needs no order, and
    its rows stay where they are; only the bucket at the edge of each source is shuffled and sorted.
    """
    size = F.col(size) if isinstance(size, str) else size
    key_of = F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col(key).cast("string"), F.lit("-"))))
    kept = docs.drop("source_size", "target", "taken")
    bucket_of = F.substring(key_of, 1, 3)
    sized = kept.select(F.col(source).alias("_s"), bucket_of.alias("_b"), size.cast("long").alias("_size"))
    buckets = stored(sized.groupBy("_s", "_b").agg(F.sum("_size").alias("_sum")))  # at most 4096 rows a source
    sums = targets(buckets.groupBy("_s").agg(F.sum("_sum").alias("source_size")), "_s", **shares).withColumnRenamed("_s", "_from")
    before = Window.partitionBy("_s").orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    plan = buckets.withColumn("_offset", F.coalesce(F.sum("_sum").over(before), F.lit(0))).join(sums, F.col("_s").eqNullSafe(F.col("_from")))
    epochs = F.when(F.col("source_size") > 0, F.floor(F.floor("target") / F.col("source_size"))).otherwise(0)
    plan = plan.withColumn("_epochs", epochs).withColumn("_rest", F.floor("target") - F.col("_epochs") * F.col("source_size") - F.col("_offset"))
    fields = F.struct("source_size", "target", "_epochs", "_rest", ((F.col("_rest") > 0) & (F.col("_rest") < F.col("_sum"))).alias("edge"))
    plan = stored(plan.select(F.col("_s").alias("_mix_source"), F.col("_b").alias("_mix_bucket"), fields.alias("_mix")))
    few = plan.count() <= most_broadcast
    marked = kept.join(F.broadcast(plan) if few else plan, F.col(source).eqNullSafe(F.col("_mix_source")) & (bucket_of == F.col("_mix_bucket")))

    whole = marked.filter(~F.col("_mix.edge")).withColumn(out, size.cast("long"))
    whole = whole.withColumn("taken", F.col("_mix._epochs") * F.col(out) + F.when(F.col("_mix._rest") > 0, F.col(out)).otherwise(0))
    within = Window.partitionBy("_mix_source", "_mix_bucket").orderBy(key_of, out).rowsBetween(Window.unboundedPreceding, -1)
    part = marked.filter("_mix.edge").withColumn(out, size.cast("long"))
    part = part.withColumn("_mix_left", F.col("_mix._rest") - F.coalesce(F.sum(out).over(within), F.lit(0)))
    part = part.withColumn("taken", F.col("_mix._epochs") * F.col(out) + F.greatest(F.lit(0), F.least(F.col(out), F.col("_mix_left")))).drop("_mix_left")
    both = whole.unionByName(part)
    both = both.withColumns({"source_size": F.col("_mix.source_size"), "target": F.col("_mix.target"), "taken": F.col("taken").cast("long")})
    return both.drop("_mix", "_mix_source", "_mix_bucket")


@F.arrow_udf(T.StringType())
def _first_words(text: pa.Array, words: pa.Array) -> pa.Array:
    def cut(t: str, n: int) -> str:
        data, at = t.encode(), 0
        for word in data.split(None, int(n))[: int(n)]:
            at = data.index(word, at) + len(word)
        return data[:at].decode()

    return pa.array([cut(t, n) for t, n in zip(text.to_pylist(), words.to_pylist(), strict=True)], pa.string())


def mixed_rows(docs: DataFrame, text: str = "text", key: str = "doc_id", source: str = "source", **options) -> DataFrame:
    """The mix itself: documents repeated for each epoch, the one at each budget's edge cut after its last word taken."""
    columns = docs.columns
    rows = docs.select(F.struct("*").alias("_row"), F.col(text).alias("_text"), F.col(key).alias("_id"), F.col(source).alias("_of"))
    mixed = mix(rows, count_words("_text"), key="_id", source="_of", out="_size", **options).filter("taken > 0")
    copies = F.sequence(F.lit(1), F.ceil(F.col("taken") / F.col("_size")).cast("int"))
    each = mixed.withColumn("_copy", F.explode(copies)).withColumn("_words", F.least(F.col("_size"), F.col("taken") - (F.col("_copy") - 1) * F.col("_size")))
    own = lambda new: [F.col(f"_row.{c}") if c != text else new.alias(text) for c in columns]
    whole = each.filter("_words = _size").select(own(F.col("_text")))
    part = each.filter("_words < _size").select(own(_first_words("_text", "_words")))
    return whole.unionByName(part)


def water_level(sizes: list[int], weights: list[float], share: float = 1.5, most: float = 2.0) -> list[float]:
    """Plain resharing, round by round, for tests."""
    left, out, live = share * sum(sizes), [0.0] * len(sizes), set(range(len(sizes)))
    while live:
        unit = left / math.fsum(weights[i] for i in live)
        over = {i for i in live if most * sizes[i] <= unit * weights[i]}
        for i in over or live:
            out[i] = most * sizes[i] if over else unit * weights[i]
        left -= sum(out[i] for i in over)
        live -= over or live
    return out
