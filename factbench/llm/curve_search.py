"""Approximate nearest neighbours by shifted space-filling curves.

Vectors are projected to a few random directions, many times over; each projection is shifted and laid along a
Hilbert curve. Spark range-partitions and sorts every curve; its rows are narrow: a key, an id, and the vector in
bytes. A query meets the rows whose place on a curve is within a window of its own. The bytes bound every score from
both sides, so that what cannot be among the best goes at once; the rest of all curves merge, meet the original
vectors once, and are ranked by exact scores. Equal vectors are one row on the curves, and become their smallest ids
again once ranked.

Windows are the square root of the number of rows and the number of curves grows with its fourth root, so that a
query scores a share of the rows that falls as the table grows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from factbench.llm.common import matrix, settles, stored, valid_vector


def hilbert_keys(cells: np.ndarray, bits: int) -> np.ndarray:
    """Places along the Hilbert curve of points with integer coordinates of ``bits`` bits (a row per point)."""
    x = cells.astype(np.int64).T.copy()
    dims = len(x)
    top = 1 << (bits - 1)
    q = top
    while q > 1:  # undo the excess turns, from the coarsest level down
        low = q - 1
        for i in range(dims):
            turned = (x[i] & q) != 0
            swap = np.where(turned, 0, (x[0] ^ x[i]) & low)
            x[0] ^= np.where(turned, low, swap)
            x[i] ^= swap
        q >>= 1
    for i in range(1, dims):  # reflected binary code
        x[i] ^= x[i - 1]
    t = np.zeros_like(x[0])
    q = top
    while q > 1:
        t ^= np.where((x[-1] & q) != 0, q - 1, 0)
        q >>= 1
    x ^= t
    key = np.zeros_like(t)
    for b in range(bits - 1, -1, -1):
        for i in range(dims):
            key = (key << 1) | ((x[i] >> b) & 1)
    return key


def curve_keys(vectors: np.ndarray, curve: int, dims: int, bits: int) -> np.ndarray:
    """Keys on one curve: seeded directions, coordinates evened out by (nearly) the normal distribution, then shifted."""
    draw = np.random.default_rng([curve, dims, 7919])
    directions = np.linalg.qr(draw.standard_normal((vectors.shape[1], min(dims, vectors.shape[1]))))[0]
    unit = vectors / np.linalg.norm(vectors, axis=1, keepdims=True)
    level = unit @ directions * np.sqrt(vectors.shape[1] / 2.0)
    place = (0.5 + 0.5 * np.tanh(level * 1.128379 + 0.100277 * level**3) + draw.random(directions.shape[1])) / 2.0
    return hilbert_keys(np.minimum((place * (1 << bits)).astype(np.int64), (1 << bits) - 1), bits)


def coded(vectors: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Components as signed bytes, and each vector's scale: byte times scale is within half a scale of the component."""
    scale = np.abs(vectors).max(axis=1) / 127.0
    return np.rint(vectors / scale[:, None]).astype(np.int8), scale


def _on_curves(curves: int, dims: int, bits: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            vectors = matrix(batch.column(1))
            if not len(vectors):
                continue
            codes, scale = coded(vectors)
            packed, scales = pa.array([c.tobytes() for c in codes], pa.binary()), pa.array(scale)
            for curve in range(curves):
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.full(len(vectors), curve, np.int32)), pa.array(curve_keys(vectors, curve, dims, bits)), batch.column(0), packed, scales, batch.column(2)], names=["curve", "key", "vec_id", "code", "scale", "asks"]
                )

    return run


def _numbered(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Number the rows of each curve within a sorted partition."""
    from pyspark import TaskContext

    part, next_of = TaskContext.get().partitionId(), {}
    for batch in batches:
        curve = batch.column(0).to_numpy()
        seq = np.empty(len(curve), np.int64)
        for c in np.unique(curve):
            own = np.flatnonzero(curve == c)
            start = next_of.get(int(c), 0)
            seq[own] = start + np.arange(len(own))
            next_of[int(c)] = start + len(own)
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(np.full(len(curve), part, np.int32)), pa.array(seq)], names=[*PLACED, "part", "seq"])


PLACED = ("curve", "vec_id", "code", "scale", "asks")
BOUNDS = "query_id long, vec_id long, low double, high double"


def _bytes(column: pa.ChunkedArray) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.int8).reshape(len(column), -1).astype(np.float32)


def _bounded(k: int):
    """Rows of a block against the queries whose windows reach it: bounds of the scores that may be among the best ``k``."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        found: list[list[np.ndarray]] = [[np.empty(0, np.int64)], [np.empty(0, np.int64)], [np.empty(0)], [np.empty(0)]]
        if left.num_rows and right.num_rows:
            order = np.argsort(left["rank"].to_numpy())
            ids, ranks, scale = (left[c].to_numpy()[order] for c in ("vec_id", "rank", "scale"))
            rows = _bytes(left["code"])[order]
            half = np.sqrt(np.einsum("ij,ij->i", rows, rows, dtype=np.float64)) * scale + scale * np.sqrt(rows.shape[1])
            queries = matrix(right["vec"])
            firsts = np.searchsorted(ranks, right["rank"].to_numpy() - right["reach"].to_numpy(), "left")
            lasts = np.searchsorted(ranks, right["rank"].to_numpy() + right["reach"].to_numpy(), "right")
            for query, vector, a, b in zip(right["vec_id"].to_numpy(), queries, firsts, lasts, strict=True):
                if a >= b:
                    continue
                near = (rows[a:b] @ vector.astype(np.float32)).astype(np.float64) * scale[a:b]
                # half a scale for each component's rounding, and single precision in the product
                slack = scale[a:b] * (0.5 * np.abs(vector).sum()) + 1e-5 * half[a:b] * np.linalg.norm(vector)
                low, high = near - slack, near + slack
                edge = np.partition(low, max(0, b - a - k))[max(0, b - a - k)]
                kept = np.flatnonzero(high >= edge)
                for column, values in zip(found, (np.full(len(kept), query), ids[a:b][kept], low[kept], high[kept]), strict=True):
                    column.append(values)
        return pa.table(dict(zip(("query_id", "vec_id", "low", "high"), map(np.concatenate, found), strict=True)))

    return run


def _exact(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Scores of (query_id, vec_id, query vector, vector) rows, summed in the order of components."""
    for batch in batches:
        score = np.cumsum(matrix(batch.column(2)) * matrix(batch.column(3)), axis=1)[:, -1] if batch.num_rows else np.empty(0)
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(score)], names=["query_id", "vec_id", "score"])


@settles
def search(vectors: DataFrame, queries: DataFrame, k: int = 20, key: str = "vec_id", column: str = "embedding", curves: int | None = None, dims: int = 10, bits: int = 6, reach: int | None = None, block: int = 4096) -> DataFrame:
    """(query_id, rank, vec_id, score): the ``k`` rows of largest inner product that each query finds, its own id left out.

    ``queries`` has ids of ``vectors`` in ``key``. A query meets, on each of ``curves`` curves (40 and 1.5 times the
    fourth root of the number of distinct vectors), those within ``reach`` places before and after its own (the square
    root of that number); scores are doubles on the original vectors, ties go to the smaller id. Vectors that are
    null, zero or hold null or non-finite components, and rows with a null id, take no part; vectors of different
    lengths don't meet. Of several rows with one id one counts; an empty table gives an empty table; further columns
    are left out.
    """
    valid = vectors.filter(valid_vector(column) & F.col(key).isNotNull()).select(F.col(key).cast("long").alias("vec_id"), F.col(column).alias("vec")).dropDuplicates(["vec_id"])
    valid = stored(valid)
    lengths = sorted(r[0] for r in valid.select(F.size("vec")).distinct().collect())  # one in all but broken tables
    asking = queries.select(F.col(key).cast("long").alias("vec_id")).distinct()
    out = [_of_one_length(valid.filter(F.size("vec") == n), asking, k, curves, dims, bits, reach, block) for n in lengths]
    if not out:
        return valid.select(F.col("vec_id").alias("query_id"), F.lit(1).alias("rank"), "vec_id", F.lit(0.0).alias("score")).limit(0)
    for more in out[1:]:
        out[0] = out[0].unionByName(more)
    return out[0]


def _of_one_length(valid: DataFrame, asking: DataFrame, k: int, curves: int | None, dims: int, bits: int, reach: int | None, block: int) -> DataFrame:
    first_ids = Window.partitionBy("vec").orderBy("vec_id")
    few = valid.withColumn("_n", F.row_number().over(first_ids)).filter(F.col("_n") <= k + 1)  # one may be the query itself
    folded = stored(few.groupBy("vec").agg(F.min("vec_id").alias("vec_id"), F.array_sort(F.collect_list("vec_id")).alias("ids")))
    asking = valid.join(asking, "vec_id", "left_semi").select(F.col("vec_id").alias("query_id"), F.col("vec").alias("_vec"))
    asking = stored(asking.join(folded, F.col("_vec") == F.col("vec")).select("query_id", F.col("vec_id").alias("_rep")))
    asked_reps = asking.select("_rep", F.lit(True).alias("asks")).distinct()
    n = folded.count()
    curves, reach = curves or int(np.ceil(40 + 1.5 * n**0.25)), reach or int(np.ceil(n**0.5))

    laid = folded.join(asked_reps, F.col("vec_id") == F.col("_rep"), "left").select("vec_id", "vec", F.coalesce("asks", F.lit(False)).alias("asks"))
    laid = laid.mapInArrow(_on_curves(curves, dims, bits), "curve int, key long, vec_id long, code binary, scale double, asks boolean")
    order = ["curve", "key", "vec_id"]
    sorted_rows = laid.repartitionByRange(*order).sortWithinPartitions(*order).select(*PLACED)
    placed = stored(sorted_rows.mapInArrow(_numbered, "curve int, vec_id long, code binary, scale double, asks boolean, part int, seq long"))
    counts = placed.groupBy("curve", "part").agg(F.count(F.lit(1)).alias("n"))
    before = Window.partitionBy("curve").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select("curve", "part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("offset"))
    ranked = placed.join(offsets, ["curve", "part"]).withColumn("rank", F.col("offset") + F.col("seq"))
    rows = ranked.select(*[F.col(c).alias(c) for c in ("curve", "vec_id", "rank", "code", "scale")], F.floor(F.col("rank") / block).alias("block"))
    asked = ranked.filter("asks").select("curve", "vec_id", "rank", F.lit(reach).cast("long").alias("reach"))
    first, last = F.floor(F.greatest(F.lit(0), F.col("rank") - F.col("reach")) / block), F.floor(F.least(F.lit(n - 1), F.col("rank") + F.col("reach")) / block)
    vecs = folded.select(F.col("vec_id").alias("_of"), "vec")
    asked = asked.join(vecs, F.col("vec_id") == F.col("_of")).select("curve", F.explode(F.sequence(first, last)).alias("block"), "vec_id", "rank", "reach", "vec")
    bounds = rows.groupBy("curve", "block").cogroup(asked.groupBy("curve", "block")).applyInArrow(_bounded(k + 1), BOUNDS)

    # a pair has the same bounds on every curve; what is below the k-th lower bound of all curves cannot be among the best
    met = bounds.groupBy("query_id", "vec_id").agg(F.max("low").alias("low"), F.max("high").alias("high"))
    edge = Window.partitionBy("query_id").orderBy(F.desc("low"))
    kth = F.max(F.when(F.col("_n") == k + 1, F.col("low"))).over(Window.partitionBy("query_id"))
    near = met.withColumn("_n", F.row_number().over(edge)).withColumn("_edge", kth).filter(F.col("_edge").isNull() | (F.col("high") >= F.col("_edge")))
    pairs = near.select("query_id", "vec_id").join(vecs.withColumnRenamed("vec", "_vec"), F.col("vec_id") == F.col("_of")).drop("_of")
    pairs = pairs.join(vecs, F.col("query_id") == F.col("_of")).select("query_id", "vec_id", F.col("vec").alias("_ask"), "_vec")
    best = pairs.mapInArrow(_exact, "query_id long, vec_id long, score double")
    by_query = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    best = best.withColumn("_n", F.row_number().over(by_query)).filter(F.col("_n") <= k + 1)
    ids = folded.select(F.col("vec_id").alias("_of"), "ids")
    spread = best.join(ids, F.col("vec_id") == F.col("_of")).select("query_id", "score", F.explode("ids").alias("vec_id"))
    spread = spread.withColumn("_n", F.row_number().over(by_query)).filter(F.col("_n") <= k + 1)
    lists = spread.groupBy("query_id").agg(F.array_sort(F.collect_list(F.struct("_n", "vec_id", "score"))).alias("_list")).withColumnRenamed("query_id", "_found")
    told = asking.join(lists, F.col("_rep") == F.col("_found")).select("query_id", F.posexplode(F.slice(F.filter("_list", lambda x: x["vec_id"] != F.col("query_id")), 1, k)).alias("_at", "_x"))
    return told.select("query_id", (F.col("_at") + 1).alias("rank"), F.col("_x.vec_id").alias("vec_id"), F.col("_x.score").alias("score"))
