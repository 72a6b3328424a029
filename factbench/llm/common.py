"""Helpers that several operators share: stored intermediates, exact words, hashed word runs, running sums."""

from __future__ import annotations

import atexit
import ctypes
import functools
import tempfile
import uuid

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401  makes pa.compute available
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: A word: a run without ASCII white space. ``bytes.split()`` cuts at the same six bytes.
WORD = r"[^\x20\x09-\x0D]+"

_stored: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder named in spark.checkpoint.dir, else the checkpoint folder set on the context, else one in the warehouse.

    All executors see the warehouse; a temporary folder of one machine is taken in local mode alone.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    current = spark.sparkContext._jsc.sc().getCheckpointDir()
    if current.isEmpty():
        local = spark.sparkContext.master.startswith("local")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="factbench-") if local else f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/_factbench")
        current = spark.sparkContext._jsc.sc().getCheckpointDir()
    return current.get().rstrip("/")


def stored(df: DataFrame) -> DataFrame:
    """Write ``df`` once to the shared folder and read it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/factbench-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _stored.append((spark, path))
    return spark.read.schema(df.schema).parquet(path)


def _delete(spark: SparkSession, path: str) -> None:
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(hadoop, True)


def settles(f):
    """Store the table that ``f`` returns, and delete all that ``f`` stored on the way to it."""

    @functools.wraps(f)
    def run(*args, **kwargs) -> DataFrame:
        before = len(_stored)
        out = stored(f(*args, **kwargs))
        while len(_stored) > before + 1:
            _delete(*_stored.pop(before))
        return out

    return run


def release() -> None:
    """Delete all that ``stored`` wrote; call it once the results made from it have been written."""
    while _stored:
        try:
            _delete(*_stored.pop())
        except Exception:  # the session has ended; the folder's owner cleans up
            return


atexit.register(release)


def keep_ids(df: DataFrame, ids: DataFrame, key: str, most: int = 2_000_000) -> DataFrame:
    """Rows of ``df`` whose ``key`` is in the stored one-column table ``ids``: broadcast up to ``most`` ids, a shuffle beyond."""
    small = ids.count() <= most
    return df.join(F.broadcast(ids) if small else ids, key, "left_semi")


def running_sum(df: DataFrame, keys: list[str], bucket: str, order: list[Column], value: str, out: str) -> DataFrame:
    """Exclusive running sum of ``value`` inside ``keys``, in the order of (bucket, order), without one task per key.

    Sums are taken per (keys, bucket) with map-side combination, offsets run over those few rows, and each
    bucket adds its own running sum. ``bucket`` must rise with the wanted order and spread a hot key.
    """
    sums = df.groupBy(*keys, bucket).agg(F.sum(value).alias("_sum"))
    over = Window.partitionBy(*keys).orderBy(bucket).rowsBetween(Window.unboundedPreceding, -1)
    offsets = sums.select(
        *[F.col(k).alias(f"_o_{k}") for k in [*keys, bucket]],
        F.coalesce(F.sum("_sum").over(over), F.lit(0)).alias("_offset"),
    )
    on = [df[k].eqNullSafe(offsets[f"_o_{k}"]) for k in [*keys, bucket]]
    within = Window.partitionBy(*keys, bucket).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    return (
        df.join(offsets, on)
        .withColumn(out, F.col("_offset") + F.coalesce(F.sum(value).over(within), F.lit(0)))
        .drop("_offset", *[f"_o_{k}" for k in [*keys, bucket]])
    )


class _WordHashes(dict):
    """64-bit hashes of words; forgets all when full, so that memory stays bounded."""

    most = 100_000

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.most:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word)
        return value


_hashes = _WordHashes()


def word_hashes(text: bytes) -> np.ndarray:
    """One 64-bit hash for each word of a whole text."""
    words = text.split()
    return np.fromiter(map(_hashes.__getitem__, words), np.uint64, len(words))


_STEP = np.uint64(0x9E3779B97F4A7C15)


def run_hashes(hashes: np.ndarray, length: int, step: np.uint64 = _STEP) -> np.ndarray:
    """A 64-bit hash of each run of ``length`` consecutive words; other odd ``step``s give independent ones."""
    n = len(hashes) - length + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    out = np.zeros(n, np.uint64)
    for j in range(length):
        out = out * step + hashes[j : j + n]
    out ^= out >> np.uint64(32)
    out *= np.uint64(0xD6E8FEB86659FD93)
    out ^= out >> np.uint64(32)
    out *= np.uint64(0xD6E8FEB86659FD93)
    out ^= out >> np.uint64(32)
    return out


_trim = getattr(ctypes.CDLL(None), "malloc_trim", None)


def tidy() -> None:
    """Give memory that batches have freed back to the system, as workers share their host with others."""
    pa.default_memory_pool().release_unused()
    if _trim:
        _trim(0)


def text_slices(batches, place: int = 1, most: int = 8 << 20):
    """Batches cut so that the texts in column ``place`` of each part add up to about ``most`` bytes.

    Memory is given back before the first batch and after each, and hashes of words are forgotten at the end, as the
    worker goes on to other work.
    """
    tidy()
    for batch in batches:
        ends = np.asarray(pa.compute.cumulative_sum(pa.compute.fill_null(pa.compute.binary_length(batch.column(place)), 0).cast(pa.int64())))
        start = 0
        while start < batch.num_rows:
            done = ends[start - 1] if start else 0
            stop = max(start + 1, int(np.searchsorted(ends, done + most, "right")))
            yield batch.slice(start, stop - start)
            start = stop
        del batch
        tidy()
    _hashes.clear()
    tidy()


OWNED = "token long, owner long, owners array<long>"


def owned_batch(tokens: list[np.ndarray], owners: list[int]) -> pa.RecordBatch:
    """A row per distinct token of a batch: its smallest owner, and all owners if there are several.

    This is the map-side combination that keeps a token of a third of all documents to a row per batch.
    """
    token = np.concatenate(tokens) if tokens else np.empty(0, np.uint64)
    owner = np.repeat(np.array(owners, np.int64), [len(t) for t in tokens]) if tokens else np.empty(0, np.int64)
    order = np.lexsort((owner, token))
    token, owner = token[order], owner[order]
    first = np.flatnonzero(np.r_[True, token[1:] != token[:-1]]) if len(token) else np.empty(0, np.int64)
    last = np.r_[first[1:], len(token)].astype(np.int64)
    many = last - first > 1
    counts = np.where(many, last - first, 0)
    offsets = np.r_[0, np.cumsum(counts)].astype(np.int32)
    values = owner[np.repeat(many, last - first)] if len(token) else owner
    lists = pa.ListArray.from_arrays(pa.array(offsets), pa.array(values), mask=pa.array(~many))
    return pa.RecordBatch.from_arrays(
        [pa.array(token[first].view(np.int64)), pa.array(owner[first]), lists], names=["token", "owner", "owners"]
    )


def shared_tokens(rows: DataFrame) -> DataFrame:
    """(token, owner) for every token of OWNED rows that two or more owners have.

    A semi-join of the rows with themselves: both sides need the same columns and read one exchange, a hot token
    has a row per batch, and skewed partitions can be split.
    """
    another = (F.col("a.token") == F.col("b.token")) & ((F.col("a.owner") != F.col("b.owner")) | F.col("b.owners").isNotNull())
    kept = rows.alias("a").join(rows.alias("b").hint("merge"), another, "left_semi")
    return kept.select("token", F.explode(F.coalesce("owners", F.array("owner"))).alias("owner"))


def valid_vector(column: str) -> Column:
    """True if a vector is neither null nor zero and holds only finite components."""
    inf = F.lit(float("inf"))
    value = F.col(column)
    finite = F.forall(value, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x.cast("double")) < inf))
    return F.coalesce(value.isNotNull() & finite & F.exists(value, lambda x: x != 0), F.lit(False))


def matrix(column: pa.ChunkedArray | pa.Array, dim: int | None = None) -> np.ndarray:
    """A list column as a two-dimensional array of doubles."""
    whole = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    if len(whole) == 0:
        return np.empty((0, dim or 0))
    return np.asarray(whole.flatten(), dtype=np.float64).reshape(len(whole), -1)
