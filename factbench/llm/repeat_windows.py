"""Substring dedup by level-wise doubling.

Level one looks at windows of half the length, and of those only at anchors: each full window names the least
hash among its half windows, so that equal windows name equal anchors and fewer than a quarter of all places do.
Anchors that a single document has die here. Only around survivors are windows of full length formed and
compared; further doublings (``longest``) again extend survivors alone. Every level counts over all documents.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from numpy.lib.stride_tricks import sliding_window_view
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from factbench.llm.common import OWNED, owned_batch, run_hashes, settles, shared_tokens, stored, text_slices, word_hashes


def _anchored(hashes: np.ndarray, seed: int, window: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of seed runs, and for each full window the place of its anchor (the leftmost least)."""
    seeds = run_hashes(hashes, seed)
    width = window - seed + 1
    if len(seeds) < width:
        return seeds, np.empty(0, np.int64)
    return seeds, sliding_window_view(seeds, width).argmin(axis=1) + np.arange(len(seeds) - width + 1)


def _seed_rows(seed: int, window: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in text_slices(batches):
            tokens, owners = [], []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if doc is None or not text:
                    continue
                seeds, at = _anchored(word_hashes(text), seed, window)
                if len(at):
                    tokens.append(np.unique(seeds[at]))
                    owners.append(doc)
            if tokens:
                yield owned_batch(tokens, owners)

    return run


#: ``twin`` tells the different texts of one id apart (0 for an id with one text); ``more`` are further bits of the window's hash.
WINDOWS = "win long, more int, doc_id long, twin long, pos int, starts array<int>, sure boolean"


def _pairs(starts: np.ndarray) -> np.ndarray:
    """Sorted starts as runs: first, length, first, length ..."""
    first = np.flatnonzero(np.r_[True, np.diff(starts) != 1])
    return np.stack([starts[first], np.diff(np.r_[first, len(starts)])], axis=1).ravel()


def _window_batch(win: np.ndarray, more: np.ndarray, doc: np.ndarray, twin: np.ndarray, pos: np.ndarray) -> pa.RecordBatch:
    """Windows of a batch: those that a smaller document of the batch has are sure; the others are up for comparison."""
    order = np.lexsort((pos, twin, doc, more, win))
    win, more, doc, twin, pos = win[order], more[order], doc[order], twin[order], pos[order]
    fresh = np.r_[True, (win[1:] != win[:-1]) | (more[1:] != more[:-1])]
    least = doc[np.flatnonzero(fresh)][np.cumsum(fresh) - 1]
    sure = doc > least
    lists, wins, docs, twins = [], [], [], []
    again = np.lexsort((pos[sure], twin[sure], doc[sure]))
    d, t, p = doc[sure][again], twin[sure][again], pos[sure][again]
    for part in np.split(np.arange(len(d)), np.flatnonzero((np.diff(d) != 0) | (np.diff(t) != 0)) + 1) if len(d) else []:
        lists.append(_pairs(p[part]))
        docs.append(d[part[0]])
        twins.append(t[part[0]])
        wins.append(hash((int(d[part[0]]), 0x5EED)) & 0x7FFFFFFFFFFFFFFF)  # deals these rows out evenly
    w, m, d, t, p = win[~sure], more[~sure], doc[~sure], twin[~sure], pos[~sure]
    first = np.flatnonzero(np.r_[True, (w[1:] != w[:-1]) | (m[1:] != m[:-1]) | (t[1:] != t[:-1])]) if len(w) else np.empty(0, np.int64)
    # most windows start once in their document: those need no list
    times = np.diff(np.r_[first, len(w)])
    many = np.repeat(times > 1, times)
    values = np.stack([p[many], np.ones(int(many.sum()), np.int64)], axis=1).ravel()
    lengths = np.r_[[len(x) for x in lists], np.where(times > 1, 2 * times, 0)].astype(np.int64)
    single = np.r_[np.zeros(len(lists), bool), times == 1]
    starts = pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(lengths)].astype(np.int32)), pa.array(np.concatenate([*lists, values]).astype(np.int32)), mask=pa.array(single))
    return pa.RecordBatch.from_arrays(
        [
            pa.array(np.r_[np.array(wins, np.int64), w[first].view(np.int64)]),
            pa.array(np.r_[np.zeros(len(wins), np.int32), m[first]]),
            pa.array(np.r_[np.array(docs, np.int64), d[first]]),
            pa.array(np.r_[np.array(twins, np.int64), t[first]]),
            pa.array(np.r_[np.full(len(docs), -1), p[first]].astype(np.int32)),
            starts,
            pa.array(np.r_[np.ones(len(docs), bool), np.zeros(len(first), bool)]),
        ],
        names=["win", "more", "doc_id", "twin", "pos", "starts", "sure"],
    )


def _window_rows(seed: int, window: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in text_slices(batches, most=4 << 20):
            found: list[list[np.ndarray]] = []
            alive, twins = batch.column(2), batch.column(3).to_pylist()
            for i, (doc, text) in enumerate(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)):
                if not alive[i].is_valid or not text:
                    continue
                hashes = word_hashes(text)
                seeds, at = _anchored(hashes, seed, window)
                kept = np.asarray(alive[i].values).view(np.uint64)
                pos = np.flatnonzero(np.isin(seeds[at], kept))
                if len(pos):
                    # 96 bits: two windows of 64 equal bits are common among very many
                    further = (run_hashes(hashes, window, _OTHER)[pos] >> np.uint64(32)).astype(np.uint32).view(np.int32)
                    found.append([run_hashes(hashes, window)[pos], further, np.full(len(pos), doc, np.int64), np.full(len(pos), twins[i], np.int64), pos])
            if found:
                yield _window_batch(*(np.concatenate(column) for column in zip(*found, strict=True)))

    return run


_OTHER = np.uint64(0xC2B2AE3D27D4EB4F)


def _cut(window: int, names: list[str]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in text_slices(batches):
            totals, removed, kept = [], [], []
            for text, starts in zip(part.column(1).to_pylist(), part.column(2), strict=True):
                words = text.split() if text else []
                gone, last = 0, len(words) - window + 1
                if starts.is_valid and last > 0:
                    runs = np.asarray(starts.values).reshape(-1, 2)
                    edge = np.zeros(len(words) + 1, np.int64)
                    np.add.at(edge, runs[:, 0], 1)
                    np.add.at(edge, np.minimum(runs[:, 0] + runs[:, 1], last) - 1 + window, -1)
                    stays = np.cumsum(edge[:-1]) == 0
                    gone = len(words) - int(stays.sum())
                    words = [w for w, s in zip(words, stays.tolist(), strict=True) if s] if gone else words
                totals.append(len(words) + gone)
                removed.append(gone)
                kept.append(b" ".join(words))
            yield pa.RecordBatch.from_arrays(
                [part.column(0), pa.array(totals, pa.int64()), pa.array(removed, pa.int64()), pa.array(kept, pa.binary()), part.column(1), *part.columns[3:]], names=names
            )

    return run


def _twin(doc: str, text: str, several: DataFrame, docs: DataFrame) -> DataFrame:
    """``docs`` with ``twin``: 0, or a hash of the text for ids that have several texts."""
    small = several.count() <= 2_000_000
    marked = docs.join(F.broadcast(several) if small else several, F.col(doc) == F.col("_several"), "left")
    return marked.withColumn("twin", F.when(F.col("_several").isNull(), F.lit(0).cast("long")).otherwise(F.xxhash64(text))).drop("_several")


@settles
def _ids_of_several_texts(docs: DataFrame, key: str, text: str) -> DataFrame:
    kinds = docs.filter(F.col(key).isNotNull()).select(F.col(key).cast("long").alias("_several"), F.xxhash64(F.col(text).cast("binary")).alias("_t"))
    return kinds.groupBy("_several").agg(F.min("_t").alias("a"), F.max("_t").alias("b")).filter("a < b").select("_several")


@settles
def repeated_windows(docs: DataFrame, window: int = 13, key: str = "doc_id", text: str = "text", several: DataFrame | None = None) -> DataFrame:
    """(doc_id, twin, starts): where a document's windows start that also start in a document with a smaller id.

    ``starts`` are runs: first word, number of starts, and so on. Documents without any don't appear. Rows with one
    id and different texts are told apart by ``twin``, and don't count as repeats of each other. ``several`` has
    the ids with different texts in ``_several``, if they are known.
    """
    seed = max(1, window // 2)
    several = _ids_of_several_texts(docs, key, text) if several is None else several
    whole = _twin("doc_id", "text", several, docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).cast("binary").alias("text"))).filter("doc_id is not null")
    # equal texts: all windows of all but the first repeat, and only the first goes on
    same = whole.select("doc_id", "twin", F.md5("text").alias("same"))
    first = same.groupBy("same").agg(F.min("doc_id").alias("first"), F.max("doc_id").alias("last")).filter("first < last").drop("last")
    copies = stored(same.join(first, "same").filter("doc_id > first").select("doc_id", "twin").distinct())
    few = copies.count() <= 2_000_000
    whole = whole.join(F.broadcast(copies) if few else copies, ["doc_id", "twin"], "left_anti")
    # one number stands for (id, twin) up to the comparison
    whole = whole.withColumn("owner", F.when(F.col("twin") == 0, F.col("doc_id")).otherwise(F.xxhash64("doc_id", "twin")))
    anchors = shared_tokens(whole.select("owner", "text").mapInArrow(_seed_rows(seed, window), OWNED))
    alive = stored(anchors.groupBy("owner").agg(F.collect_list("token").alias("alive")).withColumnRenamed("owner", "_doc"))
    if alive.count() <= 2_000_000:  # a short list keeps other texts out of the shuffle
        whole = whole.join(F.broadcast(alive.select(F.col("_doc").alias("owner"))), "owner", "left_semi")
    near = whole.join(alive, whole["owner"] == alive["_doc"]).select("doc_id", "text", "alive", "twin")
    rows = stored(near.mapInArrow(_window_rows(seed, window), WINDOWS))
    # a window stays if a smaller document has it; sure ones meet themselves. Both sides read one exchange.
    smaller = F.col("a.sure") | (F.col("b.doc_id") < F.col("a.doc_id")) & (F.col("b.more") == F.col("a.more")) & ~F.col("b.sure") & ((F.col("b.pos") >= 0) | F.col("b.starts").isNotNull() | F.col("b.twin").isNull())
    found = rows.alias("a").join(rows.alias("b").hint("merge"), (F.col("a.win") == F.col("b.win")) & smaller, "left_semi")
    runs = F.coalesce("starts", F.array("pos", F.lit(1)))
    starts = found.groupBy("doc_id", "twin").agg(F.flatten(F.collect_list(runs)).alias("starts"))
    return starts.unionByName(copies.select("doc_id", "twin", F.array(F.lit(0), F.lit(1 << 30)).alias("starts")))


def remove_repeats(docs: DataFrame, window: int = 13, key: str = "doc_id", text: str = "text", carry: list[str] | None = None) -> DataFrame:
    """(doc_id, n_words, n_removed, kept, text): each whole text without the words that repeated windows cover.

    A window is ``window`` consecutive words of one document; it counts as repeated if its words also start in a
    document with a smaller id, judged on the input. ``kept`` has the other words, joined by one space, and
    ``text`` the input. Null and empty texts have no words. Rows with a null id keep all words and take no part.
    Repeated rows (same id, same text) are one document and each lose the same words; rows with one id and different
    texts each lose only their own, and are no repeats of each other. An empty table gives an empty table; further
    columns are left out but for those in ``carry``, whose names may not clash with these.
    """
    several = _ids_of_several_texts(docs, key, text)
    found = repeated_windows(docs, window, key, text, several).withColumnsRenamed({"doc_id": "_doc", "twin": "_twin"})
    more = carry or []
    whole = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).cast("binary").alias("text"), *[F.col(c).alias(f"_carry{n}") for n, c in enumerate(more)])
    whole = _twin("doc_id", "text", several, whole)
    joined = whole.join(found, (whole["doc_id"] == found["_doc"]) & (whole["twin"] == found["_twin"]), "left").select("doc_id", "text", "starts", *[F.col(f"_carry{n}").alias(c) for n, c in enumerate(more)])
    names = ["doc_id", "n_words", "n_removed", "kept", "text", *more]
    kinds = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in more)
    out = joined.mapInArrow(_cut(window, names), "doc_id long, n_words long, n_removed long, kept binary, text binary" + (f", {kinds}" if more else ""))
    return out.withColumns({c: F.col(c).cast("string") for c in ("kept", "text")})


def _longer(window: int):
    """Windows of one length whose first and second half both start where the half length repeats."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            tokens, owners = [], []
            for doc, text, starts in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                if doc is None or not text or not starts.is_valid:
                    continue
                pos = _at(np.asarray(starts.values), word_count := len(text.split()), window)
                if len(pos) and word_count >= window:
                    tokens.append(np.unique(run_hashes(word_hashes(text), window)[pos]))
                    owners.append(doc)
            if tokens:
                yield owned_batch(tokens, owners)

    return run


def _at(runs: np.ndarray, words: int, window: int) -> np.ndarray:
    alive = np.zeros(words + 1, bool)
    for first, length in runs.reshape(-1, 2):
        alive[first : first + length] = True
    half = window // 2
    n = words - window + 1
    return np.flatnonzero(alive[:n] & alive[half : half + n]) if n > 0 else np.empty(0, np.int64)


def longest(docs: DataFrame, window: int = 13, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, length): the longest length of window, twice window and so on at which a document shares words with another.

    Each level forms windows of twice the length only where both halves survived, until none survives.
    """
    whole = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).cast("binary").alias("text"))
    length, out = window, None
    alive = stored(_everywhere(whole, window))
    while alive.limit(1).count():
        level = alive.select("doc_id", F.lit(length).alias("length"))
        out = level if out is None else out.unionByName(level)
        length *= 2
        near = whole.join(alive.withColumnRenamed("doc_id", "_doc"), F.col("doc_id") == F.col("_doc")).select("doc_id", "text", "starts")
        tokens = shared_tokens(near.mapInArrow(_longer(length), OWNED)).groupBy(F.col("owner").alias("_doc")).agg(F.collect_list("token").alias("alive"))
        again = near.join(tokens, F.col("doc_id") == F.col("_doc")).select("doc_id", "text", "alive")
        alive = stored(again.mapInArrow(_places(length), "doc_id long, starts array<int>"))
    empty = whole.select("doc_id", F.lit(0).alias("length")).limit(0)
    return (empty if out is None else out).groupBy("doc_id").agg(F.max("length").alias("length"))


def _everywhere(whole: DataFrame, window: int) -> DataFrame:
    seed = max(1, window // 2)
    anchors = shared_tokens(whole.mapInArrow(_seed_rows(seed, window), OWNED)).groupBy(F.col("owner").alias("_doc")).agg(F.collect_list("token").alias("alive"))
    near = whole.join(anchors, F.col("doc_id") == F.col("_doc")).select("doc_id", "text", "alive")

    def windows(batches):
        for batch in batches:
            tokens, owners = [], []
            for doc, text, alive in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                hashes = word_hashes(text)
                seeds, at = _anchored(hashes, seed, window)
                tokens.append(np.unique(run_hashes(hashes, window)[np.isin(seeds[at], np.asarray(alive.values).view(np.uint64))]))
                owners.append(doc)
            if tokens:
                yield owned_batch(tokens, owners)

    full = shared_tokens(near.mapInArrow(windows, OWNED)).groupBy(F.col("owner").alias("_doc")).agg(F.collect_list("token").alias("alive"))
    again = whole.join(full, F.col("doc_id") == F.col("_doc")).select("doc_id", "text", "alive")
    return again.mapInArrow(_places(window), "doc_id long, starts array<int>")


def _places(window: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            docs, lists = [], []
            for doc, text, alive in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                pos = np.flatnonzero(np.isin(run_hashes(word_hashes(text), window), np.asarray(alive.values).view(np.uint64)))
                if len(pos):
                    docs.append(doc)
                    lists.append(_pairs(pos).astype(np.int32))
            if docs:
                yield pa.RecordBatch.from_arrays([pa.array(docs, pa.int64()), pa.array(lists, pa.list_(pa.int32()))], names=["doc_id", "starts"])

    return run
