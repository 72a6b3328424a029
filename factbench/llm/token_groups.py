"""N-gram Jaccard join by a token-group matrix.

Documents with equal shingle sets count once. Similar ones, by the least document that shares a min-hash key, form
a group, and large groups are dealt into cells of bounded size. Those that link with that least document are
connected from the start; connected pairs need no further look, as the result is connectivity.

The matrix holds, for every cell, which tokens some member has: exactly for prefix tokens, and for all tokens as
bits of hashed tokens, two to four a token. Every set bit of a document that a cell's union lacks is at least one
token missing there. A document opens a cell only if they share a prefix token and the bound on its overlap with
the union reaches the threshold; then it is compared with all members exactly, as a product of token matrices.
No pair above the threshold is missed, and a cell gives as many rows as it has linked documents, not links.

Prefixes follow one order of all tokens: those frequent anywhere come last, so that common passages open nothing.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from factbench.llm.common import keep_ids, OWNED, owned_batch, run_hashes, settles, shared_tokens, stored, text_slices, word_hashes
from factbench.llm.components import connected, spanning

KEYS, PER_KEY = 6, 3
#: A token that so many documents of one batch have is counted over all batches.
LOCAL = 4

FEATURES = "doc_id long, n_shingles long, sig_a long, sig_b long, keys array<long>, bits binary, token long, count long"


def shingle_set(text: bytes | None, words: int) -> np.ndarray:
    """Sorted distinct hashes of the runs of ``words`` words, A-Z lower-cased; all words as one run if there are fewer."""
    hashes = word_hashes(text.lower()) if text else np.empty(0, np.uint64)
    if not len(hashes):
        return hashes
    return np.unique(run_hashes(hashes, min(words, len(hashes))))


_WEIGHTS = np.uint64(0xA0761D6478BD642F)


def _signature(tokens: np.ndarray) -> tuple[int, int]:
    """128 bits that stand for a whole set."""
    a = (tokens * _WEIGHTS) ^ (tokens >> np.uint64(29))
    b = (tokens ^ _WEIGHTS) * np.uint64(0xE7037ED1A0B428DB)
    b ^= b >> np.uint64(31)
    return int(np.sum(a, dtype=np.uint64).view(np.int64)), int(np.sum(b * b | np.uint64(1), dtype=np.uint64).view(np.int64))


def _min_keys(tokens: np.ndarray) -> list[int]:
    """Keys of PER_KEY minima each: the first token at or after evenly spaced bounds of the hash range, wrapping round."""
    bounds = (np.arange(KEYS * PER_KEY, dtype=np.float64) / (KEYS * PER_KEY) * 2.0**64).astype(np.uint64)
    least = tokens[np.searchsorted(tokens, bounds) % len(tokens)].reshape(PER_KEY, KEYS)
    mixed = np.arange(1, KEYS + 1, dtype=np.uint64)
    for row in least:
        mixed = (mixed ^ row) * np.uint64(0x9FB21C651E98DF25)
        mixed ^= mixed >> np.uint64(35)
    return mixed.view(np.int64).tolist()


def token_bits(tokens: np.ndarray) -> bytes:
    """A bit for each of two to four times as many token hashes, modulo a power of two."""
    size = max(64, 1 << int(2 * len(tokens) - 1).bit_length())
    bits = np.zeros(size, np.uint8)
    bits[(tokens & np.uint64(size - 1)).astype(np.int64)] = 1
    return np.packbits(bits).tobytes()


def _fold(bits: np.ndarray, size: int) -> np.ndarray:
    """Bits of a larger table as those of one of ``size`` bytes."""
    return bits if len(bits) == size else np.bitwise_or.reduce(bits.reshape(-1, size), axis=0)


def missing(a: bytes, b: bytes) -> int:
    """A lower bound of how many tokens of the set behind ``a`` the one behind ``b`` lacks."""
    x, y = np.frombuffer(a, np.uint8), np.frombuffer(b, np.uint8)
    size = min(len(x), len(y))
    return int(np.bitwise_count(_fold(x, size) & ~_fold(y, size)).sum())


def _union_bits(table: pa.Table) -> pa.Table:
    """The union of a group's tokens; folded to the smallest of its members' tables."""
    parts = [np.frombuffer(b, np.uint8) for b in table["bits"].to_pylist()]
    size = min(len(p) for p in parts)
    union = np.bitwise_or.reduce([_fold(p, size) for p in parts])
    return pa.table({"grp": table["grp"][:1], "part": table["part"][:1], "union": pa.array([union.tobytes()], pa.binary())})


def _open_rows(threshold: int):
    """Of (rep, grp, part, n, bits, union): those whose overlap with the union may reach the threshold."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, own, union = (batch.column(i).to_pylist() for i in (3, 4, 5))
            ok = [100 * (k - missing(a, b)) >= threshold * k for k, a, b in zip(n, own, union, strict=True)]
            yield pa.RecordBatch.from_arrays([c.filter(pa.array(ok)) for c in batch.columns[:4]], names=["rep", "grp", "part", "n"])

    return run


def _chunks(sizes: np.ndarray, cells: int) -> Iterator[slice]:
    """Runs of rows whose number times their sum of sizes is at most ``cells``, one row at least."""
    start = 0
    while start < len(sizes):
        sums = np.cumsum(sizes[start:]) * np.arange(1, len(sizes) - start + 1)
        stop = start + max(1, int(np.searchsorted(sums, cells, "right")))
        yield slice(start, stop)
        start = stop


def _opened(threshold: int, cells: int = 6_000_000):
    """Members of a cell against the documents that open it: links between different components, as spanning rows.

    Both sides go in chunks, so that no matrix of tokens has much more than ``cells`` entries.
    """

    def run(members: pa.Table, askers: pa.Table) -> pa.Table:
        found_a, found_b = [], []
        if members.num_rows and askers.num_rows:
            all_ids, all_of, all_sets = members["rep"].to_numpy(), members["own"].to_numpy(), [np.asarray(x.values) for x in members["tokens"]]
            q_ids, q_of = askers["q_rep"].to_numpy(), askers["q_own"].to_numpy()
            for chunk in _chunks(np.array([len(t) for t in all_sets]), cells):
                ids, of, sets = all_ids[chunk], all_of[chunk], all_sets[chunk]
                sizes = np.array([len(t) for t in sets])
                known, place = np.unique(np.concatenate(sets), return_inverse=True)
                matrix = np.zeros((len(sets), len(known)), np.float32)
                matrix[np.repeat(np.arange(len(sets)), sizes), place] = 1
                at_once = max(1, cells // len(known))
                for start in range(0, askers.num_rows, at_once):
                    some = [np.asarray(x.values) for x in askers["q_tokens"].slice(start, at_once)]
                    q_sizes = np.array([len(t) for t in some])
                    flat = np.concatenate(some)
                    at = np.minimum(np.searchsorted(known, flat), len(known) - 1)
                    hit = known[at] == flat
                    asked = np.zeros((len(some), len(known)), np.float32)
                    asked[np.repeat(np.arange(len(some)), q_sizes)[hit], at[hit]] = 1
                    common = np.rint(asked @ matrix.T).astype(np.int64)
                    linked = 100 * common >= threshold * (q_sizes[:, None] + sizes[None, :] - common)
                    linked &= q_of[start : start + at_once, None] != of[None, :]
                    i, j = np.nonzero(linked)
                    if len(i):
                        nodes, least = spanning(q_ids[start + i], ids[j])
                        found_a.append(nodes[nodes != least])
                        found_b.append(least[nodes != least])
        empty = np.empty(0, np.int64)
        return pa.table({"a": np.concatenate([empty, *found_a]), "b": np.concatenate([empty, *found_b])})

    return run


def _pair_rows(threshold: int):
    """Of (a, b, n_a, n_b, bits_a, bits_b): pairs that may link."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n_a, n_b, bits_a, bits_b = (batch.column(i).to_pylist() for i in (2, 3, 4, 5))
            ok = []
            for na, nb, a, b in zip(n_a, n_b, bits_a, bits_b, strict=True):
                common = min(na - missing(a, b), nb - missing(b, a))
                ok.append(100 * common >= threshold * (na + nb - common))
            yield pa.RecordBatch.from_arrays([c.filter(pa.array(ok)) for c in batch.columns[:2]], names=["a", "b"])

    return run


def _feature_rows(words: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in text_slices(batches):
            rows, sets, seen = [], [], set()
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                tokens = shingle_set(text, words)
                if len(tokens):
                    sig = _signature(tokens)
                    rows.append((doc, len(tokens), *sig, _min_keys(tokens), token_bits(tokens)))
                    if sig not in seen:
                        seen.add(sig)
                        sets.append(tokens)
                else:
                    rows.append((doc, 0, None, None, None, None))
            token, count = np.unique(np.concatenate(sets), return_counts=True) if sets else (np.empty(0, np.uint64), np.empty(0, np.int64))
            often = count >= LOCAL
            token, count = token[often], count[often]
            pad = len(token)
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.binary()]
            columns = [pa.array([*(r[i] for r in rows), *[None] * pad], kind) for i, kind in enumerate(kinds)]
            columns.append(pa.concat_arrays([pa.nulls(len(rows), pa.int64()), pa.array(token.view(np.int64))]))
            columns.append(pa.concat_arrays([pa.nulls(len(rows), pa.int64()), pa.array(count.astype(np.int64))]))
            yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_shingles", "sig_a", "sig_b", "keys", "bits", "token", "count"])

    return run


def _prefix_rows(words: int, threshold: int, frequent):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        late = frequent.value
        for batch in text_slices(batches):
            tokens, owners = [], []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                own = shingle_set(text, words)
                if doc is None or not len(own):
                    continue
                n = len(own) - -(-len(own) * threshold // 100) + 1
                if len(late):
                    at = np.searchsorted(late, own)
                    common = late[np.minimum(at, len(late) - 1)] == own
                    own = np.r_[own[~common], own[common]]
                tokens.append(own[:n])
                owners.append(doc)
            if tokens:
                yield owned_batch(tokens, owners)

    return run


def _set_rows(words: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in text_slices(batches):
            sets = [shingle_set(t, words).view(np.int64) for t in part.column(1).to_pylist()]
            offsets = np.r_[0, np.cumsum([len(s) for s in sets])].astype(np.int32)
            values = np.concatenate(sets) if sets else np.empty(0, np.int64)
            yield pa.RecordBatch.from_arrays([part.column(0), pa.ListArray.from_arrays(pa.array(offsets), pa.array(values))], names=["doc_id", "tokens"])

    return run


def _linked(common: Column, n_a: Column, n_b: Column, threshold: int) -> Column:
    return 100 * common >= threshold * (n_a + n_b - common)


def _exact(pairs: DataFrame, reps: DataFrame, whole: DataFrame, words: int, threshold: int) -> DataFrame:
    """Those of the (a, b) pairs whose whole sets link; pairs that their bits rule out don't meet the sets."""
    side = lambda x: reps.select(F.col("rep").alias(x), F.col("n_shingles").alias(f"n_{x}"), F.col("bits").alias(f"bits_{x}"))
    known = pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "n_a", "n_b", "bits_a", "bits_b")
    near = stored(known.mapInArrow(_pair_rows(threshold), "a long, b long"))
    ids = stored(near.select(F.col("a").alias("doc_id")).union(near.select(F.col("b").alias("doc_id"))).distinct())
    sets = keep_ids(whole, ids, "doc_id").mapInArrow(_set_rows(words), "doc_id long, tokens array<long>")
    sets = stored(sets)
    a = sets.select(F.col("doc_id").alias("a"), F.col("tokens").alias("ta"))
    b = sets.select(F.col("doc_id").alias("b"), F.col("tokens").alias("tb"))
    joined = near.join(a, "a").join(b, "b").withColumn("common", F.size(F.array_intersect("ta", "tb")))
    return joined.filter(_linked(F.col("common"), F.size("ta"), F.size("tb"), threshold)).select("a", "b")


def _frequent(counts: DataFrame, most: int = 1_000_000) -> np.ndarray:
    """Tokens counted most, at most ``most`` of them, sorted. They only decide an order; any choice gives the same links."""
    kept = stored(counts)
    bound, n = LOCAL, kept.count()
    while n > most:
        bound *= 2
        n = kept.filter(F.col("count") >= bound).count()
    rows = kept.filter(F.col("count") >= bound).select("token").toPandas()
    return np.sort(rows["token"].to_numpy(np.int64).view(np.uint64))


@settles
def link_groups(docs: DataFrame, words: int = 4, threshold: int = 85, key: str = "doc_id", text: str = "text", group_rows: int = 256, group_tokens: int = 1_000_000) -> DataFrame:
    """(doc_id, n_shingles, component_id) for every document.

    Two documents link when 100 * intersection >= ``threshold`` * union of their sets of distinct ``words``-word
    shingles (A-Z lower-cased, words cut at ASCII white space; fewer words form one shingle). ``component_id`` is
    the smallest id that links reach, the document's own without links. Null and empty texts have no shingles and
    link with nothing. A null id is kept with component null and links with nothing. Repeated rows each give a row;
    rows with one id and different texts are compared by the texts, and one id stands for all of them in links;
    an empty table gives an empty table; further columns are left out. A cell has about ``group_rows`` documents of
    about ``group_tokens`` shingles together; a longer document is a cell of its own. Shingles are compared by 64-bit
    hashes: two of n in a pair of documents fall together with a chance of n * n / 2 ** 64.
    """
    spark = docs.sparkSession
    whole = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).cast("binary").alias("text"))
    found = stored(whole.mapInArrow(_feature_rows(words), FEATURES))
    features = found.filter("token is null").drop("token", "count")
    late = spark.sparkContext.broadcast(_frequent(found.filter("token is not null").groupBy("token").agg(F.sum("count").alias("count"))))

    # documents with equal sets count once, as the one with the least id
    alike = features.filter("n_shingles > 0 and doc_id is not null").groupBy("sig_a", "sig_b", "n_shingles").agg(F.min("doc_id").alias("rep"), F.min("keys").alias("keys"), F.min("bits").alias("bits"))
    alike = stored(alike)

    # groups: similar documents have the least document of a min-hash key in common; links with it come first
    keyed = alike.select("rep", F.explode("keys").alias("k"))
    pivots = keyed.groupBy("k").agg(F.min("rep").alias("pivot"), F.max("rep").alias("other")).filter("pivot < other").drop("other")
    tries = stored(keyed.join(pivots, "k").filter("rep > pivot").select(F.col("rep").alias("a"), F.col("pivot").alias("b")).distinct())
    links = stored(_exact(tries, alike, whole, words, threshold))
    first = stored(connected(links))
    near = tries.groupBy("a").agg(F.min("b").alias("_pivot"))
    members = alike.select("rep", "n_shingles").join(first, F.col("rep") == F.col("node"), "left").join(near, F.col("rep") == F.col("a"), "left")
    members = stored(members.select("rep", "n_shingles", F.coalesce("component", "rep").alias("own"), F.coalesce("_pivot", "rep").alias("grp")))
    # only groups of more than one cell are in this list, so it is short, and no hot group is shuffled for it
    size = F.ceil(F.greatest(F.count(F.lit(1)) / group_rows, F.sum("n_shingles") / group_tokens))
    parts = stored(members.groupBy("grp").agg(size.alias("parts")).filter("parts > 1").withColumnRenamed("grp", "_grp"))
    few = parts.count() <= 2_000_000
    members = members.join(F.broadcast(parts) if few else parts, F.col("grp") == F.col("_grp"), "left").drop("_grp")
    members = stored(members.withColumn("part", F.pmod(F.xxhash64("rep"), F.coalesce("parts", F.lit(1))).cast("int")).drop("parts"))

    # the matrix of prefix tokens and cells
    shared = shared_tokens(whole.mapInArrow(_prefix_rows(words, threshold, late), OWNED))
    rows = stored(shared.join(members, F.col("owner") == F.col("rep")).select("token", "rep", "n_shingles", "own", "grp", "part"))
    ends = lambda c: (F.min(c).alias(f"{c}_0"), F.max(c).alias(f"{c}_1"))
    cells = rows.groupBy("token", "grp", "part").agg(*ends("n_shingles"), *ends("own"))
    several = cells.groupBy("token").agg(F.min("own_0").alias("o0"), F.max("own_1").alias("o1")).filter("o0 < o1").select("token")
    ask = rows.join(several, "token", "left_semi").withColumnsRenamed({"grp": "q_grp", "part": "q_part"})
    fits = (100 * F.col("n_shingles") >= threshold * F.col("n_shingles_0")) & (100 * F.col("n_shingles_1") >= threshold * F.col("n_shingles"))
    other = (F.col("own") != F.col("own_0")) | (F.col("own") != F.col("own_1"))  # the cell holds another component
    once = F.struct("grp", "part") <= F.struct(F.col("q_grp").alias("grp"), F.col("q_part").alias("part"))
    asked = stored(ask.join(cells, "token").filter(fits & other & once).select("rep", "grp", "part").distinct())

    # the bound on the overlap with a cell's union; cells that pass are opened, for so many documents at a time
    inside = members.join(asked.select("grp", "part").distinct(), ["grp", "part"]).join(alike.select("rep", "bits"), "rep")
    unions = inside.select("grp", "part", "bits").groupBy("grp", "part").applyInArrow(_union_bits, "grp long, part int, union binary")
    facing = asked.join(alike.select("rep", "n_shingles", "bits"), "rep").join(unions, ["grp", "part"]).select("rep", "grp", "part", "n_shingles", "bits", "union")
    passing = stored(facing.mapInArrow(_open_rows(threshold), "rep long, grp long, part int, n long"))
    size = F.ceil(F.greatest(F.count(F.lit(1)) / (4 * group_rows), F.sum("n") / (4 * group_tokens))).cast("int")
    turns = passing.groupBy("grp", "part").agg(size.alias("turns"))
    passing = passing.drop("n")
    opened = members.join(turns, ["grp", "part"])
    ids = stored(passing.select(F.col("rep").alias("doc_id")).union(opened.select("rep")).distinct())
    sets = stored(keep_ids(whole, ids, "doc_id").mapInArrow(_set_rows(words), "doc_id long, tokens array<long>"))
    left = opened.withColumn("turn", F.explode(F.sequence(F.lit(0), F.col("turns") - 1))).join(sets, F.col("rep") == F.col("doc_id"))
    left = left.select("grp", "part", "turn", "rep", "own", "tokens")
    right = passing.join(turns, ["grp", "part"]).withColumn("turn", F.pmod(F.xxhash64("rep"), F.col("turns")).cast("int"))
    right = right.join(sets, F.col("rep") == F.col("doc_id")).join(members.select(F.col("rep").alias("_rep"), F.col("own").alias("_own")), F.col("rep") == F.col("_rep"))
    right = right.select(*[F.col(c).alias(f"q_{c}") for c in ("grp", "part", "turn", "rep")], F.col("_own").alias("q_own"), F.col("tokens").alias("q_tokens"))
    crossing = stored(left.groupBy("grp", "part", "turn").cogroup(right.groupBy("q_grp", "q_part", "q_turn")).applyInArrow(_opened(threshold), "a long, b long"))

    # links across join whole components
    bound = crossing.join(members.select(F.col("rep").alias("a"), F.col("own").alias("oa")), "a").join(members.select(F.col("rep").alias("b"), F.col("own").alias("ob")), "b")
    joined = connected(bound.select("oa", "ob"), "oa", "ob")
    final = members.join(joined, F.col("own") == F.col("node"), "left").select("rep", F.coalesce("component", "own").alias("component_id"))
    by_set = alike.join(final, "rep").select("sig_a", "sig_b", F.col("n_shingles").alias("_n"), "component_id")
    out = features.join(by_set, (features["sig_a"] == by_set["sig_a"]) & (features["sig_b"] == by_set["sig_b"]) & (features["n_shingles"] == by_set["_n"]) & features["doc_id"].isNotNull(), "left")
    return out.select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))
