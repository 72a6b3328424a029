"""Sharding by best-fit-decreasing bin packing of indivisible groups.

Groups of equal texts above a fixed share of a shard are items of their own: there can only be so many. All
smaller groups fall, by the hash of their text, into a fixed number of pools, each an item too. So the packing
sees a bounded number of items whatever the input, and a group always stays whole. Packing pools instead of the small
groups in them costs at most the room that a pool leaves: under one part in ``finest`` of a shard.

Either the number of shards is given, and they are filled near equally, or a capacity, and they are the fewest that
best fit decreasing opens.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from factbench.llm.common import running_sum, stored


class RoomTree:
    """A treap of (remaining room, bin): finds the tightest bin that still holds a size in logarithmic time."""

    def __init__(self):
        self.root = None

    @staticmethod
    def _rank(key):
        return hash((key[1] * 2654435761 + 12345) & 0xFFFFFFFF) * 2246822519 & 0xFFFFFFFF

    def _merge(self, a, b):
        if not a or not b:
            return a or b
        if a[1] > b[1]:
            a[3] = self._merge(a[3], b)
            return a
        b[2] = self._merge(a, b[2])
        return b

    def _split(self, node, key):
        """(nodes below key, the rest)"""
        if not node:
            return None, None
        if node[0] < key:
            low, high = self._split(node[3], key)
            node[3] = low
            return node, high
        low, high = self._split(node[2], key)
        node[2] = high
        return low, node

    def add(self, room: int, bin_no: int) -> None:
        key = (room, bin_no)
        low, high = self._split(self.root, key)
        self.root = self._merge(self._merge(low, [key, self._rank(key), None, None]), high)

    def take(self, size: int) -> tuple[int, int] | None:
        """Remove and return the (room, bin) with the least room of at least ``size``."""
        low, high = self._split(self.root, (size, -1))
        if not high:
            self.root = low
            return None
        node, parent = high, None
        while node[2]:
            parent, node = node, node[2]
        if parent:
            parent[2] = node[3]
        else:
            high = node[3]
        self.root = self._merge(low, high)
        return node[0]

    def take_roomiest(self) -> tuple[int, int]:
        """Remove and return the (room, bin) with the most room."""
        node = self.root
        while node[3]:
            node = node[3]
        key = node[0]
        self.root = self._split(self.root, key)[0]
        return key


def best_fit(sizes: list[int], capacity: int, most: int | None = None) -> list[int] | None:
    """The bin of each item when items, largest first, enter the tightest bin; new bins open as needed.

    None if more than ``most`` bins would be needed. An item above the capacity fills a bin alone.
    """
    tree, out, bins = RoomTree(), [0] * len(sizes), 0
    for i in sorted(range(len(sizes)), key=lambda i: (-sizes[i], i)):
        found = tree.take(sizes[i])
        if found is None:
            if bins == most:
                return None
            found = (max(capacity, sizes[i]), bins)
            bins += 1
        out[i] = found[1]
        tree.add(found[0] - sizes[i], found[1])
    return out


def spilled(sizes: list[int], capacity: int, bins: int) -> list[int]:
    """Best fit into a fixed number of bins; an item that fits nowhere goes to the roomiest."""
    tree, out = RoomTree(), [0] * len(sizes)
    for b in range(bins):
        tree.add(capacity, b)
    for i in sorted(range(len(sizes)), key=lambda i: (-sizes[i], i)):
        room, out[i] = tree.take(sizes[i]) or tree.take_roomiest()
        tree.add(room - sizes[i], out[i])
    return out


def near_equal(sizes: list[int], shards: int) -> list[int]:
    """Bins of nearly equal load: items above an even share get bins of their own, the others go by best fit.

    Two packings are made, at the least capacity that the bins allow and at an even share with spilling; the
    more even one is taken.
    """
    order = sorted(range(len(sizes)), key=lambda i: (-sizes[i], i))
    out, alone, left = [0] * len(sizes), 0, sum(sizes)
    while alone < min(len(order), shards - 1) and sizes[order[alone]] * (shards - alone) > left:
        out[order[alone]] = alone
        left -= sizes[order[alone]]
        alone += 1
    rest, bins = order[alone:], shards - alone
    if not rest:
        return out
    own = [sizes[i] for i in rest]
    low = max(-(-left // bins), own[0])
    high, placed = low, best_fit(own, low, bins)
    while placed is None:
        high *= 2
        placed = best_fit(own, high, bins)
    while high - low > max(1, low // 20_000):
        middle = (low + high) // 2
        tried = best_fit(own, middle, bins)
        if tried is None:
            low = middle + 1
        else:
            high, placed = middle, tried

    def spread(packing: list[int]) -> int:
        loads = [0] * bins
        for size, b in zip(own, packing, strict=True):
            loads[b] += size
        return max(loads) - min(loads)

    placed = min(placed, spilled(own, -(-left // bins), bins), key=spread)
    for i, b in zip(rest, placed, strict=True):
        out[i] = alone + b
    return out


def shard(docs: DataFrame, shards: int | None = 24, key: str = "doc_id", text: str = "text", overhead: int = 8, finest: int = 128, capacity: int | None = None, most_items: int = 1_000_000) -> DataFrame:
    """(key, size, text_crc32, shard, slot): every document in a shard of nearly equal bytes, equal texts together.

    Size is the text's UTF-8 bytes plus ``overhead``. Null texts form one group (checksum null). Slots number a
    shard's rows from 0 without gaps, by hash bucket of the id. A group larger than an even share has a shard
    to itself, and the others share the rest evenly. With a ``capacity`` in bytes, ``shards`` is not used: as few
    shards are opened as best fit decreasing needs, none above the capacity but one of a single larger group. An
    empty table gives an empty table; repeated rows each get a slot. A capacity so small that more than ``most_items``
    items would have to be packed raises an error.
    """
    spark = docs.sparkSession
    slim = stored(
        docs.select(
            F.col(key),
            (F.coalesce(F.octet_length(text), F.lit(0)) + overhead).cast("long").alias("size"),
            F.crc32(F.col(text).cast("binary")).alias("text_crc32"),
            F.coalesce(F.md5(F.col(text).cast("binary")), F.lit("null")).alias("_group"),
        )
    )
    total = slim.agg(F.sum("size")).first()[0] or 0
    of = shards if capacity is None else max(1, -(-total // capacity))
    pools = 2 * finest * of
    if pools + of * finest > most_items:
        raise ValueError(f"{of} shards are more than one packing can fill: raise the capacity or most_items")
    slim = slim.withColumn("_pool", F.pmod(F.xxhash64("_group"), F.lit(pools)).cast("int"))
    large = slim.groupBy("_group").agg(F.sum("size").alias("_bytes")).filter(F.col("_bytes") * (of * finest) > total)
    large = stored(large)  # fewer than of * finest rows, as their bytes add up to no more than all
    pooled = slim.join(F.broadcast(large.select("_group")), "_group", "left_anti").groupBy("_pool").agg(F.sum("size").alias("_bytes"))
    items = [(g, None, b) for g, b in sorted(map(tuple, large.collect()))] + [(None, p, b) for p, b in sorted(map(tuple, pooled.collect()))]
    sizes = [b for *_, b in items]
    placed = near_equal(sizes, shards) if capacity is None else best_fit(sizes, capacity)
    of_group = spark.createDataFrame([(g, s) for (g, _, _), s in zip(items, placed, strict=True) if g is not None], "_group string, _of_group int")
    of_pool = spark.createDataFrame([(p, s) for (g, p, _), s in zip(items, placed, strict=True) if g is None], "_pool int, _of_pool int")
    rows = slim.join(F.broadcast(of_group), "_group", "left").join(F.broadcast(of_pool), "_pool", "left")
    rows = rows.select(key, "size", "text_crc32", F.coalesce("_of_group", "_of_pool").alias("shard"), F.lit(1).alias("_one"), F.pmod(F.xxhash64(key), F.lit(1024)).alias("_bucket"))
    return running_sum(rows, ["shard"], "_bucket", [F.col(key)], "_one", "slot").drop("_one", "_bucket")
