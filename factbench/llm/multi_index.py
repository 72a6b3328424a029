"""Embedding near-dedup by an inverted multi-index.

Independent codebooks on the two halves of unit vectors form a product grid. Every vector lives in one cell and
visits the nearest cells of the grid in the order of a multi-sequence traversal; how many is calibrated, so that
a vector at exactly the threshold's distance is met with the target recall. Meetings are verified exactly.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from factbench.llm.common import matrix, settles, stored, valid_vector
from factbench.llm.components import connected, spanning


def unit(vectors: np.ndarray) -> np.ndarray:
    scale = np.abs(vectors).max(axis=1, keepdims=True)
    scaled = vectors / scale
    return scaled / np.linalg.norm(scaled, axis=1, keepdims=True)


def _distances(rows: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return (rows**2).sum(1)[:, None] - 2 * rows @ centres.T + (centres**2).sum(1)


def codebook(rows: np.ndarray, size: int, rounds: int = 12) -> np.ndarray:
    """k-means centres, from evenly spaced rows."""
    centres = rows[np.linspace(0, len(rows) - 1, min(size, len(rows))).astype(int)].copy()
    for _ in range(rounds):
        home = _distances(rows, centres).argmin(1)
        for c in range(len(centres)):
            own = rows[home == c]
            if len(own):
                centres[c] = own.mean(0)
    return centres


class Grid:
    """Two codebooks and the number of cells to visit."""

    def __init__(self, first: np.ndarray, second: np.ndarray, visits: int = 1):
        self.first, self.second, self.visits = first, second, visits

    def _halves(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        cut = rows.shape[1] // 2
        return _distances(rows[:, :cut], self.first), _distances(rows[:, cut:], self.second)

    def cells(self, rows: np.ndarray, visits: int | None = None) -> np.ndarray:
        """The ``visits`` nearest cells of each row, nearest first; the first is its home.

        The n-th best pair of two sorted lists has places a, b with a * b <= n (from 1): only those are summed.
        """
        a, b = self._halves(rows)
        visits = min(visits or self.visits, a.shape[1] * b.shape[1])
        order_a, order_b = np.argsort(a, axis=1, kind="stable"), np.argsort(b, axis=1, kind="stable")
        sorted_a, sorted_b = np.take_along_axis(a, order_a, 1), np.take_along_axis(b, order_b, 1)
        grid = np.arange(1, a.shape[1] + 1)[:, None] * np.arange(1, b.shape[1] + 1)[None, :]
        at_a, at_b = np.nonzero(grid <= visits)
        sums = sorted_a[:, at_a] + sorted_b[:, at_b]
        best = np.argsort(sums, axis=1, kind="stable")[:, :visits]
        return (np.take_along_axis(order_a, at_a[best], 1) * b.shape[1] + np.take_along_axis(order_b, at_b[best], 1)).astype(np.int32)


def fit(sample: np.ndarray, size: int, threshold: float, target: float) -> Grid:
    """Codebooks from a sample, and visits enough to meet the target for neighbours at exactly the threshold."""
    rows = unit(sample)
    cut = rows.shape[1] // 2
    grid = Grid(codebook(rows[:, :cut], size), codebook(rows[:, cut:], size))
    draw = np.random.default_rng(41)
    probe = rows[:: max(1, len(rows) // 2000)]
    noise = draw.standard_normal(probe.shape)
    noise -= (noise * probe).sum(1, keepdims=True) * probe
    length = np.linalg.norm(noise, axis=1, keepdims=True)
    near = threshold * probe + np.sqrt(1 - threshold**2) * np.divide(noise, length, out=np.zeros_like(noise), where=length > 0)
    every = len(grid.first) * len(grid.second)
    a, b = grid._halves(probe)
    home = grid.cells(near, 1)[:, 0]
    cost = a[np.arange(len(probe)), home // b.shape[1]] + b[np.arange(len(probe)), home % b.shape[1]]
    rank = np.array([(x[:, None] + y[None, :] < c).sum() + 1 for x, y, c in zip(a, b, cost, strict=True)])
    grid.visits = int(min(every, np.quantile(rank, target) + 1))
    return grid


def _visit_rows(grid):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 2048):
                part = batch.slice(at, 2048)
                cells = grid.value.cells(unit(matrix(part.column(1))))
                offsets = np.arange(0, cells.size + 1, cells.shape[1]).astype(np.int32)
                visits = pa.ListArray.from_arrays(pa.array(offsets), pa.array(cells.ravel()))
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), part.column(2), pa.array(cells[:, 0].copy()), visits], names=["rep", "vec", "copies", "home", "visits"])

    return run


MET = "rep long, links long, other long"


def _near(a: np.ndarray, b: np.ndarray, threshold: float) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of unit rows with cosine >= threshold; close calls are summed again in the order of components."""
    product = a @ b.T
    i, j = np.nonzero(product >= threshold - 1e-9)
    close = np.flatnonzero(product[i, j] < threshold + 1e-9)
    if len(close):
        x, y = a[i[close]], b[j[close]]
        dot, norms = np.cumsum(x * y, axis=1)[:, -1], np.cumsum(x * x, axis=1)[:, -1] * np.cumsum(y * y, axis=1)[:, -1]
        kept = np.ones(len(i), bool)
        kept[close] = dot / np.sqrt(norms) >= threshold
        i, j = i[kept], j[kept]
    return i, j


def _verified(threshold: float):
    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        reps, links, others = [np.empty(0, np.int64)], [np.empty(0, np.int64)], [np.empty(0, np.int64)]
        if left.num_rows and right.num_rows:
            ids, copies, rows, visits = left["rep"].to_numpy(), left["copies"].to_numpy(), unit(matrix(left["vec"])), matrix(left["visits"]).astype(np.int32)
            p_ids, p_copies, p_rows, p_home = right["p_rep"].to_numpy(), right["p_copies"].to_numpy(), unit(matrix(right["p_vec"])), right["p_home"].to_numpy()
            total = np.zeros(len(ids), np.int64)
            for at in range(0, len(p_ids), 512):
                i, j = _near(p_rows[at : at + 512], rows, threshold)
                i += at
                once = p_ids[i] < ids[j]
                back = np.flatnonzero(p_ids[i] > ids[j])  # the other way round it is found too, if the member visits the visitor's home
                for cut in range(0, len(back), 100_000):
                    some = back[cut : cut + 100_000]
                    once[some] = ~(visits[j[some]] == p_home[i[some]][:, None]).any(axis=1)
                i, j = i[once], j[once]
                if not len(i):
                    continue
                total += np.bincount(j, p_copies[i], len(ids)).astype(np.int64)
                mine = np.bincount(i - at, copies[j], 512).astype(np.int64)
                some = np.flatnonzero(mine)
                reps.append(p_ids[at + some])
                links.append(mine[some])
                others.append(p_ids[at + some])
                nodes, least = spanning(p_ids[i], ids[j])
                reps.append(nodes)
                links.append(np.zeros(len(nodes), np.int64))
                others.append(least)
            some = np.flatnonzero(total)
            reps.append(ids[some])
            links.append(total[some])
            others.append(ids[some])
        return pa.table({"rep": np.concatenate(reps), "links": np.concatenate(links), "other": np.concatenate(others)})

    return run


@settles
def near_groups(vectors: DataFrame, threshold: float = 0.9, key: str = "vec_id", column: str = "embedding", target: float = 0.97, cell_rows: int = 256, sample: int = 16384, block: int = 4096) -> DataFrame:
    """(vec_id, n_links, component_id, kept): links of cosine >= ``threshold`` found, and the smallest id they reach.

    Codebooks are fitted on the ``sample`` rows of least hash; every row is indexed. Equal vectors count once and
    link with all their copies. Vectors that are null, zero or hold null or non-finite components link with
    nothing: n_links 0, their own component, kept. Rows with a null id keep it, link with nothing and are kept.
    Repeated rows (same id) count once as a partner and each give a row. Vectors of different lengths don't link.
    An empty table gives an empty table; further columns are left out.
    """
    every = vectors.select(F.col(key).cast("long").alias("vec_id"), F.when(valid_vector(column), F.col(column)).alias("vec"))
    valid = every.filter("vec is not null and vec_id is not null")
    alike = stored(valid.groupBy("vec").agg(F.min("vec_id").alias("rep"), F.count_distinct("vec_id").alias("copies")).select("rep", "vec", "copies"))
    lengths = sorted(r[0] for r in alike.select(F.size("vec")).distinct().collect())  # one in all but broken tables
    parts = [_linked(alike.filter(F.size("vec") == n), threshold, target, cell_rows, sample, block) for n in lengths]
    if not parts:
        return every.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    links, groups = parts[0]
    for more_links, more_groups in parts[1:]:
        links, groups = links.unionByName(more_links), groups.unionByName(more_groups)
    told = alike.join(links, "rep", "left").join(groups, F.col("rep") == F.col("node"), "left").select("vec", F.coalesce("links", F.lit(0)).alias("_links"), "copies", F.coalesce("component", "rep").alias("_component"))
    out = every.join(told, (every["vec"] == told["vec"]) & every["vec_id"].isNotNull(), "left")
    component = F.coalesce("_component", "vec_id")
    return out.select("vec_id", F.coalesce(F.col("_links") + F.col("copies") - 1, F.lit(0)).alias("n_links"), component.alias("component_id"), F.coalesce(component == F.col("vec_id"), F.lit(True)).alias("kept"))


def _linked(alike: DataFrame, threshold: float, target: float, cell_rows: int, sample: int, block: int) -> tuple[DataFrame, DataFrame]:
    """(rep, links) and (node, component) of distinct vectors of one length."""
    spark = alike.sparkSession
    n = alike.count()
    taken = alike.orderBy(F.xxhash64("rep"), "rep").limit(sample).select("vec").toArrow()
    size = int(np.clip(round((n / cell_rows) ** 0.5), 2, 1024))
    grid = spark.sparkContext.broadcast(fit(matrix(taken["vec"]), size, threshold, target))
    kind = alike.schema["vec"].dataType.simpleString()
    placed = stored(alike.mapInArrow(_visit_rows(grid), f"rep long, vec {kind}, copies long, home int, visits array<int>"))
    chunks = placed.groupBy(F.col("home").alias("cell")).agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("chunks"))
    members = placed.join(chunks, F.col("home") == F.col("cell")).select("cell", F.pmod(F.xxhash64("rep"), F.col("chunks")).cast("int").alias("chunk"), "rep", "copies", "visits", "vec")
    again = placed.select(*[F.col(c).alias(f"p_{c}") for c in ("rep", "copies", "home", "vec")], F.explode("visits").alias("cell"))
    visitors = again.join(chunks.select(F.col("cell").alias("_cell"), F.col("chunks").alias("_chunks")), F.col("cell") == F.col("_cell"))
    visitors = visitors.select("cell", F.explode(F.sequence(F.lit(0), F.col("_chunks") - 1)).alias("chunk"), "p_rep", "p_copies", "p_home", "p_vec")
    met = stored(members.groupBy("cell", "chunk").cogroup(visitors.groupBy("cell", "chunk")).applyInArrow(_verified(threshold), MET))
    links = met.groupBy("rep").agg(F.sum("links").alias("links"))
    groups = connected(met.filter("rep != other").select("rep", "other"), "rep", "other")
    return links, groups
