"""Connected components of a link table, in Spark: neither links nor labels reach the driver."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from factbench.llm.common import settles, stored


def spanning(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For links a-b of one block: each node with the least node it reaches through them. As many rows as nodes, not links."""
    nodes, flat = np.unique(np.r_[a, b], return_inverse=True)
    i, j = flat[: len(a)], flat[len(a) :]
    label = np.arange(len(nodes))
    while True:
        new = label.copy()
        np.minimum.at(new, i, label[j])
        np.minimum.at(new, j, label[i])
        new = new[new]
        if (new == label).all():
            return nodes, nodes[label]
        label = new


@settles
def connected(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component): the smallest node that links reach, for every node of ``edges``.

    Rounds of minimum labels over links, each followed by a jump to the label's own label, until no label
    changes; the driver sees one count a round. Loops and repeated links are harmless; null ends are ignored.
    An empty table gives an empty table.
    """
    links = edges.select(F.col(a).alias("a"), F.col(b).alias("b")).filter("a != b")
    links = stored(links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    labels = stored(links.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("label")).select(F.col("a").alias("node"), "label"))
    while True:
        near = (
            links.join(labels, links["b"] == labels["node"])
            .groupBy("a")
            .agg(F.min("label").alias("least"))
        )
        lower = labels.join(near, labels["node"] == near["a"], "left").select(
            "node", F.col("label").alias("was"), F.least("label", "least").alias("label")
        )
        up = labels.select(F.col("node").alias("label"), F.col("label").alias("jump"))
        nxt = stored(lower.join(up, "label", "left").select("node", "was", F.least("label", "jump").alias("label")))
        changed = nxt.filter("label < was").count()
        labels = nxt.select("node", "label")
        if not changed:
            return labels.select("node", F.col("label").alias("component"))
