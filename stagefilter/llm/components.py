"""Connected components of a link table: in one go where the links are few, by alternating star operations beyond.

Up to `few` links are brought to the driver, where trees of nodes are hooked onto smaller
roots until both ends of every link have one root; that takes one small job where each
round of stars takes eight shuffles, whatever the size.

In a large star every node hands its larger neighbours to the least node it knows; in a
small star it hands its smaller ones. Both keep components and pull links towards the
least node; when nothing moves every node is linked to its component's least node. Only
minima are gathered per node (partial aggregation first), never neighbour lists, and each
round's links go through the shared checkpoint folder.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stagefilter.llm.common import cut

#: Most links that come to the driver at once: 8 MB.
FEW_LINKS = 500_000


def _large(links: DataFrame) -> DataFrame:
    both = links.union(links.select("b", "a")).toDF("u", "v")
    least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
    return both.filter("v > u").join(least, "u").select(F.col("v").alias("a"), F.col("m").alias("b"))


def _small(links: DataFrame) -> DataFrame:
    """links have a > b here."""
    least = links.groupBy("a").agg(F.min("b").alias("m"))
    down = links.join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return down.union(least.select("a", F.col("m").alias("b")))


def least_reachable(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The nodes of the links (a, b) and the least node that each can reach."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    root = np.arange(len(nodes))
    while len(x):
        x, y = root[x], root[y]
        open_ = x != y
        x, y = x[open_], y[open_]
        # every root is hooked onto the least one that it is linked to; roots only get smaller, so there are no rings
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while (root[root] != root).any():
            root = root[root]
    return nodes, nodes[root]


def components(links: DataFrame, most_rounds: int = 60, few: int = FEW_LINKS) -> DataFrame:
    """(node, component) of every node in links (a, b: long, any order) but those that are the least of theirs; component is the least node reachable."""
    now = cut(links.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    if now.count() <= few:
        held = now.toArrow()
        nodes, least = least_reachable(held["a"].to_numpy(), held["b"].to_numpy())
        moved = nodes != least
        return cut(now.sparkSession.createDataFrame(pa.table({"node": nodes[moved], "component": least[moved]}), "node long, component long"))
    state = None
    for _ in range(most_rounds):
        now = cut(_small(_large(now).filter("a > b").distinct()).filter("a > b").distinct())
        # a fixed point leaves count and sum of the links as they are; the sums wrap, equal states have equal sums
        fresh = now.agg(F.count("*"), F.bit_xor(F.xxhash64("a", "b"))).first()
        if fresh == state:
            break
        state = fresh
    else:
        raise RuntimeError("components did not settle")
    return now.select(F.col("a").alias("node"), F.col("b").alias("component"))
