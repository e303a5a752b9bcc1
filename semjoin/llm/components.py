"""Connected components of a link table by alternating star contractions.

Every round is two aggregations and two joins over the links; nothing is gathered
on the driver but three counts.  Hot nodes are pre-aggregated before the shuffle
(partial minimum) and their join is one that adaptive execution can split.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .scratch import Scratch

HELD = 1 << 20  # links that a task holds at once, 16 MB


def components(links: DataFrame, scratch: Scratch, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component) for every node of a link; component is the smallest node reachable."""
    e = links.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct()
    e = scratch.table(e, "links")
    while True:
        degree = e.groupBy("u").agg(F.count("*").alias("n"))
        roots = e.select(F.col("v").alias("u")).distinct()
        bad = degree.where("n > 1").select("u").union(degree.join(roots, "u", "left_semi").select("u")).limit(1).count()
        if not bad:
            break
        both = e.select("u", "v").union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        large = scratch.table(large, "large")
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v"))).distinct()
        old, e = e, scratch.table(small, "links")
        scratch.drop(old, large)
    return e.select(F.col("u").alias("node"), F.col("v").alias("component")).union(e.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())


def roots(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The nodes of links a-b in order, and the smallest node reachable from each."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    parent = np.arange(len(nodes))
    x, y = at[: len(a)], at[len(a) :]
    while True:
        px, py = parent[x], parent[y]
        apart = px != py
        if not apart.any():
            return nodes, nodes[parent]
        x, y, px, py = x[apart], y[apart], px[apart], py[apart]
        np.minimum.at(parent, np.maximum(px, py), np.minimum(px, py))
        while (up := parent[parent]).tobytes() != parent.tobytes():
            parent = up


def _forest(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Links (a, b) with the same components, fewer of them: per ``HELD`` of the task's links a star for each component."""
    held, n = [], 0

    def stars() -> tuple[np.ndarray, np.ndarray]:
        node, root = roots(*(np.concatenate([x[i] for x in held]) for i in (0, 1)))
        leaf = node != root
        return node[leaf], root[leaf]

    made = lambda x: pa.RecordBatch.from_arrays([pa.array(x[0]), pa.array(x[1])], ["a", "b"])
    for batch in batches:
        held.append((np.asarray(batch.column(0)), np.asarray(batch.column(1))))
        n += batch.num_rows
        if n >= HELD:
            held = [stars()]
            n = len(held[0][0])
            if n >= HELD // 2:
                yield made(held[0])
                held, n = [], 0
    if n:
        yield made(stars())


def _named(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    links = [(np.asarray(x.column(0)), np.asarray(x.column(1))) for x in batches if x.num_rows]
    if links:
        node, root = roots(*(np.concatenate([x[i] for x in links]) for i in (0, 1)))
        yield pa.RecordBatch.from_arrays([pa.array(node), pa.array(root)], ["node", "component"])


def components_of_few(links: DataFrame, scratch: Scratch) -> DataFrame:
    """``components`` of links (a, b) of longs without nulls, for links that are often few.

    Each task first contracts its own links, which needs no shuffle.  What is left is solved by one task if it is
    ``HELD`` links at most, whatever the size of the input, and by ``components`` if it is more.
    """
    few = scratch.table(links.select("a", "b").mapInArrow(_forest, "a bigint, b bigint"), "forest")
    if few.count() > HELD:
        return components(few, scratch)
    return few.coalesce(1).mapInArrow(_named, "node bigint, component bigint")
