"""Connected components of an edge list by alternating star contractions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from recblock.session import cut

ONE_TASK = 1 << 20  # so many edges are a few dozen megabytes for the task that finishes them


def _large_star(edges: DataFrame) -> DataFrame:
    """Every neighbour above a node is tied to the smallest of the node's neighbourhood."""
    both = edges.select("src", "dst").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    low = both.groupBy("src").agg(F.least(F.min("dst"), F.first("src")).alias("low"))
    return both.join(low, "src").where("dst > src").select(F.col("dst").alias("src"), F.col("low").alias("dst")).where("src <> dst").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """Every neighbour not above a node, and the node, are tied to the smallest of them."""
    down = edges.select(F.greatest("src", "dst").alias("src"), F.least("src", "dst").alias("dst")).distinct()
    low = down.groupBy("src").agg(F.min("dst").alias("low"))
    tied = down.join(low, "src").select(F.col("dst").alias("src"), F.col("low").alias("dst"))
    return tied.unionByName(low.select("src", F.col("low").alias("dst"))).where("src <> dst").distinct()


def _in_one_task(edges: DataFrame) -> DataFrame:
    """(node, component_id) of all nodes with an edge, by union and find, for edge lists of checked size."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches if b.num_rows]
        if not parts:
            return
        src, dst = (np.concatenate(x) for x in zip(*parts, strict=True))
        ids, at = np.unique(np.concatenate([src, dst]), return_inverse=True)
        a, b = at[: len(src)], at[len(src) :]
        root = np.arange(len(ids))
        while True:  # hook the greater root under the smaller, then shorten all paths
            x, y = root[a], root[b]
            apart = x != y
            if not apart.any():
                break
            np.minimum.at(root, np.maximum(x, y)[apart], np.minimum(x, y)[apart])
            while not np.array_equal(short := root[root], root):
                root = short
        yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(ids[root])], ["node", "component_id"])

    return edges.select(F.col("src").cast("long"), F.col("dst").cast("long")).coalesce(1).mapInArrow(run, "node long, component_id long")


def connected_components(edges: DataFrame, nodes: DataFrame | None = None, max_rounds: int = 60, one_task: int = ONE_TASK) -> DataFrame:
    """``edges(src, dst)`` to ``(node, component_id)``, the id being the smallest node.

    Each round is a large star and a small star, cut from its lineage; only a count and a sum
    reach the driver. Once no more than ``one_task`` edges are left, one task finishes them with the
    same result. Nodes without an edge are their own component when ``nodes(node)`` is
    given; self loops and repeated edges are allowed, nulls are left out."""
    now = cut(edges.where("src is not null and dst is not null and src <> dst").select(F.greatest("src", "dst").alias("src"), F.least("src", "dst").alias("dst")).distinct())
    mark = None
    for _ in range(max_rounds):
        seen = now.agg(F.count("*"), F.sum(F.col("dst").cast("decimal(38,0)")), F.sum(F.xxhash64("src", "dst").cast("decimal(38,0)"))).first()
        if tuple(seen) == mark or seen[0] <= one_task:
            break
        mark = tuple(seen)
        now = cut(_small_star(_large_star(now)))
    else:
        raise RuntimeError("components did not settle; raise max_rounds")
    if seen[0] <= one_task:
        every = _in_one_task(now)
        if nodes is None:
            return every
        roots = every
    else:
        roots = now.select(F.col("src").alias("node"), F.col("dst").alias("component_id"))
    if nodes is None:
        return roots.unionByName(roots.select(F.col("component_id").alias("node"), "component_id").distinct())
    every = nodes.select("node").where("node is not null").distinct()
    return every.join(roots, "node", "left").select("node", F.coalesce("component_id", "node").alias("component_id"))
