"""Nearest neighbours by collision counting on query-centred windows.

Each of ``lines`` random projections keeps the vectors of a block in a sorted array. A query
opens a window around its own projection on every line and widens all windows together
(virtual rehashing: the radius grows by a factor, nothing is hashed anew). A vector collides
once per line whose window holds it; vectors with enough collisions are verified by their
exact cosine. Windows widen until a share of the block, and FEW vectors at least, was verified:
the share is what buys recall, which is measured against brute force.

The vectors lie in blocks, each of them once; the queries go to every block and stream past its
index, and the best of all blocks are merged. So every row is indexed and a task holds one block.

Vectors that are null, zero, or hold a null or a non-finite component take no part; vectors
of different lengths never meet. Repeated rows are one; if an id has several vectors, its best
counts. Ties go to the smaller id; a query's own id is no candidate. An empty table gives no rows."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

LINES, NEED, SHARE, GROWTH, FIRST = 40, 0.55, 0.4, 1.12, 0.3
BLOCK, LEAST_BLOCK, NEAREST, EVERY = 4 << 20, 4_096, 5, 50  # numbers of a block, vectors of a small one
FEW = 256


def usable(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    v = F.col(vector_col)
    good = v.isNotNull() & ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists(v, lambda x: x != 0) & F.col(id_col).isNotNull()
    return vectors.select(F.col(id_col).cast("long").alias("vec_id"), v.cast("array<double>").alias("v")).where(F.coalesce(good, F.lit(False)))


def cosines(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Cosine of one vector with the rows of x, the same for equal rows."""
    return np.clip((x * q).sum(1) / (np.sqrt((x * x).sum(1)) * np.sqrt((q * q).sum())), -1.0, 1.0)


class CollisionIndex:
    def __init__(self, x: np.ndarray, lines: int = LINES, seed: int = 11):
        self.x, self.lines = x, lines
        self.unit = x / np.sqrt((x * x).sum(1))[:, None]
        self.axes = np.random.default_rng(seed).standard_normal((x.shape[1], lines))
        places = self.unit @ self.axes
        self.far = float(np.sqrt((self.axes**2).sum(0)).max()) + 1  # no projection of a unit vector is beyond
        self.shift = np.arange(lines) * 4 * self.far
        self.order = np.argsort(places, axis=0, kind="stable").T.ravel().astype(np.int32)  # line after line
        self.sorted = (np.sort(places, axis=0).T + self.shift[:, None]).ravel()

    def candidates(self, unit_query: np.ndarray, need: float = NEED, share: float = SHARE) -> np.ndarray:
        n = len(self.x)
        at = unit_query @ self.axes
        count = np.zeros(n, np.int32)
        left = np.searchsorted(self.sorted, at + self.shift)
        right, radius = left.copy(), FIRST
        least, enough = int(np.ceil(need * self.lines)), min(n, max(FEW, share * n))
        while True:
            lo = np.searchsorted(self.sorted, np.maximum(at - radius, -self.far) + self.shift)
            hi = np.searchsorted(self.sorted, np.minimum(at + radius, self.far) + self.shift)
            start, length = np.concatenate([lo, right]), np.concatenate([left - lo, hi - right])
            to = np.cumsum(length)
            fresh = self.order[np.arange(to[-1]) + np.repeat(start - (to - length), length)]
            count += np.bincount(fresh, minlength=n).astype(np.int32)
            left, right = lo, hi
            chosen = np.flatnonzero(count >= least)
            if len(chosen) >= enough or radius > 2 * self.far:
                return chosen
            radius *= GROWTH


def nearest(vectors: DataFrame, queries: DataFrame, k: int = NEAREST, block: int = BLOCK, least_block: int = LEAST_BLOCK) -> DataFrame:
    """``vectors`` and ``queries`` (vec_id, v) to query_id, rank, vec_id and score. A block holds
    ``block`` numbers; a small table is spread over the tasks there are, in blocks of ``least_block``."""
    tasks = int(vectors.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    once = lambda df: df.select("vec_id", "v", F.size("v").alias("dim")).distinct()
    own = once(vectors)
    whole = F.ceil(F.col("n") * F.col("dim") / block)
    parts = own.groupBy("dim").agg(F.count("*").alias("n")).select("dim", F.greatest(whole, F.least(F.ceil(F.col("n") / least_block), F.lit(tasks))).cast("int").alias("parts"))
    indexed = own.join(parts, "dim").select("dim", F.pmod(F.xxhash64("vec_id"), "parts").cast("int").alias("b"), F.lit(False).alias("asks"), "vec_id", "v")
    asking = once(queries).join(parts, "dim").select("dim", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("b"), F.lit(True).alias("asks"), "vec_id", "v")
    rows = indexed.unionByName(asking).repartition(tasks, "dim", "b").sortWithinPartitions("dim", "b", "asks", "vec_id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: tuple | None = None  # of the block: its key, ids and vectors
        index: CollisionIndex | None = None
        for batch in batches:
            ids, asks = batch.column("vec_id").to_numpy(), batch.column("asks").to_numpy(zero_copy_only=False)
            dims, blocks = batch.column("dim").to_numpy(), batch.column("b").to_numpy()
            edges = np.flatnonzero(np.append(True, (dims[1:] != dims[:-1]) | (blocks[1:] != blocks[:-1]) | (asks[1:] != asks[:-1]))) if len(ids) else []
            out: list[list] = [[], [], []]
            for s, e in zip(edges, [*edges[1:], len(ids)], strict=True):
                key = (int(dims[s]), int(blocks[s]))
                x = batch.column("v").slice(s, e - s).flatten().to_numpy().reshape(e - s, -1)
                if not asks[s]:
                    if held is None or held[0] != key:
                        held = (key, [], [])
                    held[1].append(ids[s:e])
                    held[2].append(x)
                    index = None
                elif held is not None and held[0] == key:
                    if index is None:
                        index, names = CollisionIndex(np.concatenate(held[2])), np.concatenate(held[1])
                    for query, v in zip(ids[s:e].tolist(), x, strict=True):
                        found = index.candidates(v / np.sqrt((v * v).sum()))
                        found = found[names[found] != query]
                        score = cosines(v, index.x[found])
                        best = np.lexsort((names[found], -score))
                        _, firsts = np.unique(names[found][best[: k * 64]], return_index=True)
                        if len(firsts) < k:  # an id may have several vectors
                            _, firsts = np.unique(names[found][best], return_index=True)
                        best = best[np.sort(firsts)[:k]]
                        out[0] += [query] * len(best)
                        out[1] += names[found][best].tolist()
                        out[2] += score[best].tolist()
            yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.float64())], ["query_id", "vec_id", "score"])

    found = rows.mapInArrow(run, "query_id long, vec_id long, score double").groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    by_query = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(by_query)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op6_collision_ann(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = usable(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))
    return nearest(rows, rows.where(F.col("vec_id") % EVERY == 0))
