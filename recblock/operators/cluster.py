"""Cluster-based blocking: nearest-neighbour clusters, canopies, reference values."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from recblock.operators.graph import connected_components
from recblock.operators.klsh import rank_by_digest
from recblock.operators.minhash import similar_pairs
from recblock.operators.scan import running_sums
from recblock.operators.shingle import shingle_counts
from recblock.session import cut, stored

FEW = 10_000  # vectors that are sent to every worker at once


def unit_bags(texts: DataFrame, k: int = 2) -> DataFrame:
    """(rec_id, terms, ws): unit TF-IDF vectors, the rarest terms first (by frequency, then digest).
    Records without text, or whose terms stand in every record, have none."""
    counts = stored(shingle_counts(texts, k))
    df = counts.groupBy("term").agg(F.count("*").alias("df"))
    weight = F.ln(F.lit(texts.count()) / F.col("df"))
    terms = counts.join(df, "term").select("rec_id", "df", F.xxhash64("term").alias("h"), (F.col("tf") * weight).alias("w")).where("w > 0")
    bags = terms.groupBy("rec_id").agg(F.array_sort(F.collect_list(F.struct("df", "h", "w"))).alias("b"), F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    return bags.select("rec_id", F.col("b.h").alias("terms"), F.transform("b.w", lambda w: w / F.col("norm")).alias("ws"))


def epsilon_pairs(texts: DataFrame, t: float, k: int = 2, metric: str = "tfidf", block: int = 1024, way: str = "auto") -> DataFrame:
    """(id_a, id_b, distance) of all pairs within t. ``tfidf``: Euclidean distance of unit vectors;
    ``cosine``: one less their cosine; ``jaccard``: one less the share of common shingles.

    Prefix filter: a vector's rarest terms, as many as leave a rest shorter than the least
    similarity, are its prefix; two near vectors share a term of both prefixes. Each prefix term's
    records are compared in cells of at most two blocks, whatever their number, and a pair is told
    by its first common prefix term only.

    ``way``: ``prefix``, or ``blocks``, which compares all blocks with each other once, as is
    cheaper where prefixes are so long and frequent (a wide t, small alphabets) that their records
    make more comparisons than there are pairs; ``auto`` counts both. The rows are the same."""
    if metric == "jaccard":
        percent = math.ceil(round((1 - t) * 100, 6))
        return similar_pairs(texts, percent, k).select("id_a", "id_b", (1 - F.col("jaccard")).alias("distance")).where(F.col("distance") <= t)
    limit, far = (1.0, t) if metric == "cosine" else (2**0.5, t * t / 2)
    if t >= limit:
        raise ValueError("beyond orthogonal vectors every pair is near")
    least = 1 - far
    bags = stored(unit_bags(texts, k))

    @F.arrow_udf("int")
    def prefix_length(ws: pa.Array) -> pa.Array:
        length = pc.list_value_length(ws).to_numpy()
        total = np.append(0.0, np.cumsum(ws.flatten().to_numpy() ** 2))
        end = np.cumsum(length)
        after = np.repeat(total[end], length) - total[1:]  # squares of what follows each term
        long = np.append(0, np.cumsum(np.sqrt(np.maximum(after, 0.0)) >= least - 1e-9))
        return pa.array(np.minimum(1 + long[end] - long[end - length], length), pa.int32())

    placed = bags.select("rec_id", "terms", "ws", F.posexplode(F.slice("terms", F.lit(1), prefix_length("ws"))).alias("at", "term"))
    held = stored(placed.groupBy("term").agg(F.count("*").alias("n")))  # vectors are not written for each of their prefix terms
    if way == "auto":
        one = held.agg(F.sum(F.col("n").cast("double") * F.col("n"))).first()[0]
        way = "blocks" if one and one > float(bags.count()) ** 2 else "prefix"
    if way == "blocks":
        placed = bags.select("rec_id", "terms", "ws", F.lit(0).alias("at"), F.lit(0).cast("long").alias("term"))
        held = placed.groupBy("term").agg(F.count("*").alias("n"))
    many = held.where("n > 1").select("term", F.ceil(F.col("n") / block).cast("int").alias("g"), "n")
    cells = placed.join(many, "term").withColumn("own", F.pmod(F.xxhash64("rec_id", "term"), "g").cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("g") - 1)))
    cells = cells.select("term", "at", "rec_id", "terms", "ws", "own", F.least("own", "other").alias("ci"), F.greatest("own", "other").alias("cj"))

    def compare(table: pa.Table) -> pa.Table:
        ids, own, at = (table.column(c).to_numpy() for c in ("rec_id", "own", "at"))
        first, second = int(table.column("ci")[0].as_py()), int(table.column("cj")[0].as_py())
        lists = table.column("terms").combine_chunks()
        length = pc.list_value_length(lists).to_numpy()
        row = np.repeat(np.arange(len(ids)), length)
        words, column = np.unique(lists.flatten().to_numpy(), return_inverse=True)
        weight = table.column("ws").combine_chunks().flatten().to_numpy()
        place = np.arange(len(row)) - np.repeat(np.cumsum(length) - length, length)
        x, y = (np.arange(len(ids)),) * 2 if first == second else (np.flatnonzero(own == first), np.flatnonzero(own == second))
        sims, seen = np.zeros((len(x), len(y))), np.zeros((len(x), len(y)), bool)
        for c in range(0, len(words), 4096):
            part = (column >= c) & (column < c + 4096)
            dense = np.zeros((len(ids), min(4096, len(words) - c)))
            dense[row[part], column[part] - c] = weight[part]
            sims += dense[x] @ dense[y].T
            part &= place < at[row]  # prefix terms before this one
            if part.any():
                before = np.zeros(dense.shape, np.float32)
                before[row[part], column[part] - c] = 1
                seen |= before[x] @ before[y].T > 0
        apart = 1 - sims if metric == "cosine" else np.sqrt(np.maximum(0.0, (2 - 2 * sims).round(9)))
        a, b = np.nonzero((apart <= t) & ~seen)
        one, two, d = ids[x[a]], ids[y[b]], apart[a, b]
        keep = one < two if first == second else one != two
        return pa.table({"id_a": np.minimum(one, two)[keep], "id_b": np.maximum(one, two)[keep], "distance": d[keep]})

    return cells.groupBy("term", "ci", "cj").applyInArrow(compare, "id_a long, id_b long, distance double")


def cell_pairs(points: DataFrame, t: float) -> DataFrame:
    """(id_a, id_b) of ``points(rec_id, x)`` within t on a line: cells of width t, a cell and the next."""
    cells = points.withColumn("cell", F.floor(F.col("x") / t))
    near = points.select(F.col("rec_id").alias("id_b"), F.col("x").alias("xb"), F.explode(F.sequence(F.floor(F.col("x") / t) - 1, F.floor(F.col("x") / t) + 1)).alias("cell"))
    return cells.select(F.col("rec_id").alias("id_a"), F.col("x").alias("xa"), "cell").join(near, "cell").where((F.col("id_a") < F.col("id_b")) & (F.abs(F.col("xa") - F.col("xb")) <= t)).select("id_a", "id_b")


def vector_pairs(vectors: DataFrame, t: float) -> DataFrame:
    """(id_a, id_b, distance) of ``vectors(rec_id, vec)`` within t: near vectors are near on the first
    axis, whose cells give the candidates."""
    side = lambda s: vectors.select(F.col("rec_id").alias(f"id_{s}"), F.col("vec").alias(f"v_{s}"))
    candidates = cell_pairs(vectors.select("rec_id", F.col("vec")[0].alias("x")), t)
    far = F.sqrt(F.aggregate(F.zip_with("v_a", "v_b", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))
    return candidates.join(side("a"), "id_a").join(side("b"), "id_b").select("id_a", "id_b", far.alias("distance")).where(F.col("distance") <= t)


def near_forest(vectors: DataFrame, t: float, block: int = 4096) -> DataFrame:
    """(id_a, id_b) that join the same records as all pairs of ``vectors(rec_id, vec)`` within t, linear in
    number for a cell. Blocks of vectors are compared with each other once, by matrix products; distances
    that rounding could decide are summed again, component by component. Of the near pairs of a cell,
    those that tie together what no pair before them did are given, so their components are those of
    all pairs. Components that either vector lacks (a null, or a shorter vector) count nothing, a pair without
    a common one is not near, nor is one with a NaN in a common one. Quadratic in comparisons, as any exact way."""
    kind = vectors.schema["rec_id"].dataType.simpleString()
    held = stored(vectors.where("rec_id is not null and size(vec) > 0").select("rec_id", F.col("vec").cast("array<double>").alias("vec")))
    g = max(1, math.ceil(held.count() / block))
    own = held.withColumn("own", F.pmod(F.xxhash64("rec_id"), F.lit(g)).cast("int"))
    cells = own.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(g - 1)))).select("rec_id", "vec", "own", F.least("own", "other").alias("ci"), F.greatest("own", "other").alias("cj"))

    def dense(lists: pa.ListArray) -> tuple[np.ndarray, np.ndarray]:
        """Components, 0 where there is none, and where there is one."""
        length = pc.list_value_length(lists).to_numpy()
        row = np.repeat(np.arange(len(lists)), length)
        at = np.arange(len(row)) - np.repeat(np.cumsum(length) - length, length)
        flat = lists.flatten()
        x, has = np.zeros((len(lists), int(length.max(initial=0)))), np.zeros((len(lists), int(length.max(initial=0))), bool)
        has[row, at] = flat.is_valid().to_numpy(zero_copy_only=False)
        x[row, at] = pc.fill_null(flat, 0.0).to_numpy()
        return x, has

    def near(x: np.ndarray, y: np.ndarray, hx: np.ndarray, hy: np.ndarray) -> np.ndarray:
        bound = t * t
        if hx.all() and hy.all():
            far = (x * x).sum(1)[:, None] + (y * y).sum(1)[None, :] - 2 * (x @ y.T)
            common = np.True_
        else:
            far = (x * x) @ hy.T.astype(float) + hx.astype(float) @ (y * y).T - 2 * (x @ y.T)
            common = hx.astype(np.float32) @ hy.T.astype(np.float32) > 0
        # products of n components err by less than n + 3 roundings of the squares that stand in them
        err = (x.shape[1] + 3) * 4.5e-16 * ((x * x).sum(1)[:, None] + (y * y).sum(1)[None, :] + bound)
        sure = far <= bound
        a, b = np.nonzero(~(np.abs(far - bound) > err))  # NaN and infinite ones too
        for k in range(0, len(a), 4096):
            p, q = a[k : k + 4096], b[k : k + 4096]
            with np.errstate(invalid="ignore"):
                steps = np.where(hx[p] & hy[q], (x[p] - y[q]) ** 2, 0.0)
            sure[p, q] = np.sqrt(np.cumsum(steps, axis=1)[:, -1]) <= t
        return sure & common

    def run(table: pa.Table) -> pa.Table:
        ids, side = table.column("rec_id").to_numpy(), table.column("own").to_numpy()
        first, second = int(table.column("ci")[0].as_py()), int(table.column("cj")[0].as_py())
        x, has = dense(table.column("vec").combine_chunks())
        a, b = (np.arange(len(ids)),) * 2 if first == second else (np.flatnonzero(side == first), np.flatnonzero(side == second))
        root, out = np.arange(len(ids)), []
        for k in range(0, len(a), 256):
            with np.errstate(invalid="ignore", over="ignore"):
                i, j = np.nonzero(near(x[a[k : k + 256]], x[b], has[a[k : k + 256]], has[b]))
            i, j = a[k + i], b[j]
            while len(i):
                apart = root[i] != root[j]
                i, j = i[apart], j[apart]
                high, low = np.maximum(root[i], root[j]), np.minimum(root[i], root[j])
                roots, pick = np.unique(high, return_index=True)  # one pair for each root that is hooked
                out.append(np.stack([i[pick], j[pick]], 1))
                root[roots] = low[pick]
                while not np.array_equal(short := root[root], root):
                    root = short
        pairs = ids[np.concatenate(out)] if out else np.zeros((0, 2), ids.dtype)
        pairs = pairs[pairs[:, 0] != pairs[:, 1]]
        return pa.table({"id_a": pairs.min(1), "id_b": pairs.max(1)})

    return cells.groupBy("ci", "cj").applyInArrow(run, f"id_a {kind}, id_b {kind}")


def tnn_blocks(ids: DataFrame, pairs: DataFrame, growth: str = "chain", seed: int = 42) -> DataFrame:
    """Threshold nearest neighbours over ``pairs`` of near records. ``chain``: growing a cluster until
    its nearest outsider is too far ends at a component of the graph of near pairs, from whatever base
    it began. ``base``: only what is near to the base itself joins, bases in a random order."""
    if growth == "base":
        near = pairs.select("id_a", "id_b", F.lit(0.0).alias("distance"))
        return canopy_blocks(canopies(ids, near, 0.0, 0.0, seed), "equal", seed)
    edges = pairs.select(F.col("id_a").alias("src"), F.col("id_b").alias("dst"))
    return connected_components(edges, ids.select(F.col("rec_id").alias("node"))).select(F.col("node").alias("rec_id"), F.col("component_id").alias("block_id"))


def sorted_tnn_blocks(texts: DataFrame, t: int) -> DataFrame:
    """Records in the order of their text; a new block where the edit distance to the one before
    exceeds t. The order is cut into ranges once; each range looks back to the last text of the
    ranges before it, and the blocks are numbered by two-phase sums. Null texts count as empty."""
    spark = texts.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    ranged = texts.select("rec_id", F.coalesce("rec_text", F.lit("")).alias("rec_text")).repartitionByRange(parts, "rec_text", "rec_id")
    placed = stored(ranged.withColumn("__pid", F.spark_partition_id()))
    ends = placed.groupBy("__pid").agg(F.max(F.struct("rec_text", "rec_id")).alias("m"))
    carried = ends.select((F.lead("__pid").over(Window.orderBy("__pid"))).alias("__pid"), F.col("m.rec_text").alias("__carried"))  # one row for each range
    inside = Window.partitionBy("__pid").orderBy("rec_text", "rec_id")
    before = F.coalesce(F.lag("rec_text").over(inside), F.col("__carried"))
    new = placed.join(F.broadcast(carried.where("__pid is not null")), "__pid", "left").withColumn("__before", before)
    flagged = stored(new.select("rec_id", "rec_text", "__pid", F.when(F.col("__before").isNull() | (F.levenshtein("rec_text", "__before") > t), 1).otherwise(0).alias("__new")))
    totals = flagged.groupBy("__pid").agg(F.sum("__new").alias("__t"))
    offsets = totals.select("__pid", F.coalesce(F.sum("__t").over(Window.orderBy("__pid").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("__b"))
    running = F.sum("__new").over(inside.rowsBetween(Window.unboundedPreceding, 0))
    return flagged.join(F.broadcast(offsets), "__pid").select("rec_id", (running + F.col("__b")).alias("block_id"))


def knn_blocks(vectors: DataFrame, k: int, cells: int = 1, limit: int = 20_000) -> DataFrame:
    """Clusters of at least k: a base (least id left) takes its k - 1 nearest; what is over joins
    the cluster of its nearest record. The greedy order is sequential, so a worker holds a cell:
    ``cells`` of them, cut along the first component, are each clustered for itself, as the caller
    asks; more than ``limit`` records in a cell are refused, not cut silently. Records with a null
    vector, or one with a null, make a cell and a cluster of their own."""
    n = vectors.count()
    if n > cells * limit:
        raise ValueError(f"{n} records need at least {-(-n // limit)} cells")
    whole = F.coalesce(~F.exists("vec", lambda x: x.isNull() | F.isnan(x)), F.lit(False))
    good = vectors.where(whole)
    placed = good.select("rec_id", "vec", F.lit(0).cast("long").alias("cell"))
    if cells > 1:
        placed = running_sums(good, [F.col("vec")[0], F.col("rec_id")], {"__pos": F.lit(1)}).select("rec_id", "vec", F.floor((F.col("__pos") - 1) * cells / n).alias("cell"))
    rest = vectors.where(~whole)

    def grow(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("rec_id")
        ids, x = pdf["rec_id"].to_numpy(), np.stack(pdf["vec"].to_numpy())
        block, left = np.full(len(ids), -1), np.ones(len(ids), bool)
        if len(ids) < k:
            return pd.DataFrame({"rec_id": ids, "block_id": ids.min()})
        base_of = np.full(len(ids), -1)
        while left.sum() >= k:
            base = int(np.flatnonzero(left)[0])
            d = ((x - x[base]) ** 2).sum(1).round(9)
            d[~left] = np.inf
            d[base] = -1
            own = np.lexsort((ids, d))[:k]
            block[own], left[own], base_of[own] = ids[own].min(), False, base
        for i in np.flatnonzero(left):
            d = ((x - x[i]) ** 2).sum(1).round(9)
            d[base_of < 0] = np.inf
            block[i] = block[int(d.argmin())]
        return pd.DataFrame({"rec_id": ids, "block_id": block})

    least = rest.agg(F.min("rec_id").alias("block_id"))  # one row
    return placed.groupBy("cell").applyInPandas(grow, "rec_id long, block_id long").unionByName(rest.select("rec_id").join(F.broadcast(least)))


def canopy_bases(ids: DataFrame, near: DataFrame, seed: int = 42) -> DataFrame:
    """Bases of canopies: taking records in a random order and dropping what is near to one gives
    the first-in-order independent set, found in rounds: a record before all its undecided
    neighbours is a base, and its neighbours are out."""
    state = cut(rank_by_digest(ids, seed).withColumn("base", F.lit(None).cast("boolean")))
    both = cut(near.select("id_a", "id_b").unionByName(near.select(F.col("id_b").alias("id_a"), F.col("id_a").alias("id_b"))).distinct())
    while not (open_rows := state.where("base is null")).isEmpty():
        rivals = both.join(open_rows.select(F.col("rec_id").alias("id_b"), F.col("ord").alias("ob")), "id_b").groupBy("id_a").agg(F.min("ob").alias("least"))
        fresh = open_rows.join(rivals, open_rows["rec_id"] == rivals["id_a"], "left").where(F.col("least").isNull() | (F.col("ord") < F.col("least"))).select("rec_id")
        out = both.join(fresh.withColumnRenamed("rec_id", "id_b"), "id_b", "left_semi").select(F.col("id_a").alias("rec_id")).distinct()
        state = cut(state.join(fresh.withColumn("f", F.lit(True)), "rec_id", "left").join(out.withColumn("o", F.lit(True)), "rec_id", "left").select("rec_id", "ord", F.coalesce("base", "f", F.when(F.col("o"), F.lit(False))).alias("base")))
    return state.where("base").select("rec_id", "ord")


def canopies(ids: DataFrame, pairs: DataFrame, t1: float, t2: float, seed: int = 42) -> DataFrame:
    """(rec_id, canopy_id): ``pairs(id_a, id_b, distance)`` hold all within t1."""
    if t2 > t1:
        raise ValueError("t2 must not exceed t1")
    bases = canopy_bases(ids, pairs.where(F.col("distance") <= t2), seed)
    both = pairs.where(F.col("distance") <= t1).select("id_a", "id_b").unionByName(pairs.where(F.col("distance") <= t1).select(F.col("id_b").alias("id_a"), F.col("id_a").alias("id_b")))
    members = both.join(bases.select(F.col("rec_id").alias("id_a")), "id_a").select(F.col("id_b").alias("rec_id"), F.col("id_a").alias("canopy_id"))
    return bases.select("rec_id", F.col("rec_id").alias("canopy_id")).unionByName(members).distinct()


def canopy_pairs(cover: DataFrame) -> DataFrame:
    a, b = cover.select(F.col("rec_id").alias("id_a"), "canopy_id"), cover.select(F.col("rec_id").alias("id_b"), "canopy_id")
    return a.join(b, "canopy_id").where("id_a < id_b").select("id_a", "id_b").distinct()


def canopy_blocks(cover: DataFrame, mode: str = "equal", seed: int = 42) -> DataFrame:
    """``equal``: each record to its first base; ``atoms``: records of the same canopies; ``merge``: canopies that share a record."""
    if mode == "atoms":
        return cover.groupBy("rec_id").agg(F.array_join(F.array_sort(F.collect_set("canopy_id")), ",").alias("block_id"))
    if mode == "merge":
        return connected_components(cover.select(F.col("rec_id").alias("src"), F.col("canopy_id").alias("dst")), cover.select(F.col("rec_id").alias("node"))).select(F.col("node").alias("rec_id"), F.col("component_id").alias("block_id"))
    order = rank_by_digest(cover.select(F.col("canopy_id").alias("rec_id")).distinct(), seed).select(F.col("rec_id").alias("canopy_id"), "ord")
    return cover.join(order, "canopy_id").groupBy("rec_id").agg(F.min_by("canopy_id", "ord").alias("block_id"))


def reference_blocks(records: DataFrame, refs: DataFrame, key: str, k: int, most: int = 1_000_000) -> DataFrame:
    """(rec_id, ref, block_id): each record's nearest reference value that is not above its own, by an
    as-of scan (records and values in one order, cut into ranges, the last value carried on); blocks
    of adjacent values merge until they hold k records, what is over joins the last block. A record
    below all values, or with a null, has the empty value. Merging goes value by value, so at most
    ``most`` of the public values may be in use; more are refused."""
    spark = records.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    both = records.select("rec_id", F.col(key).alias("v"), F.lit(None).cast("string").alias("ref")).unionByName(refs.where(F.col(key).isNotNull()).select(F.lit(None).cast("long").alias("rec_id"), F.col(key).alias("v"), F.col(key).cast("string").alias("ref")).distinct())
    placed = stored(both.repartitionByRange(parts, "v", F.col("rec_id").asc_nulls_first()).withColumn("__pid", F.spark_partition_id()))
    order = [F.col("v").asc_nulls_first(), F.col("rec_id").asc_nulls_first()]
    ends = placed.where("ref is not null").groupBy("__pid").agg(F.max("v").cast("string").alias("last"))
    pids = placed.select("__pid").distinct().join(ends, "__pid", "left")
    carried = pids.select("__pid", F.last("last", ignorenulls=True).over(Window.orderBy("__pid").rowsBetween(Window.unboundedPreceding, -1)).alias("carried"))  # one row for each range
    inside = Window.partitionBy("__pid").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    found = F.coalesce(F.last("ref", ignorenulls=True).over(inside), F.col("carried"), F.lit(""))
    named = stored(placed.join(F.broadcast(carried), "__pid").withColumn("found", found).where("rec_id is not null").select("rec_id", F.when(F.col("v").isNull(), F.lit("")).otherwise(F.col("found")).alias("ref")))
    sizes = named.groupBy("ref").agg(F.count("*").alias("n"))
    if sizes.count() > most:
        raise ValueError(f"more than {most} reference values are in use")
    group, held, of = 0, 0, []
    for v, n in sorted(map(tuple, sizes.collect())):  # at most ``most`` rows
        of.append((v, group))
        held += n
        if held >= k:
            group, held = group + 1, 0
    if held and group:
        of = [(v, min(g, group - 1)) for v, g in of]
    return named.join(spark.createDataFrame(of, "ref string, block_id long"), "ref").select("rec_id", "ref", "block_id")


def assign_new(new: DataFrame, old: DataFrame, blocks: DataFrame) -> DataFrame:
    """Block of the nearest record for each new vector, ties to the smaller id; new vectors are sent
    to the old ones so many at a time, each ``FEW`` of them in a pass over the old ones."""
    turns = -(-new.count() // FEW)
    far = F.round(F.aggregate(F.zip_with("va", "vb", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x), 9)
    b = old.select("rec_id", F.col("vec").alias("vb"))
    out = None
    numbered = new.select(F.col("rec_id").alias("new_id"), F.col("vec").alias("va"))
    if turns > 1:
        numbered = stored(running_sums(numbered, [F.col("new_id")], {"__n": F.lit(1)}))
    for i in range(max(turns, 1)):
        a = numbered.where(F.floor((F.col("__n") - 1) / FEW) == i).drop("__n") if turns > 1 else numbered
        part = b.join(F.broadcast(a)).groupBy("new_id").agg(F.min(F.struct(far.alias("d"), F.col("rec_id"))).alias("m")).select("new_id", F.col("m.rec_id").alias("rec_id"))
        out = part if out is None else out.unionByName(part)
    return out.join(blocks, "rec_id").select(F.col("new_id").alias("rec_id"), "block_id")
