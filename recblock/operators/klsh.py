"""Projection blocking: weighted bags of shingles, random projections, k-means."""

from __future__ import annotations

import hashlib
import math
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from recblock.operators.shingle import shingle_counts, with_text
from recblock.session import cut, stored

CENTROID_NUMBERS = 1 << 24  # 128 MB
VOCABULARY = 1 << 17  # shingles whose frequencies every worker holds
SHORT = 4  # vectors that have so many bytes for each letter are worked out again, not written


def idf(counts: DataFrame, n: int, smooth: bool = False) -> DataFrame:
    """(term, df, idf): ln(n / df), or its smoothed form."""
    df = counts.groupBy("term").agg(F.count("*").alias("df"))
    weight = F.ln((F.lit(n) + 1) / (F.col("df") + 1)) if smooth else F.ln(F.lit(n) / F.col("df"))
    return df.select("term", "df", weight.alias("idf"))


def weighted_terms(counts: DataFrame, n: int, smooth: bool = False) -> DataFrame:
    return counts.join(idf(counts, n, smooth), "term").select("rec_id", "term", (F.col("tf") * F.col("idf")).alias("w"))


def bag_similarity(weighted: DataFrame, normalize: bool = False) -> DataFrame:
    """(id_a, id_b, sim): inner products over the inverted index."""
    if normalize:
        norms = weighted.groupBy("rec_id").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
        weighted = weighted.join(norms.where("norm > 0"), "rec_id").select("rec_id", "term", (F.col("w") / F.col("norm")).alias("w"))
    a, b = weighted.select(F.col("rec_id").alias("id_a"), "term", F.col("w").alias("wa")), weighted.select(F.col("rec_id").alias("id_b"), "term", F.col("w").alias("wb"))
    return a.join(b, "term").where("id_a < id_b").groupBy("id_a", "id_b").agg(F.sum(F.col("wa") * F.col("wb")).alias("sim"))


def signs(term: str, p: int, kind: str = "sign", seed: int = 42) -> np.ndarray:
    """A term's row of the projection, from digests: nothing is stored and no vocabulary is needed."""
    if kind == "sign":
        return np.array([1.0 if int(hashlib.md5(f"{seed}|{term}|{j}".encode()).hexdigest()[0], 16) % 2 == 0 else -1.0 for j in range(p)]) / math.sqrt(p)
    rng = np.random.default_rng(int.from_bytes(hashlib.md5(f"{seed}|{term}".encode()).digest()[:8], "little"))
    if kind == "gaussian":
        return rng.standard_normal(p) / math.sqrt(p)
    if kind == "sparse3":
        return rng.choice([-1.0, 0.0, 1.0], p, p=[1 / 6, 2 / 3, 1 / 6]) * math.sqrt(3 / p)
    raise ValueError(kind)


def project(weighted: DataFrame, p: int = 150, kind: str = "sign", seed: int = 42, unit: bool = False) -> DataFrame:
    """(rec_id, vec)."""
    bags = weighted.groupBy("rec_id").agg(F.collect_list("term").alias("terms"), F.collect_list("w").alias("ws"))
    known: dict[str, np.ndarray] = {}

    @F.pandas_udf("array<double>")
    def run(terms: pd.Series, ws: pd.Series) -> pd.Series:
        out = []
        for t, w in zip(terms, ws, strict=True):
            v = np.zeros(p)
            for term, x in sorted(zip(t, w, strict=True)):
                if term not in known:
                    if len(known) > 50_000:
                        known.clear()
                    known[term] = signs(term, p, kind, seed)
                v += x * known[term]
            if unit and (norm := np.linalg.norm(v)) > 0:
                v /= norm
            out.append(v.round(9))
        return pd.Series(out)

    return bags.select("rec_id", run("terms", "ws").alias("vec"))


def blocks_for(n: int, mode: str = "sqrt", c: int = 100, size: int = 100) -> int:
    return {"constant": c, "size": max(1, n // size), "sqrt": math.ceil(math.sqrt(n))}[mode]


def _held(c: int, p: int) -> None:
    """Centroids stand on the driver and in every worker, so their size is checked."""
    if c * p > CENTROID_NUMBERS:
        raise ValueError(f"{c} centroids of {p} numbers are too many for one level; cluster in two levels")


def least_digests(rows: DataFrame, c: int, seed: int = 42) -> DataFrame:
    return rows.orderBy(F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("rec_id").cast("string"))), "rec_id").limit(c)


def first_centroids(vectors: DataFrame, c: int, seed: int = 42) -> np.ndarray:
    """The vectors of the c records of least digest."""
    rows = least_digests(vectors, c, seed).select("vec").collect()
    if rows:
        _held(c, len(rows[0][0]))
    return np.array([r[0] for r in rows])


def assign_nearest(vectors: DataFrame, centroids: np.ndarray) -> DataFrame:
    """(rec_id, cluster, vec): the nearest centroid, ties to the lower number."""
    shared = vectors.sparkSession.sparkContext.broadcast(centroids)  # c * p numbers

    @F.pandas_udf("int")
    def run(vec: pd.Series) -> pd.Series:
        m, out = shared.value, []
        norms = (m * m).sum(1)
        for k in range(0, len(vec), 2048):
            x = np.stack(vec.iloc[k : k + 2048].to_numpy())
            out.append((norms[None, :] - 2 * x @ m.T).round(9).argmin(1))
        return pd.Series(np.concatenate(out) if out else [], dtype="int32")

    return vectors.select("rec_id", run("vec").alias("cluster"), "vec")


def lloyd_step(vectors: DataFrame, centroids: np.ndarray) -> np.ndarray:
    """Means of the assigned vectors; an empty cluster keeps its centroid. c * p sums reach the driver."""
    c, p = centroids.shape
    assigned = assign_nearest(vectors, centroids)

    def sums(batches):
        total, count = np.zeros((c, p)), np.zeros(c, np.int64)
        for pdf in batches:
            if len(pdf):
                np.add.at(total, pdf["cluster"].to_numpy(), np.stack(pdf["vec"].to_numpy()))
                count += np.bincount(pdf["cluster"].to_numpy(), minlength=c)
        own = np.flatnonzero(count)
        yield pd.DataFrame({"cluster": own.repeat(p), "j": np.tile(np.arange(p), len(own)), "s": total[own].ravel(), "n": count[own].repeat(p)})

    out = centroids.copy()
    for r in assigned.mapInPandas(sums, "cluster long, j long, s double, n long").groupBy("cluster", "j").agg((F.sum("s") / F.sum("n")).alias("m")).collect():
        out[r[0], r[1]] = r[2]
    return out


def kmeans_blocks(vectors: DataFrame, c: int, iters: int = 10, seed: int = 42, engine: str = "own", levels: int = 1, written: bool = False, start: np.ndarray | None = None) -> DataFrame:
    """(rec_id, block_id). ``written``: the vectors need not be written before the rounds read them. ``start``: the first centroids, if they are known.
    ``engine``: ``own`` (fixed rounds, fixed start) or ``mllib`` (k-means||);
    two levels cluster the cells of a coarse clustering again."""
    if levels == 2:
        coarse = max(1, round(math.sqrt(c)))
        cells = cut(vectors.join(kmeans_blocks(vectors, coarse, iters, seed, engine), "rec_id"))
        parts = [kmeans_blocks(cells.where(F.col("block_id") == i).select("rec_id", "vec"), -(-c // coarse), iters, seed, engine).select("rec_id", (F.col("block_id") + i * c).alias("block_id")) for i in range(coarse)]
        out = parts[0]
        for x in parts[1:]:
            out = out.unionByName(x)
        return out
    if engine == "mllib":
        from pyspark.ml.clustering import KMeans
        from pyspark.ml.functions import array_to_vector

        points = vectors.select("rec_id", array_to_vector("vec").alias("features"))
        return KMeans(k=c, maxIter=iters, seed=seed).fit(points).transform(points).select("rec_id", F.col("prediction").cast("long").alias("block_id"))
    held = vectors if written else cut(vectors)
    centroids = first_centroids(held, c, seed) if start is None else start
    if not len(centroids):
        return held.select("rec_id", F.lit(0).cast("long").alias("block_id"))
    for _ in range(iters):
        centroids = lloyd_step(held, centroids)
    return assign_nearest(held, centroids).select("rec_id", F.col("cluster").cast("long").alias("block_id"))


def merge_small(vectors: DataFrame, blocks: DataFrame, k: int) -> DataFrame:
    """Blocks below k records dissolve into the nearest of the others, so every block has k."""
    sizes = blocks.groupBy("block_id").agg(F.count("*").alias("n"))
    large = sizes.where(F.col("n") >= k)
    held = stored(vectors.join(blocks, "rec_id"))
    means = held.join(large, "block_id").select("block_id", F.posexplode("vec").alias("j", "x")).groupBy("block_id", "j").agg(F.avg("x").alias("m")).groupBy("block_id").agg(F.array_sort(F.collect_list(F.struct("j", "m"))).alias("m")).orderBy("block_id").collect()  # c * p numbers
    if not means:
        return blocks.withColumn("block_id", F.lit(0).cast("long"))
    _held(len(means), len(means[0][1]))
    ids = F.array(*[F.lit(r[0]).cast("long") for r in means])
    rest = held.join(large, "block_id", "left_anti").select("rec_id", "vec")
    moved = assign_nearest(rest, np.array([[x["m"] for x in r[1]] for r in means])).select("rec_id", ids[F.col("cluster")].alias("block_id"))
    return held.join(large, "block_id", "left_semi").select("rec_id", "block_id").unionByName(moved)


def _bag(text: str | None, k: int) -> Counter:
    """char_shingles of a text, counted."""
    text = text or ""
    return Counter([text[i : i + k] for i in range(len(text) - k + 1)] or ([text] if text else []))


def shingle_df(texts: DataFrame, k: int) -> DataFrame:
    """(term, df) of ``texts(rec_id, rec_text)``: counted where texts stand, so that no text's shingles are written."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        df: Counter = Counter()
        for batch in batches:
            for text in batch.column(0).to_pylist():
                df.update(_bag(text, k).keys())
                if len(df) > VOCABULARY:
                    yield pa.RecordBatch.from_arrays([pa.array(list(df)), pa.array(list(df.values()))], ["term", "df"])
                    df.clear()
        yield pa.RecordBatch.from_arrays([pa.array(list(df), pa.string()), pa.array(list(df.values()), pa.int64())], ["term", "df"])

    return texts.select("rec_text").mapInArrow(run, "term string, df long").groupBy("term").agg(F.sum("df").alias("df"))


def klsh_vectors(records: DataFrame, fields: list[str], k: int = 2, p: int = 150, kind: str = "sign", seed: int = 42, unit: bool = False, vocabulary: int = VOCABULARY) -> DataFrame:
    """(rec_id, vec) of the records that have text. Where at most ``vocabulary`` shingles are in use and no
    id repeats, frequencies go to the texts and no shingle is written; else counts are joined with them. The
    vectors are the same."""
    texts, n = with_text(records, fields), records.count()
    weights = _held_weights(records, texts, n, k, vocabulary)
    if weights is None:
        counts = stored(shingle_counts(texts, k))  # read for the frequencies and for the bags
        return project(weighted_terms(counts, n), p, kind, seed, unit)
    return _text_vectors(texts, weights, k, p, kind, seed, unit)


def _held_weights(records: DataFrame, texts: DataFrame, n: int, k: int, vocabulary: int = VOCABULARY):
    """Frequencies' weights for every worker, of bounded size; None if there are more, or an id repeats."""
    df = stored(shingle_df(texts, k))
    if df.count() > vocabulary or not records.groupBy("rec_id").count().where("count > 1").isEmpty():
        return None
    return records.sparkSession.sparkContext.broadcast(dict(map(tuple, df.select("term", F.ln(F.lit(n) / F.col("df"))).collect())))


_known: dict[tuple, dict[str, np.ndarray]] = {}  # rows of projections that a worker has worked out


def _text_vectors(texts: DataFrame, weights, k: int, p: int, kind: str, seed: int, unit: bool) -> DataFrame:
    """(rec_id, vec) of ``texts(rec_id, rec_text)`` that are not empty, worked out where texts stand."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        of, known = weights.value, _known.setdefault((p, kind, seed), {})
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part, ids, bags = batch.slice(at, 256), [], []
                if len(known) > 50_000:
                    known.clear()
                for i, text in enumerate(part.column(1).to_pylist()):
                    if bag := _bag(text, k):
                        ids.append(i)
                        bags.append(sorted(bag.items()))
                if not ids:
                    continue
                terms = list({t for bag in bags for t, _ in bag})
                place = {t: x for x, t in enumerate(terms)}
                rows = np.stack([known[t] if t in known else known.setdefault(t, signs(t, p, kind, seed)) for t in terms])
                size = np.array([len(bag) for bag in bags])
                first = np.cumsum(size) - size
                term = np.array([place[t] for bag in bags for t, _ in bag])
                weight = np.array([c * of[t] for bag in bags for t, c in bag])
                vec = np.zeros((len(ids), p))
                for j in range(int(size.max())):  # row after row, of all texts that have so many
                    own = np.flatnonzero(size > j)
                    vec[own] += weight[first[own] + j][:, None] * rows[term[first[own] + j]]
                if unit:
                    norm = np.array([np.linalg.norm(v) for v in vec])
                    vec[norm > 0] /= norm[norm > 0, None]
                lists = pa.ListArray.from_arrays(pa.array(np.arange(0, len(ids) * p + 1, p, dtype=np.int32)), pa.array(vec.round(9).ravel()))
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(ids)), lists], ["rec_id", "vec"])

    return texts.mapInArrow(run, f"rec_id {texts.schema['rec_id'].dataType.simpleString()}, vec array<double>")


def klsh_blocks(records: DataFrame, fields: list[str], k: int = 2, p: int = 150, c: int = 100, iters: int = 10, seed: int = 42, kind: str = "sign", unit: bool = False, engine: str = "own", min_block_size: int | None = None, levels: int = 1) -> DataFrame:
    """A partition in c blocks. ``kind='none'`` clusters hashed weights without a projection.
    A record without text is a block of its own (of a negative number); with ``min_block_size`` it has
    the zero vector and goes to the nearest block that is large enough."""
    if kind == "none":
        from pyspark.ml.clustering import KMeans
        from pyspark.ml.feature import IDF, HashingTF

        from recblock.operators.shingle import char_shingles

        bags = HashingTF(inputCol="s", outputCol="tf", numFeatures=1 << 12).transform(with_text(records, fields).select("rec_id", char_shingles(F.col("rec_text"), k).alias("s")))
        points = IDF(inputCol="tf", outputCol="features").fit(bags).transform(bags)
        return KMeans(k=c, maxIter=iters, seed=seed).fit(points).transform(points).select("rec_id", F.col("prediction").cast("long").alias("block_id"))
    texts, weights = with_text(records, fields), None
    some = texts.where(F.length("rec_text") > 0)
    n, letters = some.agg(F.count("*"), F.coalesce(F.sum(F.length("rec_text")), F.lit(0))).first()
    if engine == "own" and levels == 1 and not min_block_size and letters * SHORT <= n * p * 8:
        weights = _held_weights(records, texts, records.count(), k)
    if weights is not None:  # vectors are many times as long as their texts: rounds read these, and no vector is written
        make = lambda rows: _text_vectors(rows, weights, k, p, kind, seed, unit)
        c = min(c, max(1, n))
        start = first_centroids(make(least_digests(some, c, seed)), c, seed)
        blocks = kmeans_blocks(make(some), c, iters, seed, written=True, start=start)
    else:
        vectors = stored(klsh_vectors(records, fields, k, p, kind, seed, unit))
        blocks = kmeans_blocks(vectors, min(c, max(1, vectors.count())), iters, seed, engine, levels, written=True)
    empty = records.select("rec_id").join(some, "rec_id", "left_anti")
    own = F.when(F.col("rec_id") >= 0, -1 - 2 * F.col("rec_id")).otherwise(2 * F.col("rec_id"))
    blocks = blocks.unionByName(empty.select("rec_id", own.cast("long").alias("block_id")))
    if not min_block_size:
        return blocks
    zero = F.array(*[F.lit(0.0)] * p)
    return merge_small(vectors.unionByName(empty.select("rec_id", zero.alias("vec"))), stored(blocks), min_block_size)


def rank_by_digest(ids: DataFrame, seed: int = 42) -> DataFrame:
    """(rec_id, ord): a random order that every engine can recompute."""
    return ids.select("rec_id", F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("rec_id").cast("string"))).alias("ord"))


__all__ = ["Window", "assign_nearest", "bag_similarity", "blocks_for", "first_centroids", "idf", "klsh_blocks", "klsh_vectors", "kmeans_blocks", "lloyd_step", "merge_small", "project", "rank_by_digest", "signs", "weighted_terms"]
