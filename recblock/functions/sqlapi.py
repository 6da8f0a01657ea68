"""Functions for SQL: register(spark) makes them known."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from recblock.operators.minhash import PRIME, band_sizes, hash_family


class _Shingles:
    def eval(self, text: str, k: int) -> Iterator[tuple[str]]:
        if text:
            yield from ((text[i : i + k],) for i in range(max(1, len(text) - k + 1)))


class _Bands:
    def eval(self, sig: list[int], b: int) -> Iterator[tuple[int, str]]:
        at = 0
        for i, r in enumerate(band_sizes(len(sig), b)):
            yield i, ",".join(map(str, sig[at : at + r]))
            at += r


shingles = F.udtf(_Shingles, returnType="shingle: string")
bands = F.udtf(_Bands, returnType="band: int, rows: string")


@F.pandas_udf("double")
def qgram_similarity(a: pd.Series, b: pd.Series) -> pd.Series:
    """Jaccard similarity of two-letter shingle sets."""

    def one(x: str | None, y: str | None) -> float | None:
        if x is None or y is None:
            return None
        s, t = ({v[i : i + 2] for i in range(max(1, len(v) - 1))} if v else set() for v in (x, y))
        return len(s & t) / len(s | t) if s | t else 1.0

    return pd.Series([one(x, y) for x, y in zip(a, b, strict=True)])


@F.pandas_udf("array<double>")
def centroid_avg(v: pd.Series) -> list:
    """Mean vector of a group."""
    import numpy as np

    return np.stack(v.to_numpy()).mean(0).tolist()


def register(spark: SparkSession, p: int = 100, seed: int = 42) -> None:
    """rb_shingles(text, k) and rb_bands(sig, b) as tables; rb_shingle_set, rb_jaccard and
    rb_minhash as expressions that the optimizer sees through."""
    spark.udtf.register("rb_shingles", shingles)
    spark.udtf.register("rb_bands", bands)
    spark.udf.register("rb_qgram_similarity", qgram_similarity)
    family = ", ".join(f"named_struct('a', {a}L, 'c', {c}L)" for a, c in hash_family(p, seed))
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION rb_shingle_set(t STRING, k INT) RETURNS ARRAY<STRING> RETURN array_distinct(transform(sequence(1, greatest(1, length(t) - k + 1)), i -> substr(t, i, k)))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION rb_jaccard(a ARRAY<STRING>, b ARRAY<STRING>) RETURNS DOUBLE RETURN size(array_intersect(a, b)) / size(array_union(a, b))")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION rb_minhash(s ARRAY<STRING>) RETURNS ARRAY<BIGINT> RETURN transform(array({family}), f -> array_min(transform(s, x -> (CAST(conv(substr(md5(x), 1, 8), 16, 10) AS BIGINT) % {PRIME} * f.a + f.c) % {PRIME})))")
