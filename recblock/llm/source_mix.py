"""Mixing sources to target weights.

Every row gets a hash-random key; within a source the rows stand in key order, cut into
buckets of the key's leading bits, so that no source, however large, is one group. Bucket
totals give each bucket its offset, a window inside the bucket the rest of the prefix sum,
and the prefix is cut at the source's exact budget of words. A budget above the source's
size takes whole epochs first.

Nulls: a null text has size 0; a null source is a source of its own, ordered last; a row without
an id has the key of its text. Repeated rows count each for itself. An empty table gives no rows.
Other columns are not looked at."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from recblock.operators.scan import running_sums
from recblock.session import cut

WEIGHTS, SHARE, EPOCHS = (5, 2, 1), 1.5, 2.0
BUCKETS, BUCKET_ROWS = 64, 50_000  # at least so many buckets of a source, and more for a larger table


def word_count(text: Column) -> Column:
    return F.size(F.filter(F.split(F.coalesce(text, F.lit("")), r"[\x20\x09-\x0D]+"), lambda w: w != "")).cast("long")


def mix_key(doc_id: Column, text: Column) -> Column:
    """60 bits of a digest of the id, or of the text where there is none."""
    return F.conv(F.substring(F.md5(F.coalesce(doc_id.cast("string"), F.concat(F.lit("text "), text), F.lit(""))), 1, 15), 16, 10).cast("long")


def source_targets(sizes: DataFrame, weights: tuple = WEIGHTS, share: float = SHARE, epochs: float = EPOCHS) -> DataFrame:
    """``sizes(src, source_size)`` with each source's ``target``: in proportion to the weights
    up to ``epochs`` times its size, the excess going to the rest. Sources are filled in the
    order of the level at which they are full; all sums are running sums over ranges."""
    ranked = running_sums(sizes, [F.col("src")], {"__rank": F.lit(1)})
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), ((F.col("__rank") - 1) % len(weights) + 1).cast("int"))
    caps = ranked.select("src", "source_size", weight.alias("__w"), (F.col("source_size") * epochs).alias("__cap"))
    filled = running_sums(caps, [F.col("__cap") / F.col("__w"), F.col("src")], {"__caps": F.col("__cap"), "__ws": F.col("__w")})
    whole = filled.agg(F.sum("source_size").alias("__all"), F.sum("__w").alias("__all_w"))  # one row
    level = (F.col("__all") * share - (F.col("__caps") - F.col("__cap"))) / (F.col("__all_w") - (F.col("__ws") - F.col("__w")))
    placed = filled.join(F.broadcast(whole)).withColumn("__level", level).withColumn("__full", F.col("__cap") / F.col("__w") <= F.col("__level"))
    open_level = placed.agg(F.min_by(F.when(~F.col("__full"), F.col("__level")), F.when(~F.col("__full"), F.struct(F.col("__cap") / F.col("__w"), "src"))).alias("__open"))  # one row
    return placed.join(F.broadcast(open_level)).select("src", "source_size", F.when(F.col("__full"), F.col("__cap")).otherwise(F.least("__cap", F.col("__open") * F.col("__w"))).alias("target"))


def _taken(docs: DataFrame, weights: tuple, share: float, epochs: float, least_buckets: int) -> DataFrame:
    """One row per row of ``docs``: doc_id, src, text_hash, size, source_size, target, taken."""
    text = F.col("text").cast("string")
    named = docs.select(
        F.col("doc_id"),
        word_count(text).alias("size"),
        F.when(F.col("source").isNull(), F.lit("1")).otherwise(F.concat(F.lit("0"), F.col("source").cast("string"))).alias("src"),
        F.xxhash64(text).alias("text_hash"),
        mix_key(F.col("doc_id"), text).alias("__key"),
    )
    keyed = cut(named)
    buckets = max(least_buckets, -(-keyed.count() // BUCKET_ROWS))  # a window holds so many rows, whatever its source's size
    sized = keyed.withColumn("__bucket", F.floor(F.col("__key") / F.lit(((1 << 60) - 1) // buckets + 1)).cast("int"))
    by_bucket = sized.groupBy("src", "__bucket").agg(F.sum("size").alias("__sum"))
    targets = source_targets(by_bucket.groupBy("src").agg(F.sum("__sum").alias("source_size")), weights, share, epochs)
    before = Window.partitionBy("src").orderBy("__bucket").rowsBetween(Window.unboundedPreceding, -1)
    offsets = by_bucket.withColumn("__before", F.coalesce(F.sum("__sum").over(before), F.lit(0))).join(targets, "src")
    running = Window.partitionBy("src", "__bucket").orderBy("__key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, 0)
    budget = F.floor(F.col("target")).cast("long")
    placed = sized.join(offsets, ["src", "__bucket"]).withColumn("__start", F.col("__before") + F.sum("size").over(running) - F.col("size"))
    whole = F.when(F.col("source_size") > 0, F.floor(budget / F.col("source_size"))).otherwise(0).cast("long")
    rest = budget - whole * F.col("source_size")
    taken = whole * F.col("size") + F.greatest(F.lit(0).cast("long"), F.least(F.col("size"), rest - F.col("__start")))
    return placed.select("doc_id", "src", "text_hash", "size", "source_size", "target", taken.cast("long").alias("taken"))


def mix_sources(docs: DataFrame, weights: tuple = WEIGHTS, share: float = SHARE, epochs: float = EPOCHS, buckets: int = BUCKETS) -> DataFrame:
    """``docs(doc_id, text, source)`` to doc_id, size, source_size, target and taken (words)."""
    return _taken(docs, weights, share, epochs, buckets).select("doc_id", "size", "source_size", "target", "taken")


def mixed_documents(docs: DataFrame, weights: tuple = WEIGHTS, share: float = SHARE, epochs: float = EPOCHS) -> DataFrame:
    """The rows of ``docs`` that the mix takes, each as often as it takes it; the one document
    of a source that the cut splits stays whole if at least half of it is inside. Rows that are equal
    in id, source and text share what is taken of them, so nothing is taken twice."""
    id_hash = F.xxhash64(F.col("doc_id").isNull(), F.col("doc_id"))
    times = F.when(F.col("size") > 0, F.floor(F.col("taken") / F.col("size") + 0.5)).otherwise(0).cast("long")
    shares = _taken(docs, weights, share, epochs, BUCKETS).groupBy(id_hash.alias("__id"), F.col("src").alias("__src"), F.col("text_hash").alias("__hash")).agg(F.sum(times).alias("__all"), F.count("*").alias("__rows")).where("__all > 0")
    source = F.when(F.col("source").isNull(), F.lit("1")).otherwise(F.concat(F.lit("0"), F.col("source").cast("string")))
    rows = docs.select(F.struct(*docs.columns).alias("__row"), id_hash.alias("__id"), source.alias("__src"), F.xxhash64(F.col("text").cast("string")).alias("__hash"))
    key = ["__id", "__src", "__hash"]
    number = F.row_number().over(Window.partitionBy(*key).orderBy("__all"))
    both = rows.join(shares, key).withColumn("__n", F.floor(F.col("__all") / F.col("__rows")) + (number <= F.col("__all") % F.col("__rows")).cast("int"))
    return both.where("__n > 0").select("__row", F.explode(F.sequence(F.lit(1).cast("long"), F.col("__n")))).select("__row.*")


def op7_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_sources(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "source"))


OP7_SQL = r"""
WITH d AS (
  SELECT doc_id, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS size,
         CASE WHEN source IS NULL THEN '1' ELSE '0' || source END AS src,
         CAST('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), 'text ' || text, '')), 1, 15) AS BIGINT) AS k
  FROM documents),
s AS (SELECT src, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY src),
w AS (SELECT src, source_size, 2.0::DOUBLE * source_size AS cap,
             CASE (row_number() OVER (ORDER BY encode(src)) - 1) % 3 WHEN 0 THEN 5.0::DOUBLE WHEN 1 THEN 2.0::DOUBLE ELSE 1.0::DOUBLE END AS w FROM s),
f AS (SELECT *, sum(source_size) OVER () AS total, sum(w) OVER () AS total_w,
             coalesce(sum(cap) OVER (ORDER BY cap / w, encode(src) ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS caps,
             coalesce(sum(w) OVER (ORDER BY cap / w, encode(src) ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS ws FROM w),
l AS (SELECT *, (total * 1.5::DOUBLE - caps) / (total_w - ws) AS lvl FROM f),
o AS (SELECT arg_min(lvl, cap / w) AS open_lvl FROM l WHERE cap / w > lvl),
t AS (SELECT src, source_size, CASE WHEN cap / w <= lvl THEN cap ELSE least(cap, open_lvl * w) END AS target FROM l LEFT JOIN o ON true),
p AS (SELECT d.doc_id, d.size, t.source_size, t.target, CAST(floor(t.target) AS BIGINT) AS b,
             CAST(sum(d.size) OVER (PARTITION BY d.src ORDER BY d.k, d.doc_id, d.size ROWS UNBOUNDED PRECEDING) - d.size AS BIGINT) AS st
      FROM d JOIN t USING (src)),
q AS (SELECT *, CASE WHEN source_size > 0 THEN b // source_size ELSE 0 END AS full_epochs FROM p)
SELECT doc_id, CAST(size AS BIGINT) AS size, source_size, target,
       CAST(full_epochs * size + greatest(0, least(size, b - full_epochs * source_size - st)) AS BIGINT) AS taken
FROM q
"""
