"""Accuracy and cost of blocks and of candidate pairs, without making pairs of blocks."""

from __future__ import annotations

import math
import time

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def choose2(n: Column) -> Column:
    """Pairs among n; decimal, as a large file's pairs exceed a long."""
    n = n.cast("decimal(19,0)")
    return (n * (n - 1) / 2).cast("decimal(38,0)")


def _settings(by: list[str] | None) -> list[str]:
    """Names of columns that tell a setting; those of the results are taken."""
    taken = {"rec_id", "entity_id", "block_id", "id_a", "id_b", "kept", "kept_true", "recall", "rr", "missed", "precision", "blocks", "max_block", "n", "all_true", "ea", "eb"}
    if clash := taken & set(by or []):
        raise ValueError(f"a setting can't be named {sorted(clash)}")
    return by or []


def block_scores(blocks: DataFrame, truth: DataFrame, by: list[str] | None = None) -> DataFrame:
    """kept, kept_true, recall and rr of ``blocks(rec_id, block_id)`` against ``truth(rec_id, entity_id)``:
    sums over block sizes, never over pairs. ``by``: columns of blocks that name a setting."""
    by = _settings(by)
    both = blocks.join(truth.select("rec_id", "entity_id"), "rec_id")
    cells = both.groupBy(*by, "block_id", "entity_id").agg(F.count("*").alias("__c"))
    per_block = cells.groupBy(*by, "block_id").agg(F.sum("__c").alias("__size"), F.sum(choose2(F.col("__c"))).alias("__true"))
    kept = per_block.groupBy(*by).agg(F.sum(choose2(F.col("__size"))).alias("kept"), F.sum("__true").alias("kept_true"), F.count("*").alias("blocks"), F.max("__size").alias("max_block"))
    return rates(kept, truth)


def pair_scores(pairs: DataFrame, truth: DataFrame, by: list[str] | None = None) -> DataFrame:
    """The same of distinct ``pairs(id_a, id_b)``."""
    by = _settings(by)
    a, b = truth.select(F.col("rec_id").alias("id_a"), F.col("entity_id").alias("ea")), truth.select(F.col("rec_id").alias("id_b"), F.col("entity_id").alias("eb"))
    kept = pairs.join(a, "id_a").join(b, "id_b").groupBy(*by).agg(F.count("*").cast("decimal(38,0)").alias("kept"), F.sum(F.when(F.col("ea") == F.col("eb"), 1).otherwise(0)).cast("decimal(38,0)").alias("kept_true"))
    return rates(kept, truth)


def rates(kept: DataFrame, truth: DataFrame) -> DataFrame:
    """Adds recall, rr, the share missed and precision to rows with kept and kept_true; recall is null without true pairs, rr is null below two records."""
    entities = truth.groupBy("entity_id").agg(F.count("*").alias("c"))
    whole = entities.agg(F.sum("c").alias("n"), F.sum(choose2(F.col("c"))).alias("all_true"))
    rows = kept.crossJoin(F.broadcast(whole))  # one row
    total = choose2(F.col("n"))
    kept_true = F.coalesce("kept_true", F.lit(0))
    recall = F.when(F.col("all_true") > 0, F.round(kept_true.cast("double") / F.col("all_true").cast("double"), 6))
    rr = F.when(F.col("n") > 1, F.round(1 - F.col("kept").cast("double") / total.cast("double"), 6))
    return rows.select(*[c for c in kept.columns if c not in ("kept", "kept_true")], F.col("kept").cast("double").alias("kept"), kept_true.cast("double").alias("kept_true"), recall.alias("recall"), rr.alias("rr"), F.round(1 - recall, 6).alias("missed"), F.when(F.col("kept") > 0, F.round(kept_true.cast("double") / F.col("kept").cast("double"), 6)).alias("precision"))


def comparison_cost(blocks: DataFrame, d: int = 2) -> DataFrame:
    """blocks, n_max, the bound blocks * n_max**d and the sum of size**d."""
    sizes = blocks.groupBy("block_id").agg(F.count("*").alias("s"))
    return sizes.agg(F.count("*").alias("blocks"), F.max("s").alias("n_max"), F.sum(F.pow("s", F.lit(d))).alias("sum_cost")).select("blocks", "n_max", (F.col("blocks") * F.pow("n_max", F.lit(d))).alias("bound_cost"), "sum_cost")


def block_dispersion(blocks: DataFrame) -> DataFrame:
    sizes = blocks.groupBy("block_id").agg(F.count("*").alias("s"))
    return sizes.agg(F.count("*").alias("blocks"), F.round(F.avg("s"), 6).alias("mean_size"), F.round(F.stddev_pop("s"), 6).alias("sd_size"), F.min("s").alias("min_size"), F.max("s").alias("max_size"), F.round(F.stddev_pop("s") / F.avg("s"), 6).alias("cv_size"))


def size_histogram(blocks: DataFrame) -> DataFrame:
    return blocks.groupBy("block_id").agg(F.count("*").alias("size")).groupBy("size").agg(F.count("*").alias("n_blocks"))


def anonymity_level(blocks: DataFrame, k: int = 2) -> DataFrame:
    """The least block size, and how many blocks are below k."""
    sizes = blocks.groupBy("block_id").agg(F.count("*").alias("s"))
    return sizes.agg(F.min("s").alias("level"), F.sum(F.when(F.col("s") < k, 1).otherwise(0)).alias("below_k"))


def bucket_stats(keys: DataFrame) -> DataFrame:
    """Of each band: buckets, largest bucket, sum of squared sizes."""
    return keys.groupBy("band", "key").agg(F.count("*").alias("v")).groupBy("band").agg(F.count("*").alias("buckets"), F.max("v").alias("max_v"), F.sum(F.col("v") * F.col("v")).alias("sum_v2"))


def predicted_cost(method: str, n: float, p: int = 100, b: int = 22, buckets: float = 1e9, beta: float = 0.5, rounds: int = 10, c: float | None = None, files: int = 2) -> float:
    """Steps that the growth formulas give for a method over n records; ``files``: how many files
    every combination of records is taken from when nothing is blocked."""
    c = math.sqrt(n) if c is None else c
    return float(
        {
            "tlsh": n + n * p + n * b + n * n / buckets + n * math.log(n) ** 2,
            "klsh": n * p * n**beta + c * n * p * rounds,
            "traditional": n,
            "traditional_pairs": n * n,
            "tnn": n * n,
            "canopies": n * c,
            "blocked": c * (n / c) ** files,
            "none": float(n) ** files,
        }[method]
    )


def timed(frame: DataFrame) -> float:
    """Seconds to compute all rows of a frame, which go nowhere."""
    began = time.time()
    frame.write.format("noop").mode("overwrite").save()
    return time.time() - began


def sqrt_time_fit(times: DataFrame) -> DataFrame:
    """How straight the root of the time is over n."""
    return times.agg(F.regr_slope(F.sqrt("seconds"), F.col("n").cast("double")).alias("slope"), F.regr_r2(F.sqrt("seconds"), F.col("n").cast("double")).alias("r2"))


def dominated(results: DataFrame) -> DataFrame:
    """Pairs of settings of which the first is no worse in recall and rr and better in one."""
    a, b = results.select(F.col("method").alias("better"), F.col("recall").alias("ra"), F.col("rr").alias("qa")), results.select(F.col("method").alias("worse"), F.col("recall").alias("rb"), F.col("rr").alias("qb"))
    return a.join(b, (F.col("ra") >= F.col("rb")) & (F.col("qa") >= F.col("qb")) & ((F.col("ra") > F.col("rb")) | (F.col("qa") > F.col("qb")))).select("better", "worse")


def best_setting(results: DataFrame, least_rr: float) -> DataFrame:
    """The setting of highest recall whose rr is high enough."""
    return results.where(F.col("rr") >= least_rr).orderBy(F.desc("recall"), F.desc("rr"), "method").limit(1)
