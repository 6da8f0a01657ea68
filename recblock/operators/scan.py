"""Ordered scans without a single-partition window: running sums in two phases."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from recblock.session import cut


def running_sums(df: DataFrame, order: list[Column], sums: dict[str, Column], parts: int | None = None) -> DataFrame:
    """Adds, for each name in ``sums``, the inclusive running sum of its column in the global
    ``order``. The rows are range-partitioned and written once, so the ranges can't move when a
    task is rerun; the totals of the ranges (one row each) give the offsets."""
    spark = df.sparkSession
    parts = parts or int(spark.conf.get("spark.sql.shuffle.partitions"))
    keyed = df.select("*", *[o.alias(f"__o{i}") for i, o in enumerate(order)], *[v.alias(f"__v_{k}") for k, v in sums.items()])
    keys = [f"__o{i}" for i in range(len(order))]
    placed = cut(keyed.repartitionByRange(parts, *keys).withColumn("__pid", F.spark_partition_id()))
    by_range = Window.orderBy("__pid").rowsBetween(Window.unboundedPreceding, -1)
    totals = placed.groupBy("__pid").agg(*[F.sum(f"__v_{k}").alias(f"__t_{k}") for k in sums])
    before = totals.select("__pid", *[F.coalesce(F.sum(f"__t_{k}").over(by_range), F.lit(0)).alias(f"__b_{k}") for k in sums])
    inside = Window.partitionBy("__pid").orderBy(*keys).rowsBetween(Window.unboundedPreceding, 0)
    joined = placed.join(F.broadcast(before), "__pid")  # one row for each range
    return joined.select(*df.columns, *[(F.sum(f"__v_{k}").over(inside) + F.col(f"__b_{k}")).alias(k) for k in sums])
