"""Where blocks are kept, and a source that makes person files."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def write_blocks(blocks: DataFrame, table: str, buckets: int = 64) -> None:
    """A table bucketed and sorted by block, so that linking and scoring need no shuffle."""
    blocks.write.bucketBy(buckets, "block_id").sortBy("block_id", "rec_id").mode("overwrite").saveAsTable(table)


def write_by_batch(blocks: DataFrame, path: str, batch: int) -> None:
    """Writing a batch again replaces it."""
    blocks.write.mode("overwrite").parquet(f"{path}/batch={batch}")


def read_text_format(spark: SparkSession, path: str, kind: str, schema: str) -> DataFrame:
    """csv, json or orc with a given schema; nothing is inferred."""
    return spark.read.schema(schema).format(kind).load(path)


class _Range(InputPartition):
    def __init__(self, start: int, end: int):
        self.start, self.end = start, end


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.n, self.parts = int(options.get("n", 1000)), int(options.get("parts", 4))

    def partitions(self):
        return [_Range(i * self.n // self.parts, (i + 1) * self.n // self.parts) for i in range(self.parts)]

    def read(self, partition) -> Iterator[tuple]:
        import hashlib

        names = ("anna", "bernd", "clara", "dieter", "erika", "franz", "greta", "hans", "ida", "jonas", "karin", "lukas")
        for e in range(partition.start, partition.end):
            d = hashlib.md5(f"42|{e}".encode()).digest()
            yield e, names[d[0] % 12], names[d[1] % 12] + "er", 1920 + d[2] % 80, 1 + d[3] % 12, 1 + d[4] % 28


class PersonsSource(DataSource):
    """format('recblock_persons'): n synthetic records without copies, made where they are read."""

    @classmethod
    def name(cls) -> str:
        return "recblock_persons"

    def schema(self) -> str:
        return "rec_id long, first_name string, last_name string, birth_year int, birth_month int, birth_day int"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)
