"""Readers and writers of relations, and a source of generated rectangles."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..operators.relations import Rel


def read_relation(spark: SparkSession, path: str, keep: str, on: str, where: str | None = None) -> DataFrame:
    """Two columns of a Parquet table; the filter reaches the scan."""
    df = spark.read.parquet(path)
    return (df.where(where) if where else df).select(keep, on)


def read_baskets(df: DataFrame, key: str, text: str, sep: str = " ") -> DataFrame:
    """(item, bag) of lines of items; empty items are dropped."""
    return df.select(F.explode(F.split(F.lower(text), sep)).alias("item"), F.col(key).alias("bag")).where("item <> ''")


def to_coordinates(df: DataFrame, key: str, array: str, cutoff: float) -> DataFrame:
    """(row, col) of array cells above the cutoff: a sparse boolean matrix."""
    return df.select(F.col(key).alias("row"), F.posexplode(array).alias("col", "v")).where(F.col("v").cast("double") > cutoff).select("row", "col")


def read_edges(spark: SparkSession, path: str, fmt: str, schema: str) -> DataFrame:
    """An edge list with an explicit schema, ``csv`` or ``json``."""
    if fmt not in ("csv", "json"):
        raise ValueError("fmt is 'csv' or 'json'")
    return spark.read.schema(schema).format(fmt).load(path)


def save_clustered(rel: Rel, name: str, buckets: int) -> None:
    """Both sides as tables bucketed and sorted by the join value; later joins need no exchange."""
    for side, df in (("left", rel.left), ("right", rel.right)):
        df.write.mode("overwrite").bucketBy(buckets, "jk").sortBy("jk").saveAsTable(f"{name}_{side}")


def table_blocks(df: DataFrame, by: str, left: str, right: str) -> tuple[DataFrame, DataFrame]:
    """(lk, jk) and (jk, rk) of a table's rectangles: what each value of ``by`` has in two columns."""
    rows = df.where(F.col(by).isNotNull())
    return rows.select(F.col(left).alias("lk"), F.col(by).alias("jk")).distinct(), rows.select(F.col(by).alias("jk"), F.col(right).alias("rk")).distinct()


class _Block(InputPartition):
    def __init__(self, number: int):
        self.number = number


class _BlockReader(DataSourceReader):
    def __init__(self, blocks: int, left: int, right: int, overlap: int):
        self.blocks, self.left, self.right, self.overlap = blocks, left, right, overlap

    def partitions(self):
        return [_Block(i) for i in range(self.blocks)]

    def read(self, partition: _Block) -> Iterator[tuple]:
        first = partition.number * (self.left - self.overlap)
        for a in range(first, first + self.left):
            yield ("left", a, partition.number)
        for c in range(self.right):
            yield ("right", c, partition.number)


class BlockSource(DataSource):
    """Rectangles ``left`` x ``right``, one for each join value, neighbours sharing ``overlap`` left values.

    All right sets are equal, so the result has (blocks * left - (blocks - 1) * overlap) * right pairs.
    """

    @classmethod
    def name(cls) -> str:
        return "sparse_blocks"

    def schema(self) -> str:
        return "side string, value long, jk long"

    def reader(self, schema) -> _BlockReader:
        o = self.options
        return _BlockReader(int(o.get("blocks", 4)), int(o.get("left", 10)), int(o.get("right", 10)), int(o.get("overlap", 0)))
