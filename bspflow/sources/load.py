"""Graphs from edge tables, edge lists and adjacency text, and results to files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..model import Graph


def from_edges(spark: SparkSession, path: str, fmt: str = "parquet", src: str = "src", dst: str = "dst", weight: str | None = None, **options) -> Graph:
    """A graph from a table of pairs: parquet, csv or json, with a declared schema for text formats."""
    reader = spark.read.format(fmt).options(**options)
    if fmt in ("csv", "json"):
        reader = reader.schema(f"{src} long, {dst} long" + (f", {weight} long" if weight else ""))
    rows = reader.load(path)
    value = F.col(weight).cast("long") if weight else F.lit(1).cast("long")
    return Graph.of(rows.select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst"), value.alias("weight")))


def from_adjacency(spark: SparkSession, path: str) -> Graph:
    """Lines ``vid dst dst ...``; a line with a vid alone is a vertex without edges."""
    parts = spark.read.text(path).select(F.split(F.trim("value"), r"\s+").alias("x")).where("x[0] <> ''")
    rows = parts.select(F.expr("x[0]").cast("long").alias("src"), F.explode_outer(F.expr("slice(x, 2, greatest(size(x) - 1, 0))")).cast("long").alias("dst"))
    edges = rows.where("dst IS NOT NULL").withColumn("weight", F.lit(1).cast("long"))
    return Graph.of(edges, vertices=rows.select(F.col("src").alias("vid")).distinct())


def dump(df: DataFrame, path: str, fmt: str = "parquet", partitions: int | None = None) -> None:
    """Write a result; csv and json suit flat results only."""
    (df.repartition(partitions) if partitions else df).write.mode("overwrite").format(fmt).save(path)


class _Chunk(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class RingSource(DataSource):
    """``spark.read.format("ring")``: edges of a ring of ``n`` vertices, made in ``parts`` partitions; for tests."""

    @classmethod
    def name(cls) -> str:
        return "ring"

    def schema(self) -> str:
        return "src bigint, dst bigint, weight bigint"

    def reader(self, schema):
        return _RingReader(int(self.options.get("n", 10)), int(self.options.get("parts", 2)))


class _RingReader(DataSourceReader):
    def __init__(self, n: int, parts: int):
        self.n, self.parts = n, parts

    def partitions(self):
        return [_Chunk(self.n * i // self.parts, self.n * (i + 1) // self.parts) for i in range(self.parts)]

    def read(self, chunk):
        for v in range(chunk.first, chunk.last):
            yield v, (v + 1) % self.n, 1
