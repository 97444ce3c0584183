"""Edges from files, and graphs made by rule."""

from __future__ import annotations

import random
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

EDGES = "src bigint, dst bigint"


def read_edge_list(spark: SparkSession, path: str, sep: str = "\t", comment: str = "#", schema: str = EDGES) -> DataFrame:
    """Two columns a line, with comment lines."""
    return spark.read.csv(path, schema=schema, sep=sep, comment=comment)


def read_edges(spark: SparkSession, path: str, kind: str = "parquet", src: str = "src", dst: str = "dst") -> DataFrame:
    """Edges from Parquet, ORC or JSON lines, with the names of the columns given."""
    if kind not in ("parquet", "orc", "json"):
        raise ValueError("kind is one of parquet, orc, json")
    return spark.read.format(kind).load(path).select(F.col(src).alias("src"), F.col(dst).alias("dst"))


def read_matrix_market(spark: SparkSession, path: str) -> DataFrame:
    """Edges of a Matrix Market coordinate file, through Spark's text reader, which splits large files.

    Comments start with ``%`` and the first other line holds the sizes.  A
    symmetric matrix gives both directions.
    """
    lines = spark.read.text(path)
    head = lines.where("value LIKE '!%!%MatrixMarket%' ESCAPE '!'").first()
    if head is None or "coordinate" not in head[0]:
        raise ValueError("not a Matrix Market coordinate file")
    # the line of sizes is told by its place: an entry may read the same
    placed = spark.read.text(path).select("value", F.col("_metadata.file_path").alias("file"), F.monotonically_increasing_id().alias("place")).where("NOT startswith(value, '%') AND trim(value) <> ''")
    first = placed.orderBy("file", "place").first()
    sizes, parts = first["value"], F.split(F.trim("value"), r"\s+")
    body = placed.where((F.col("place") != first["place"]) | (F.col("file") != first["file"]))
    edges = body.select(parts[0].cast("bigint").alias("src"), parts[1].cast("bigint").alias("dst"))
    if len(sizes.split()) == 3 and "symmetric" in head[0]:
        edges = edges.union(edges.select("dst", "src")).distinct()
    return edges


class SyntheticEdges(DataSource):
    """``spark.read.format("synthetic_edges")``: option ``kind`` of ring, star, grid, path, uniform or skewed, with ``n`` and, where drawn, ``m`` and ``seed``."""

    @classmethod
    def name(cls) -> str:
        return "synthetic_edges"

    def schema(self) -> str:
        return EDGES

    def reader(self, schema) -> DataSourceReader:
        return _SyntheticReader(self.options)


class _SyntheticReader(DataSourceReader):
    def __init__(self, options) -> None:
        self.kind, self.n = options.get("kind", "ring"), int(options.get("n", 100))
        self.m, self.seed = int(options.get("m", 4 * self.n)), int(options.get("seed", 1))
        self.parts = int(options.get("partitions", 4))

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(k) for k in range(self.parts)]

    def read(self, partition: InputPartition) -> Iterator[tuple[int, int]]:
        n, draw = self.n, random.Random(self.seed * 1_000_003 + partition.value)
        for i in range(partition.value, self.m if self.kind in ("uniform", "skewed") else n, self.parts):
            if self.kind == "ring":
                yield i, (i + 1) % n
            elif self.kind == "path":
                if i + 1 < n:
                    yield i, i + 1
            elif self.kind == "star":
                if i:
                    yield i, 0
            elif self.kind == "grid":
                side = max(1, int(n**0.5))
                if (i + 1) % side and i + 1 < n:
                    yield i, i + 1
                if i + side < n:
                    yield i, i + side
            elif self.kind == "uniform":
                yield draw.randrange(n), draw.randrange(n)
            elif self.kind == "skewed":
                yield draw.randrange(n), int(n * draw.random() ** 3)
            else:
                raise ValueError("kind is one of ring, path, star, grid, uniform, skewed")


def synthetic(spark: SparkSession, kind: str, n: int, **options) -> DataFrame:
    spark.dataSource.register(SyntheticEdges)
    return spark.read.format("synthetic_edges").options(kind=kind, n=str(n), **{k: str(v) for k, v in options.items()}).load()
