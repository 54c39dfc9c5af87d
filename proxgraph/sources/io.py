"""Readers and writers of edge tables, a Python data source for text edge lists, and an adjacency store."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..operators.graph import Graph
from ..session import ship

EDGES = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType())])


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", src: str = "src", dst: str = "dst", **options) -> DataFrame:
    """(src, dst) from Parquet, ORC, CSV, JSON, or text with two white-space separated numbers a line."""
    if fmt == "text":
        parts = F.split(F.trim("value"), r"\s+")
        lines = spark.read.text(path).where(~F.col("value").rlike(r"^\s*(#|%|$)"))
        return lines.select(parts[0].cast("long").alias("src"), parts[1].cast("long").alias("dst"))
    reader = spark.read.format(fmt).options(**options)
    if fmt in ("csv", "json"):
        reader = reader.schema(f"{src} long, {dst} long")
    return reader.load(path).select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst"))


def from_table(spark: SparkSession, name: str, src: str = "src", dst: str = "dst") -> DataFrame:
    return spark.table(name).select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst"))


class _Lines(InputPartition):
    def __init__(self, path: str, begin: int, end: int):
        self.path, self.begin, self.end = path, begin, end


class _EdgeListReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.size = options["path"], int(options.get("split", 32 << 20))

    def partitions(self) -> list[_Lines]:
        import glob
        import os

        out = []
        for p in sorted(glob.glob(self.path)):
            total = os.path.getsize(p)
            out += [_Lines(p, a, min(a + self.size, total)) for a in range(0, total, self.size)]
        return out

    def read(self, part: _Lines):
        """The lines that begin in [begin, end)."""
        with open(part.path, "rb") as f:
            f.seek(max(0, part.begin - 1))
            if part.begin:
                f.readline()
            while f.tell() < part.end and (line := f.readline()):
                words = line.split()
                if words and not words[0].startswith((b"#", b"%")):
                    yield int(words[0]), int(words[1])


class EdgeListSource(DataSource):
    """``spark.read.format("edgelist").load(path)``: text edge lists on a mounted file system, split by size."""

    @classmethod
    def name(cls) -> str:
        return "edgelist"

    def schema(self) -> T.StructType:
        return EDGES

    def reader(self, schema: T.StructType) -> DataSourceReader:
        return _EdgeListReader(self.options)


def register(spark: SparkSession) -> None:
    ship(spark)
    spark.dataSource.register(EdgeListSource)


def write_adjacency(graph: Graph, path: str, buckets: int = 64) -> None:
    """Arcs by bucket of their source, sorted inside: a step that joins on (bucket, src) reads only the buckets it needs."""
    arcs = graph.arcs.withColumn("bucket", F.pmod(F.col("src"), F.lit(buckets)).cast("int"))
    arcs.repartition(buckets, "bucket").sortWithinPartitions("bucket", "src", "idx").write.partitionBy("bucket").mode("overwrite").parquet(path)


def read_adjacency(spark: SparkSession, path: str, directed: bool) -> Graph:
    return Graph(spark.read.parquet(path).select("src", "dst", "idx", "out_deg", "dst_deg"), directed)


def neighbours(spark: SparkSession, path: str, frontier: DataFrame, buckets: int = 64) -> DataFrame:
    """Arcs out of the nodes of ``frontier`` (id); files of untouched buckets are pruned at run time."""
    keys = frontier.select(F.col("id").alias("src"), F.pmod("id", F.lit(buckets)).cast("int").alias("bucket"))
    return spark.read.parquet(path).join(keys, ["bucket", "src"]).select("src", "dst", "idx", "out_deg", "dst_deg")


def write_scores(scores: DataFrame, path: str) -> None:
    """Overwrites, so a repeated run leaves the same table."""
    scores.write.mode("overwrite").parquet(path)
