"""Edges and labels in files: usual formats, edge lists, and adjacency files through a Python data source."""

from __future__ import annotations

import os

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

EDGES = "src long, dst long, w long"


def write_edges(edges: DataFrame, path: str, kind: str = "parquet", mode: str = "overwrite", by: str | None = None) -> None:
    w = edges.write.mode(mode)
    (w.partitionBy(by) if by else w).format(kind).save(path)


def read_edges(spark: SparkSession, path: str, kind: str = "parquet", schema: str = EDGES) -> DataFrame:
    return spark.read.schema(schema).format(kind).load(path)


def labels_there_and_back(labels: DataFrame, path: str, kind: str) -> DataFrame:
    """Labels written in a format and read again by their schema."""
    write_edges(labels.select("id", "c"), path, kind)
    return read_edges(labels.sparkSession, path, kind, "id long, c long")


def write_bucketed(df: DataFrame, name: str, column: str, buckets: int = 16) -> DataFrame:
    """A table bucketed and sorted by a column, for joins without an exchange."""
    df.write.mode("overwrite").bucketBy(buckets, column).sortBy(column).saveAsTable(name)
    return df.sparkSession.table(name)


def read_edge_list(spark: SparkSession, path: str) -> DataFrame:
    """Two or three numbers a line, by white space; lines from # on are remarks; weight 1 if absent."""
    parts = F.split(F.trim("value"), r"\s+")
    rows = spark.read.text(path).where("not startswith(trim(value), '#') and trim(value) <> ''").select(parts.alias("p"))
    return rows.select(F.col("p")[0].cast("long").alias("src"), F.col("p")[1].cast("long").alias("dst"), F.coalesce(F.try_element_at("p", F.lit(3)).cast("long"), F.lit(1)).alias("w"))


class _Range(InputPartition):
    def __init__(self, path: str, start: int, end: int, first: int):
        self.path, self.start, self.end, self.first = path, start, end, first


class AdjacencyReader(DataSourceReader):
    """Reads a header "n m" and then one line of neighbours per node, from 1; byte ranges in parallel.

    The path must be readable by all workers as a file.
    """

    def __init__(self, options: dict):
        self.path, self.parts = options["path"], int(options.get("partitions", 4))

    def partitions(self):
        size, cuts = os.path.getsize(self.path), []
        with open(self.path, "rb") as f:
            head = len(f.readline())
            step = max(1, (size - head) // self.parts)
            at, line = head, 0
            while at < size:
                f.seek(min(size, at + step))
                f.readline()
                end = f.tell()
                f.seek(at)
                cuts.append(_Range(self.path, at, end, line))
                line += f.read(end - at).count(b"\n")
                at = end
        return cuts

    def read(self, part: _Range):
        with open(part.path, "rb") as f:
            f.seek(part.start)
            for i, line in enumerate(f.read(part.end - part.start).split(b"\n")):
                for v in line.split():
                    yield part.first + i, int(v) - 1, 1


class AdjacencySource(DataSource):
    @classmethod
    def name(cls):
        return "adjacency"

    def schema(self):
        return EDGES

    def reader(self, schema):
        return AdjacencyReader(self.options)


def write_adjacency(edges: DataFrame, path: str, n: int) -> None:
    """The adjacency format, through the driver: for exports of small graphs."""
    near: dict[int, list[int]] = {}
    for r in edges.select("src", "dst").toLocalIterator():
        near.setdefault(r.src, []).append(r.dst + 1)
    with open(path, "w") as f:
        f.write(f"{n} {sum(map(len, near.values())) // 2}\n")
        f.writelines(" ".join(map(str, sorted(near.get(i, [])))) + "\n" for i in range(n))
