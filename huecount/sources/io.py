"""Readers and writers of edge lists, and an edge generator as a data source."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from huecount.operators.graph import DataGraph, simple_edges

EDGE_SCHEMA = "src long, dst long"


def read_edges(spark: SparkSession, path: str, kind: str = "parquet", name: str = "edges") -> DataGraph:
    """text: two tab-separated ids a line, comments after #; or csv, json, orc, parquet with src and dst."""
    if kind == "text":
        rows = spark.read.schema(EDGE_SCHEMA).csv(path, sep="\t", comment="#")
    elif kind == "csv":
        rows = spark.read.schema(EDGE_SCHEMA).csv(path, header=True)
    elif kind in ("json", "orc", "parquet"):
        rows = spark.read.schema(EDGE_SCHEMA).format(kind).load(path)
    else:
        raise ValueError(f"no reader for {kind!r}")
    return DataGraph(name, simple_edges(rows))


def write_edges(edges: DataFrame, path: str, kind: str = "parquet") -> None:
    if kind in ("text", "csv"):
        edges.select("src", "dst").write.mode("overwrite").csv(path, sep="\t" if kind == "text" else ",", header=kind == "csv")
    elif kind in ("json", "orc", "parquet"):
        edges.select("src", "dst").write.mode("overwrite").format(kind).save(path)
    else:
        raise ValueError(f"no writer for {kind!r}")


class _Range(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class RmatSource(DataSource):
    """spark.read.format('huecount_rmat').option('scale', 10).load(): raw edges, loops and repeats included."""

    @classmethod
    def name(cls) -> str:
        return "huecount_rmat"

    def schema(self) -> str:
        return EDGE_SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _RmatReader(int(self.options.get("scale", 10)), int(self.options.get("edgefactor", 16)), int(self.options.get("seed", 1)), int(self.options.get("partitions", 8)))


class _RmatReader(DataSourceReader):
    SHARES = (0.5, 0.1, 0.1, 0.3)

    def __init__(self, scale: int, factor: int, seed: int, parts: int):
        self.scale, self.edges, self.seed, self.parts = scale, factor << scale, seed, parts

    def partitions(self) -> list[InputPartition]:
        step = -(-self.edges // self.parts)
        return [_Range(i, min(i + step, self.edges)) for i in range(0, self.edges, step)]

    def read(self, partition):
        import numpy as np

        rng = np.random.default_rng([self.seed, partition.first])
        n = partition.last - partition.first
        src, dst = np.zeros(n, np.int64), np.zeros(n, np.int64)
        for _ in range(self.scale):
            quadrant = rng.choice(4, size=n, p=self.SHARES)
            src, dst = 2 * src + quadrant // 2, 2 * dst + quadrant % 2
        yield from zip(src.tolist(), dst.tolist(), strict=True)
