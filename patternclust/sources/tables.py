"""Tables, graph files and sinks.

Graph text files are transactions: ``t # id`` opens a graph, ``v i label`` and ``e i j label``
add to it. Files are split at ``t`` lines, so large ones are read in parallel.
"""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..model import GRAPH_SCHEMA, from_text, to_text


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_graph_text(spark: SparkSession, path: str) -> DataFrame:
    """Compact graphs from transaction text; blocks that hold no graph are left out."""
    blocks = spark.read.option("lineSep", "t # ").text(path).where(F.trim("value") != "")
    return from_text(blocks)


def write_graph_text(graphs: DataFrame, path: str) -> None:
    to_text(graphs).write.text(path)


def read_graph_json(spark: SparkSession, path: str) -> DataFrame:
    """One compact graph a line."""
    return spark.read.schema(GRAPH_SCHEMA).json(path)


def read_edge_lists(spark: SparkSession, vertices: str, edges: str) -> tuple[DataFrame, DataFrame]:
    """CSV files with headers: vertices g,v,l and edges g,a,b,l."""
    v = spark.read.option("header", True).schema("g bigint, v string, l string").csv(vertices)
    return v, spark.read.option("header", True).schema("g bigint, a string, b string, l string").csv(edges)


def write_assignment(assignment: DataFrame, path: str, buckets: int = 64) -> None:
    """Parquet in folders by cluster bucket, so that split and merge read only what they need."""
    assignment.withColumn("bucket", F.pmod("cluster_id", F.lit(buckets))).write.partitionBy("bucket").parquet(path)


def write_model(model: dict, path: str) -> None:
    with open(path, "w") as f:
        json.dump(model, f, indent=1, sort_keys=True)


class _Range(InputPartition):
    def __init__(self, low: int, high: int):
        self.low, self.high = low, high


class PlantedGraphs(DataSource):
    """``spark.read.format("planted_graphs").option("n", ...)``: the synthetic corpus, made where it is read."""

    @classmethod
    def name(cls):
        return "planted_graphs"

    def schema(self):
        return GRAPH_SCHEMA

    def reader(self, schema):
        return _PlantedReader(self.options)


class _PlantedReader(DataSourceReader):
    def __init__(self, options):
        self.n, self.parts = int(options.get("n", 1000)), int(options.get("partitions", 8))

    def partitions(self):
        step = -(-self.n // self.parts)
        return [_Range(k, min(self.n, k + step)) for k in range(0, self.n, step)]

    def read(self, partition):
        from ..planted import planted_graph

        for key in range(partition.low, partition.high):
            g = planted_graph(key)
            yield (key, g.labels, *g.edge_columns())
