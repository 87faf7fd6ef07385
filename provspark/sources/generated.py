"""A Python data source for generated graphs: ``spark.read.format("uncertain_graph").option("nodes", 20).load()``."""

from __future__ import annotations

import random
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class UncertainGraph(DataSource):
    """Edges src, dst, pi of a graph grown by preferential attachment; options ``nodes``, ``edges`` per node, ``seed``."""

    @classmethod
    def name(cls) -> str:
        return "uncertain_graph"

    def schema(self) -> str:
        return "src bigint, dst bigint, pi double"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(int(self.options.get("nodes", 10)), int(self.options.get("edges", 2)), int(self.options.get("seed", 0)))


class _Reader(DataSourceReader):
    def __init__(self, nodes: int, edges: int, seed: int):
        self.nodes, self.edges, self.seed = nodes, edges, seed

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(0)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        rng, ends = random.Random(self.seed), [0]
        for node in range(1, self.nodes):
            for other in sorted({rng.choice(ends) for _ in range(min(self.edges, node))}):
                yield node, other, 1 - rng.random()
                ends += [node, other]


def register(spark: SparkSession) -> None:
    spark.dataSource.register(UncertainGraph)
