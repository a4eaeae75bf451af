"""A data source of synthetic planted-partition graphs: spark.read.format("planted_partition")."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class PlantedReader(DataSourceReader):
    def __init__(self, nodes: int, groups: int, degree: int, inside: float, parts: int, seed: int):
        self.nodes, self.groups, self.degree, self.inside, self.parts, self.seed = nodes, groups, degree, inside, parts, seed

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition: InputPartition) -> Iterator[tuple[int, int, int]]:
        import numpy as np

        for a in range(partition.value, self.nodes, self.parts):
            rng = np.random.default_rng((self.seed, a))
            group = a % self.groups
            for _ in range(max(1, self.degree // 2)):
                if rng.random() < self.inside:
                    b = int(rng.integers(0, (self.nodes - group + self.groups - 1) // self.groups)) * self.groups + group
                else:
                    b = int(rng.integers(0, self.nodes))
                if a != b:
                    yield a, b, group


class PlantedPartition(DataSource):
    """Options: nodes, groups, degree (mean), inside (share of edges inside a group), parts, seed. Columns a, b, group of a."""

    @classmethod
    def name(cls) -> str:
        return "planted_partition"

    def schema(self) -> str:
        return "a long, b long, group int"

    def reader(self, schema) -> PlantedReader:
        o = self.options
        return PlantedReader(int(o.get("nodes", 1000)), int(o.get("groups", 4)), int(o.get("degree", 10)), float(o.get("inside", 0.9)), int(o.get("parts", 4)), int(o.get("seed", 1)))


def register(spark: SparkSession) -> None:
    from attrgraph.session import workers

    workers(spark).dataSource.register(PlantedPartition)
