"""A data source of hashed random models: ``spark.read.format("random_model").option("trials", 20)``."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..hashing import uniform_value


class RandomModelSource(DataSource):
    """Rows trial, src, dst, theta; options: trials, n, p, coupling (repulsive, mixed, attractive), strength, seed."""

    @classmethod
    def name(cls) -> str:
        return "random_model"

    def schema(self) -> str:
        return "trial long, src long, dst long, theta double"

    def reader(self, schema) -> DataSourceReader:
        return RandomModelReader(dict(self.options))


class RandomModelReader(DataSourceReader):
    def __init__(self, options: dict[str, str]):
        self.options = options

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(t) for t in range(int(self.options.get("trials", 1)))]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        o, trial = self.options, partition.value
        n, p, strength, seed = int(o.get("n", 24)), float(o.get("p", 0.3)), float(o.get("strength", 1)), int(o.get("seed", 1))
        low, high = {"repulsive": (-strength, 0.0), "mixed": (-strength, strength), "attractive": (0.0, strength)}[o.get("coupling", "mixed")]
        for i in range(n):
            for j in range(i + 1, n):
                if uniform_value(seed, trial, i, j) < p:
                    yield trial, i, j, low + (high - low) * uniform_value(2, trial, i, j)
