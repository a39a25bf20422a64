"""A batch data source of synthetic points: spark.dataSource.register(SyntheticPoints); spark.read.format("synthetic_points")."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class SyntheticPoints(DataSource):
    """Options: rows, d, clusters (0: uniform), seed, partitions."""

    @classmethod
    def name(cls) -> str:
        return "synthetic_points"

    def schema(self) -> str:
        return "id long, " + ", ".join(f"x{i} double" for i in range(int(self.options.get("d", "3"))))

    def reader(self, schema) -> DataSourceReader:
        return _Reader({k: int(self.options.get(k, v)) for k, v in (("rows", "1000"), ("d", "3"), ("clusters", "0"), ("seed", "0"), ("partitions", "8"))})


class _Reader(DataSourceReader):
    def __init__(self, options: dict[str, int]):
        self.options = options

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(i) for i in range(self.options["partitions"])]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        import numpy as np

        o, p = self.options, partition.value
        first, last = o["rows"] * p // o["partitions"], o["rows"] * (p + 1) // o["partitions"]
        rng = np.random.default_rng([o["seed"], p])
        x = rng.random((last - first, o["d"]))
        if o["clusters"]:
            centres = np.random.default_rng(o["seed"]).random((o["clusters"], o["d"]))
            x = np.clip(centres[rng.integers(o["clusters"], size=last - first)] + rng.normal(0, 0.05, x.shape), 0, 1)
        for i, row in enumerate(x, first):
            yield (i, *row.tolist())
