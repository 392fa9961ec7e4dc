"""A Python data source of random sparse instances of any number, for load tests: spark.dataSource.register(SyntheticSparse)."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class Span(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class SyntheticSparse(DataSource):
    """Options: rows, dims, nonzeros, labels, partitions, seed."""

    @classmethod
    def name(cls) -> str:
        return "synthetic_sparse"

    def schema(self) -> str:
        return "instance_id long, feats array<int>, vals array<float>, labels array<int>"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


class _Reader(DataSourceReader):
    def __init__(self, options):
        get = lambda k, d: int(options.get(k, d))
        self.rows, self.dims, self.nonzeros = get("rows", 1000), get("dims", 10_000), get("nonzeros", 50)
        self.labels, self.parts, self.seed = get("labels", 100), get("partitions", 4), get("seed", 11)

    def partitions(self) -> list[InputPartition]:
        return [Span(self.rows * i // self.parts, self.rows * (i + 1) // self.parts) for i in range(self.parts)]

    def read(self, partition: Span) -> Iterator[tuple]:
        import numpy as np

        for i in range(partition.first, partition.last):
            rng = np.random.default_rng((self.seed, i))
            label = int(rng.integers(self.labels))
            # half of the features speak of the label
            own = np.random.default_rng((self.seed, 1, label)).choice(self.dims, self.nonzeros // 2, replace=False)
            feats = np.unique(np.concatenate([own, rng.choice(self.dims, self.nonzeros - len(own), replace=False)]))
            yield (i, feats.tolist(), [float(1 / np.sqrt(len(feats)))] * len(feats), [label])
