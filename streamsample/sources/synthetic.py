"""A seeded weighted stream as a data source: ``spark.read.format("weighted_items")`` and ``readStream`` alike."""

from __future__ import annotations

import numpy as np
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

SCHEMA = "item_id long, batch_no long, pe int, w double"


def weights(kind: str, n: int, seed: int, batch_no: int, pe: int) -> np.ndarray:
    """uniform: 0 to 100. drift: normal around batch number plus partition, at least 0.01."""
    rng = np.random.default_rng([seed, batch_no, pe])
    return 100 * (1 - rng.random(n)) if kind == "uniform" else np.maximum(0.01, rng.normal(batch_no + pe, 1, n))


class WeightedItems(DataSource):
    """Options: n items a partition and batch, p partitions, batches, seed, kind."""

    @classmethod
    def name(cls) -> str:
        return "weighted_items"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:
        return _StreamReader(self.options)


def _settings(options) -> tuple[int, int, int, int, str]:
    return int(options.get("n", 1000)), int(options.get("p", 4)), int(options.get("batches", 1)), int(options.get("seed", 7)), options.get("kind", "uniform")


def _rows(n: int, p: int, seed: int, kind: str, batch_no: int, pe: int):
    for i, w in enumerate(weights(kind, n, seed, batch_no, pe).tolist()):
        yield ((batch_no * p + pe) * n + i, batch_no, pe, w)


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.n, self.p, self.batches, self.seed, self.kind = _settings(options)

    def partitions(self) -> list[InputPartition]:
        return [InputPartition((b, pe)) for b in range(self.batches) for pe in range(self.p)]

    def read(self, partition: InputPartition):
        yield from _rows(self.n, self.p, self.seed, self.kind, *partition.value)


class _StreamReader(SimpleDataSourceStreamReader):
    def __init__(self, options):
        self.n, self.p, self.batches, self.seed, self.kind = _settings(options)

    def initialOffset(self) -> dict:
        return {"batch": 0}

    def read(self, start: dict):
        b = start["batch"]
        if b >= self.batches:
            return iter([]), start
        return (r for pe in range(self.p) for r in _rows(self.n, self.p, self.seed, self.kind, b, pe)), {"batch": b + 1}

    def readBetweenOffsets(self, start: dict, end: dict):
        return (r for b in range(start["batch"], end["batch"]) for pe in range(self.p) for r in _rows(self.n, self.p, self.seed, self.kind, b, pe))
