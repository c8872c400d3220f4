"""A local reservoir as a sorted run: numpy arrays inside a partition, windows over a ``pe`` column in tables.

Inserts come in bulk once a batch, so a run is merged rather than kept as a tree.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def insert_many(run: tuple[np.ndarray, np.ndarray], keys: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    k, i = np.concatenate([run[0], keys]), np.concatenate([run[1], ids])
    order = np.lexsort((i, k))
    return k[order], i[order]


def rank(run: tuple[np.ndarray, np.ndarray], key: float) -> int:
    """Items with smaller keys."""
    return int(np.searchsorted(run[0], key, side="left"))


def kth(run: tuple[np.ndarray, np.ndarray], j: int) -> tuple[float, object]:
    """The j-th smallest, from 1."""
    return run[0][j - 1], run[1][j - 1]


def split(run: tuple[np.ndarray, np.ndarray], key: float):
    """(items up to the key, items above it)."""
    at = int(np.searchsorted(run[0], key, side="right"))
    return (run[0][:at], run[1][:at]), (run[0][at:], run[1][at:])


def join(low: tuple[np.ndarray, np.ndarray], high: tuple[np.ndarray, np.ndarray]):
    """Two runs as one; a plain concatenation where their ranges don't overlap."""
    if not len(low[0]) or not len(high[0]) or low[0][-1] < high[0][0]:
        return np.concatenate([low[0], high[0]]), np.concatenate([low[1], high[1]])
    return insert_many(low, *high)


def cap_limits(k: int) -> tuple[int, int]:
    """(local batch size from which the first batch is capped, run length at which it is cut back to k). 1.5, 500, 1.1, 250."""
    return max(-(-3 * k // 2), k + 500), max(-(-11 * k // 10), k + 250)


class FirstBatch:
    """The local run of a first batch, kept near k items by a local threshold; never cut below k."""

    def __init__(self, k: int):
        self.k, self.most = k, cap_limits(k)[1]
        self.keys, self.ids, self.threshold = np.zeros(0), np.zeros(0, dtype=object), np.inf

    def add(self, keys: np.ndarray, ids: np.ndarray) -> None:
        step = max(1, self.most - self.k)
        for at in range(0, len(keys), step):
            part = keys[at : at + step]
            low = part < self.threshold
            self.keys, self.ids = np.concatenate([self.keys, part[low]]), np.concatenate([self.ids, ids[at : at + step][low]])
            if len(self.keys) > self.most:
                keep = np.argpartition(self.keys, self.k - 1)[: self.k]
                self.keys, self.ids = self.keys[keep], self.ids[keep]
                self.threshold = float(self.keys.max())


def in_order(part: str | None = "pe"):
    w = Window.partitionBy(part) if part else Window.partitionBy(F.lit(0))
    return w.orderBy("key", "item_id")


def ranked(runs: DataFrame) -> DataFrame:
    """Each item's place within its own run, from 1."""
    return runs.withColumn("place", F.row_number().over(in_order()))


def local_rank(runs: DataFrame, key: float) -> DataFrame:
    return runs.groupBy("pe").agg(F.count_if(F.col("key") < F.lit(key)).alias("rank"))


def local_kth(runs: DataFrame, j: int) -> DataFrame:
    return ranked(runs).where(F.col("place") == j).drop("place")


def local_split(runs: DataFrame, key: Column) -> DataFrame:
    """Which side of a key each item is on."""
    return runs.withColumn("low", F.col("key") <= key)


def local_neighbours(runs: DataFrame) -> DataFrame:
    return runs.withColumn("before", F.lag("item_id").over(in_order())).withColumn("after", F.lead("item_id").over(in_order()))


def local_smallest(runs: DataFrame, k: int) -> DataFrame:
    """The k smallest of each run; Spark keeps k rows a group in the first step already."""
    return ranked(runs).where(F.col("place") <= k).drop("place")
