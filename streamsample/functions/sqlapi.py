"""The samplers from SQL: key functions, a sampling table function, a bottom-k aggregate."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StringType, StructType

from ..model import SamplerSpec
from ..operators.reservoir import sample_once


def register(spark: SparkSession) -> None:
    """``uniform_key(stream, seed, id)``, ``exp_key(stream, seed, id, w)`` as SQL expressions, which the optimiser sees into, and the table function ``sample_weighted``."""
    bits = "conv(substring(md5(concat(stream, ':', seed, ':', id)), 1, 13), 16, 10)"
    unit = f"(CAST({bits} AS BIGINT) + 1) / power(2D, 52)"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION uniform_key(stream STRING, seed INT, id STRING) RETURNS DOUBLE RETURN {unit}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION exp_key(stream STRING, seed INT, id STRING, w DOUBLE) RETURNS DOUBLE RETURN -ln({unit}) / w")
    spark.udtf.register("sample_weighted", _table_function())


def sample_table(spark: SparkSession, table: str, spec: SamplerSpec) -> DataFrame:
    """The same as a plan over a table or view by name: pruning reaches the scan."""
    return sample_once(spark.table(table), spec)


def _table_function():
    from pyspark.sql.functions import udtf

    class SampleWeighted:
        """A sample of k of each partition of its input table (item, w); keys are drawn from the seed and the item."""

        def __init__(self) -> None:
            self.rows: list[tuple[float, str, float]] = []
            self.k = 1

        def eval(self, row: Row, k: int, seed: int):
            import hashlib
            import heapq

            item, w = str(row[0]), row[1]
            self.k = k
            if w is None or not 0 < w < float("inf"):
                return
            u = (int(hashlib.md5(f"udtf:{seed}:{item}".encode()).hexdigest()[:13], 16) + 1) / 2.0**52
            entry = (np.log(u) / w, item, w)
            if len(self.rows) < k:
                heapq.heappush(self.rows, entry)
            elif entry > self.rows[0]:
                heapq.heapreplace(self.rows, entry)

        def terminate(self):
            for key, item, w in sorted(self.rows, reverse=True):
                yield item, float(w), float(-key)

    return udtf(SampleWeighted, returnType=StructType().add("item_id", StringType()).add("w", DoubleType()).add("key", DoubleType()))


def bottom_k_aggregate(k: int):
    """Aggregate expression: a group's k smallest (key, item_id) as an array. It gathers the group; for large groups use ``sample_by_group``."""
    return F.slice(F.array_sort(F.collect_list(F.struct("key", "item_id"))), 1, k)


def batch_keys(batches: Iterator[pd.DataFrame], seed: int) -> Iterator[pd.DataFrame]:
    """For ``mapInPandas``: exponential keys drawn, not derived from items; each partition draws its own."""
    rng = np.random.default_rng([seed, TaskContext.get().partitionId()])
    for b in batches:
        yield b.assign(key=-np.log(1 - rng.random(len(b))) / b["w"])


def arrow_exp_key(stream: str, seed: int):
    """``exp_key`` as a scalar function over Arrow arrays, for callers that have no expression; the expression is faster."""

    @F.udf(DoubleType(), useArrow=True)
    def key(item: str, w: float) -> float:
        import hashlib
        import math

        u = (int(hashlib.md5(f"{stream}:{seed}:{item}".encode()).hexdigest()[:13], 16) + 1) / 2.0**52
        return -math.log(u) / w

    return key


def bottom_k_udaf(k: int):
    """A grouped aggregate in pandas: the k-th smallest key of a group, or the largest one of fewer. It gathers the group, like any such function."""

    @F.pandas_udf(DoubleType())
    def kth(keys: pd.Series) -> float:
        return float(np.sort(keys.to_numpy())[: k][-1])

    return kth
