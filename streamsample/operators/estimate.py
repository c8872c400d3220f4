"""What a sample tells about its stream, and measures of its accuracy."""

from __future__ import annotations

from collections.abc import Sequence
from itertools import permutations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def inclusion_feasibility(rows: DataFrame, k: int) -> DataFrame:
    """Items whose share k * w / W exceeds 1, so that no sampler could include them in proportion to their weights."""
    total = rows.agg(F.sum("w").alias("total"))
    return rows.crossJoin(F.broadcast(total)).where(F.col("w") * k > F.col("total")).withColumn("share", F.col("w") * k / F.col("total"))


def adjusted_weight(threshold: float) -> Column:
    """What one sampled row stands for: its weight over its chance to lie strictly below the threshold."""
    return F.col("w") / -F.expm1(-F.col("w") * F.lit(threshold))


def subset_sum(sample: DataFrame, threshold: float, where: Column | None = None) -> DataFrame:
    """Unbiased total weight of the rows that fulfil ``where``, from the rows strictly below the threshold; the row at it is left out."""
    rows = sample.where(F.col("key") < threshold)
    rows = rows if where is None else rows.where(where)
    return rows.agg(F.coalesce(F.sum(adjusted_weight(threshold)), F.lit(0.0)).alias("estimate"), F.count(F.lit(1)).alias("rows_used"))


def heavy_hitters(sample: DataFrame, threshold: float, group: str, share: float) -> DataFrame:
    """Groups that hold at least ``share`` of the estimated total weight."""
    by = sample.where(F.col("key") < threshold).groupBy(group).agg(F.sum(adjusted_weight(threshold)).alias("estimate"))
    total = by.agg(F.sum("estimate").alias("total"))
    return by.crossJoin(F.broadcast(total)).withColumn("share", F.col("estimate") / F.col("total")).where(F.col("share") >= share).drop("total")


def count_track(sample: DataFrame, threshold: float) -> DataFrame:
    """Number of items seen, from a uniform sample: each row strictly below the threshold stands for 1 / threshold items."""
    return sample.where(F.col("key") < threshold).agg((F.count(F.lit(1)) / F.lit(threshold)).alias("estimate"))


def relative_error(estimate: float, true: float) -> float:
    return abs(estimate - true) / abs(true) if true else abs(estimate)


def ordered_law(weights: Sequence[float], k: int) -> dict[tuple[int, ...], float]:
    """Chance of each ordered sample by successive draws without replacement."""
    law, total = {}, sum(weights)
    for order in permutations(range(len(weights)), k):
        left, chance = total, 1.0
        for i in order:
            chance, left = chance * weights[i] / left, left - weights[i]
        law[order] = chance
    return law


def inclusion_law(weights: Sequence[float], k: int) -> np.ndarray:
    out = np.zeros(len(weights))
    for order, chance in ordered_law(weights, k).items():
        out[list(order)] += chance
    return out


def largest_z(counts: np.ndarray, chances: np.ndarray, trials: int) -> float:
    """How far counts are from what their chances promise, in standard deviations; the largest."""
    return float(np.max(np.abs(counts - trials * chances) / np.sqrt(np.maximum(trials * chances * (1 - chances), 1e-12))))
