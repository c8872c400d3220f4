"""Random keys as column expressions.

A variate is a function of (stream, seed, purpose, item), so that a task that runs again, another batch split or another engine
sees the same one. The stream's name is part of it: equal ids of different tables must not get equal variates.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F

GRID = 2.0**52


def item_id(cols: Sequence[str]) -> Column:
    return F.concat_ws("|", *[F.col(c).cast("string") for c in cols])


def _digest(item: Column, stream: str, seed: int, purpose: str) -> Column:
    return F.md5(F.concat(F.lit(f"{stream}:{seed}:{purpose}{':' if purpose else ''}"), item))


def _bits(digest: Column, start: int) -> Column:
    return F.conv(F.substring(digest, start, 13), 16, 10).cast("long")


def uniform_key(item: Column, stream: str, seed: int, purpose: str = "") -> Column:
    """In (0, 1], on a grid of 2**-52."""
    return (_bits(_digest(item, stream, seed, purpose), 1) + 1).cast("double") / F.lit(GRID)


def power_key(u: Column, w: Column) -> Column:
    """The k largest form a weighted sample. Heavy weights crowd near 1."""
    return F.pow(u, 1 / w)


def exp_key(u: Column, w: Column) -> Column:
    """Exponential with rate w; the k smallest form a weighted sample. Minus the logarithm of the power key."""
    return -F.log(u) / w


def deep_exp_key(item: Column, w: Column, stream: str, seed: int, purpose: str = "") -> Column:
    """As ``exp_key`` from 104 bits, fine-grained near 0: for more items than 52 bits tell apart."""
    digest = _digest(item, stream, seed, purpose)
    deep = _bits(digest, 1).cast("double") / F.lit(GRID) + _bits(digest, 14).cast("double") / F.lit(GRID) / F.lit(GRID)
    return -F.log1p(-deep) / w


def exp_key_below(u: Column, w: Column, threshold: float) -> Column:
    """Exponential with rate w, given that it is below the threshold; keeps its digits where threshold * w is tiny."""
    return -F.log1p((1 - u) * F.expm1(-w * F.lit(float(threshold)))) / w


def uniform_key_below(u: Column, threshold: float) -> Column:
    return u * F.lit(float(threshold))


def included(u: Column, w: Column, threshold: float) -> Column:
    """Whether an item's key, not yet drawn, will be below the threshold."""
    return u < -F.expm1(-w * F.lit(float(threshold)))


def valid_weight(w: Column) -> Column:
    """Finite and above 0; nulls, NaN, infinities, zero and negative weights are rejected."""
    return F.coalesce((w > 0) & (w < F.lit(float("inf"))) & ~F.isnan(w), F.lit(False))


def coin(item: Column, *salt: int) -> Column:
    """A variate in [0, 1) for draws that need no replay outside Spark."""
    return F.shiftrightunsigned(F.xxhash64(item, *[F.lit(s) for s in salt]), 11).cast("double") / F.lit(2.0**53)
