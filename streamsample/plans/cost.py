"""Cost formulas: time as local work + beta * words + alpha * messages, insertions, and their bounds. Constants are fitted by the user.

Names: b items of a batch on a partition, c_local candidates on one, k sample size, p partitions, g longest run, d pivots, n items seen, alpha time to start a
message, beta time a word.
"""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


COLLECTIVES = ("broadcast", "reduce", "all_reduce", "gather")


def log2(x: float) -> float:
    return math.log2(max(x, 2.0))


def collective(kind: str, words: float, p: int, alpha: float, beta: float) -> float:
    """Time of one collective step; a gather brings the words of all partitions to one."""
    if kind not in COLLECTIVES:
        raise ValueError(kind)
    return beta * words * (p if kind == "gather" else 1) + alpha * log2(p)


def columns_collective(kind: Column, words: Column, p: Column, alpha: float, beta: float) -> Column:
    """``collective`` over a table of messages."""
    return beta * words * F.when(kind == "gather", p).otherwise(1) + alpha * F.log2(F.greatest(p, F.lit(2)))


def selection(kind: str, *, b_star: float, k: float, p: int, g: float, d: int, rank: float, alpha: float, beta: float) -> float:
    """Time to select a threshold."""
    lg, lp = log2(g), log2(p)
    return {
        "two_pivot": lambda: lg + alpha * lp,
        "approximate": lambda: lg + alpha * lp,
        "multi_pivot": lambda: d * lg + beta * d + alpha * lp,
        "pivot": lambda: log2(rank * p) * lg + alpha * log2(rank * p) ** 2,
        "combined": lambda: lg + (beta * rank + alpha) * lp,
        "incremental": lambda: log2(b_star + k) + beta * min(b_star, k) * lp + alpha * lp,
        "sparse": lambda: log2(b_star + k) + alpha * (b_star + lp),
        "unsorted": lambda: g + beta * min(math.sqrt(p) * (1 + math.log(max(g, 2), max(p, 2))), g) + alpha * lg,
    }[kind]()


def predict(method: str, *, b: float, b_star: float, k: float, p: int, alpha: float, beta: float, d: int = 8, select: str = "multi_pivot", weighted: bool = True) -> float:
    """Time of a batch. Weighted sampling looks at every weight, uniform sampling only at what enters."""
    fill = (b if weighted else 0.0) + (b_star + 1) * log2(b_star + k)
    if method == "gather":
        return (b if weighted else b_star) + beta * b_star * p + alpha * log2(p) + k + b_star * p + collective("broadcast", 1, p, alpha, beta)
    return fill + selection(select, b_star=b_star, k=k, p=p, g=b_star + k, d=d, rank=k, alpha=alpha, beta=beta)


def insert_probability(k: int, n_before: int) -> float:
    return 1.0 if n_before < k else k / n_before


def expected_insertions(n: int, k: int, p: int, b: int) -> float:
    """Expected insertions on a partition over all batches of b items on each: the exact sum, the first batches in full."""
    return sum(b * min(1.0, k / (i * p * b)) if i else float(b) for i in range(n // (p * b)))


def insertions_shape(n: int, k: int, p: int) -> float:
    """The bound's leading term."""
    return k / p * (1 + math.log(n / k))


def max_insertions_bound(n: int, k: int, p: int) -> float:
    """Bound on the expected insertions of the busiest partition, from that on a partition."""
    mean = insertions_shape(n, k, p)
    return mean + math.sqrt(2 * mean * math.log(p))


def monitoring_messages(n: int, k: int, p: int) -> float:
    """Messages of per-item synchronisation with a coordinator: one for each item accepted, and the new threshold to all sites."""
    return insertions_shape(n, k, 1) * (1 + p)


def columns_expected(n: Column, k: Column, p: Column, b: Column) -> Column:
    """``expected_insertions`` over a table of parameters."""
    last = F.floor(n / (p * b)) - 1  # the first batch has number 0
    batches = F.when(last >= 1, F.sequence(F.lit(1).cast("long"), last)).otherwise(F.array().cast("array<long>"))
    later = F.aggregate(batches, F.lit(0.0), lambda s, i: s + F.least(b.cast("double"), k.cast("double") / (i * p)))
    return F.when(last >= 0, b + later).otherwise(F.lit(0.0))


def columns_shape(n: Column, k: Column, p: Column) -> Column:
    return k / p * (1 + F.log(n / k))


def columns_max(n: Column, k: Column, p: Column) -> Column:
    mean = columns_shape(n, k, p)
    return mean + F.sqrt(2 * mean * F.log(p))
