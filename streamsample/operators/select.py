"""The item of global rank r over runs that lie in partitions: several ways, all of which exchange only a few numbers.

``runs`` has key and item_id; the order is (key, item_id) everywhere, so ranks are total. Each round is one or two aggregations with
partial results in the partitions; items stay where they are, but for ``combined_select``, which spreads the few it keeps, and for the ends
that the driver finishes once no more than ``finish`` items are left between two known keys.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.variates import coin

Bound = tuple[float, str]
#: Rows that the driver takes at most to find the last of them.
FEW = 4096


@dataclass
class Selected:
    key: float
    item_id: str
    rank: int
    rounds: int = 0
    pivots: int = 0
    jobs: int = 0
    rows_moved: int = 0


def up_to(bound: Bound) -> Column:
    """Rows at most (key, item_id)."""
    key, item = bound
    return (F.col("key") < F.lit(key)) | ((F.col("key") == F.lit(key)) & (F.col("item_id") <= F.lit(item)))


def within(low: Bound | None, high: Bound | None) -> Column:
    """Rows above ``low`` and at most ``high``."""
    out = F.lit(True)
    if low is not None:
        out = out & ~up_to(low)
    return out & up_to(high) if high is not None else out


def _checked(low: int, high: int, size: int) -> None:
    if not 1 <= low <= high <= size:
        raise ValueError(f"ranks {low}..{high} are not within 1..{size}")


def _fetch(rows: DataFrame, rank: int, out: Selected, below: int) -> Selected:
    """Finish on the driver: the few rows, in order."""
    got = sorted((r["key"], r["item_id"]) for r in rows.select("key", "item_id").collect())
    out.jobs, out.rows_moved = out.jobs + 1, out.rows_moved + len(got)
    out.key, out.item_id = got[rank - 1]
    out.rank = below + rank
    return out


def _side(rank: int, inside: int) -> tuple[bool, float]:
    """(whether pivots come from the low end, the chance that a row is taken for one)."""
    from_low = 2 * rank <= inside + 1
    return from_low, 1 / rank if from_low else 1 / (inside - rank + 1)


def pivot_select(runs: DataFrame, low: int, high: int, size: int, d: int = 1, seed: int = 0, finish: int = 1, shrink: bool = False) -> Selected:
    """An item of any rank in low..high; exact if they are equal. ``d`` pivots a round.

    A pivot is the smallest of a random part of the items, each taken with chance 1 / rank, or the largest of one taken from the other
    end if the rank is nearer to that. With several pivots a round is two jobs, one that draws them and one that counts the rows up to each. With one pivot it is
    one job, which counts and draws ahead on both sides (``_ahead``). ``shrink`` keeps the rows still in question for the next round, for
    unsorted or uncached input.
    """
    _checked(low, high, size)
    out = Selected(math.nan, "", 0)
    bottom, top, below, inside = None, None, 0, size  # the bracket (bottom, top], rows up to bottom, rows in it
    rows, draw, held, drawn = runs.select("key", "item_id"), 0, [], None
    try:
        while True:
            a, b = low - below, high - below
            if inside <= finish or inside == 1:
                rank = max(1, min(a + (b - a) // 2, inside))
                return _fetch(rows.where(within(bottom, top)), rank, out, below)
            left, draw = rows.where(within(bottom, top)), draw + 1
            from_low, chance = _side((a + b) // 2, inside)
            ahead = None
            if d == 1:
                pivots = [] if drawn is None else _drawn(drawn, from_low, chance)
                counts, ahead = _ahead(left, pivots, seed, draw)
            else:
                spot, pick = F.struct("key", "item_id"), F.min if from_low else F.max
                got = left.agg(*[pick(F.when(coin(F.col("item_id"), seed, draw, j) < chance, spot)).alias(f"p{j}") for j in range(d)]).first()
                pivots = sorted({(p["key"], p["item_id"]) for p in got if p is not None})
                out.jobs += 1
                counts = left.agg(*[F.count_if(up_to(p)).alias(f"c{j}") for j, p in enumerate(pivots)]).first() if pivots else []
            out.jobs += 1 if d == 1 or pivots else 0
            if pivots:
                out.rounds, out.pivots = out.rounds + 1, out.pivots + d
            for p, c in zip(pivots, counts, strict=True):
                if a <= c <= b:
                    out.key, out.item_id, out.rank = p[0], p[1], below + c
                    return out
            gap = sum(c < a for c in counts)  # the gap after so many pivots holds the rank
            bounds, ends = [bottom, *pivots, top], [0, *counts, inside]
            bottom, top = bounds[gap], bounds[gap + 1]
            below, inside = below + ends[gap], ends[gap + 1] - ends[gap]
            drawn = ahead[gap] if ahead else None
            if shrink and pivots:
                rows = rows.where(within(bottom, top)).persist()
                held.append(rows)
    finally:
        for x in held:
            x.unpersist()


Level = dict[int, tuple[Bound, Bound]]


def _ahead(rows: DataFrame, pivots: list[Bound], seed: int, draw: int) -> tuple[list[int], list[Level]]:
    """(rows up to the pivot, if there is one; on each side of it, by level, the smallest and the largest row), in one job.

    A row's level is how often its coin can be halved: half of all rows reach level 1, a quarter level 2. Which chance the next pivot needs is known only once
    the rows are counted, but then it is the first or last row of some level or a higher one.
    """
    gap = F.lit(0) if not pivots else F.when(up_to(pivots[0]), 0).otherwise(1)
    level = F.least(F.lit(50), F.floor(-F.log2(coin(F.col("item_id"), seed, draw, 0) + F.lit(2.0**-53)))).cast("int")
    spot = F.struct("key", "item_id")
    got = rows.groupBy(gap.alias("gap"), level.alias("level")).agg(F.count(F.lit(1)).alias("n"), F.min(spot).alias("low"), F.max(spot).alias("high")).collect()
    sides: list[Level] = [{} for _ in range(len(pivots) + 1)]
    for r in got:
        sides[r["gap"]][r["level"]] = (tuple(r["low"]), tuple(r["high"]))
    return [sum(r["n"] for r in got if r["gap"] == 0)] * len(pivots), sides


def _drawn(levels: Level, from_low: bool, chance: float) -> list[Bound]:
    """The pivot that the level nearest to the chance gives; none if no row reached it."""
    need = round(-math.log2(chance))
    reached = [spots for level, spots in levels.items() if level >= need]
    return [min(s[0] for s in reached) if from_low else max(s[1] for s in reached)] if reached else []


def unsorted_select(runs: DataFrame, rank: int, size: int, d: int = 8, seed: int = 0) -> Selected:
    """For input in no order: ranks are counted over the rows that are left, and these shrink each round."""
    return pivot_select(runs, rank, rank, size, d, seed, finish=64, shrink=True)


def two_pivot_select(runs: DataFrame, rank: int, size: int, p: int = 8, seed: int = 0, finish: int = 4096) -> Selected:
    """For keys spread at random over partitions: two keys of a sorted sample bracket the rank, and few rows lie between them."""
    _checked(rank, rank, size)
    out = Selected(math.nan, "", 0)
    if size <= 64:
        return _fetch(runs, rank, out, 0)
    want = max(64, 4 * math.isqrt(p))
    got = runs.where(coin(F.col("item_id"), seed, 101) < want / size).select("key", "item_id").limit(8 * want).collect()
    sample = sorted((r["key"], r["item_id"]) for r in got)
    out.jobs, out.rounds, out.pivots, out.rows_moved = 1, 1, 2, len(sample)
    spot, margin = rank / size * len(sample), 2 * math.sqrt(len(sample)) / 2 + 1
    lo, hi = math.floor(spot - margin), math.ceil(spot + margin)
    bottom = sample[lo] if 0 <= lo < len(sample) else None
    top = sample[hi] if 0 <= hi < len(sample) else None
    first = F.count_if(up_to(bottom)) if bottom else F.lit(0)
    second = F.count_if(up_to(top)) if top else F.count(F.lit(1))
    below, upto = runs.agg(first.alias("a"), second.alias("b")).first()
    out.jobs += 1
    if below < rank <= upto and upto - below <= finish:
        return _fetch(runs.where(within(bottom, top)), rank - below, out, below)
    part = runs.where(within(bottom, top)) if below < rank <= upto else runs
    skip, left = (below, upto - below) if below < rank <= upto else (0, size)
    rest = pivot_select(part, rank - skip, rank - skip, left, 8, seed + 1, finish=min(finish, 256))
    return Selected(rest.key, rest.item_id, rank, out.rounds + rest.rounds, out.pivots + rest.pivots, out.jobs + rest.jobs, out.rows_moved + rest.rows_moved)


def combined_select(runs: DataFrame, rank: int, size: int, p: int = 8, seed: int = 0) -> Selected:
    """Any rank in rank..2*rank first; what is up to it is spread at random; then two pivots."""
    if 2 * rank >= size:
        return two_pivot_select(runs.repartition(p, F.xxhash64("item_id")), rank, size, p, seed)
    rough = pivot_select(runs, rank, 2 * rank, size, 1, seed, finish=256)
    near = runs.where(up_to((rough.key, rough.item_id))).select("key", "item_id").repartition(p, F.xxhash64("item_id"))
    fine = two_pivot_select(near, rank, rough.rank, p, seed + 1)
    return Selected(fine.key, fine.item_id, rank, rough.rounds + fine.rounds, rough.pivots + fine.pivots, rough.jobs + fine.jobs, fine.rows_moved + rough.rank)


def incremental_select(runs: DataFrame, rank: int, size: int, new: int, p: int = 8, seed: int = 0) -> Selected:
    """The combined way where rows are spread at random as they come in, so that only the ``new`` ones have moved.

    Up to ``rank`` new rows the rough step is left out: at most twice the rank is there anyway. Beyond, it comes first, and what it leaves is spread already.
    """
    if new <= rank or 2 * rank >= size:
        return two_pivot_select(runs, rank, size, p, seed)
    rough = pivot_select(runs, rank, 2 * rank, size, 1, seed, finish=256)
    fine = two_pivot_select(runs.where(up_to((rough.key, rough.item_id))), rank, rough.rank, p, seed + 1)
    return Selected(fine.key, fine.item_id, rank, rough.rounds + fine.rounds, rough.pivots + fine.pivots, rough.jobs + fine.jobs, fine.rows_moved)


def tail_select(runs: DataFrame, rank: int, size: int, budget: int = 100_000) -> Selected:
    """Rank k of k + c items by fetching the c + 1 largest, or the k smallest if those are fewer; pivots beyond the budget. One job."""
    _checked(rank, rank, size)
    n_top = size - rank + 1
    if min(rank, n_top) > budget:
        return pivot_select(runs, rank, rank, size, 32, finish=256)
    want = min(rank, n_top)
    out = Selected(math.nan, "", rank, jobs=1, rows_moved=want)
    order = [F.desc("key"), F.desc("item_id")] if n_top <= rank else ["key", "item_id"]
    ends = runs.select("key", "item_id").orderBy(*order).limit(want)
    # few rows come as they are, which is one job without an exchange; of more, only the last one
    last = ends.collect()[-1] if want <= FEW else ends.agg((F.min if n_top <= rank else F.max)(F.struct("key", "item_id"))).first()[0]
    out.key, out.item_id = last["key"], last["item_id"]
    return out


def sort_select(runs: DataFrame, rank: int, size: int) -> Selected:
    """Brute force: sort all."""
    _checked(rank, rank, size)
    row = runs.select("key", "item_id").orderBy("key", "item_id").offset(rank - 1).limit(1).first()
    return Selected(row["key"], row["item_id"], rank, 1, 0, 1, size)


def local_kth(keys: np.ndarray, ids: np.ndarray, k: int) -> Bound:
    """At one place: quickselect on keys, ids only among ties."""
    kth = np.partition(keys, k - 1)[k - 1]
    ties = np.sort(ids[keys == kth].astype(str))
    return float(kth), str(ties[k - 1 - int((keys < kth).sum())])


def select(name: str, runs: DataFrame, rank: int, size: int, d: int = 8, p: int = 8, seed: int = 0, finish: int = 256) -> Selected:
    if name == "pivot":
        return pivot_select(runs, rank, rank, size, d, seed, finish)
    if name == "two_pivot":
        return two_pivot_select(runs, rank, size, p, seed)
    if name == "combined":
        return combined_select(runs, rank, size, p, seed)
    if name == "unsorted":
        return unsorted_select(runs, rank, size, d, seed)
    return sort_select(runs, rank, size) if name == "sort" else tail_select(runs, rank, size)
