"""Jumps: how much weight, or how many items, to pass over before the next item enters. Numpy kernels for one partition or block.

A jump that the end of the input cuts off is dropped: each unit of weight is as likely as any other to bring an item in, wherever
a walk began. So partitions, files and blocks can each start afresh.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass

import numpy as np


def unit(rng: np.random.Generator) -> float:
    """In (0, 1]."""
    return 1.0 - rng.random()


def weight_jump(threshold: float, rng: np.random.Generator) -> float:
    """Weight to pass over: exponential, its rate the threshold."""
    return -np.log(unit(rng)) / threshold


def power_jump(power_threshold: float, rng: np.random.Generator) -> float:
    """The same where keys are powers and the threshold is the smallest kept one."""
    return np.log(unit(rng)) / np.log(power_threshold)


def item_jump(threshold: float, rng: np.random.Generator) -> int:
    """Items to pass over: geometric, success the threshold."""
    return 0 if threshold >= 1 else int(np.floor(np.log(unit(rng)) / np.log1p(-threshold)))


def key_below(w: float, threshold: float, rng: np.random.Generator) -> float:
    return -np.log1p((1 - unit(rng)) * np.expm1(-threshold * w)) / w


@dataclass
class Walk:
    positions: np.ndarray
    keys: np.ndarray
    examined: int = 0
    skipped_blocks: int = 0


def weighted_fill(weights: np.ndarray, threshold: float, rng: np.random.Generator, block: int = 32, first: float | None = None) -> Walk:
    """The items that enter under a fixed threshold, with their keys. Whole blocks are passed over by their sums; only in blocks that a jump ends in are weights
    looked at one by one (``examined``).

    ``first``: the first jump, if it is already drawn.
    """
    n = len(weights)
    if not n:
        return Walk(np.zeros(0, dtype=np.int64), np.zeros(0))
    ends = np.cumsum(np.add.reduceat(weights, np.arange(0, n, block)))
    positions, keys, examined = [], [], 0
    target, opened, inside = weight_jump(threshold, rng) if first is None else first, -1, None
    while (b := int(np.searchsorted(ends, target, side="left"))) < len(ends):
        if b != opened:
            part = weights[b * block : (b + 1) * block]
            before = float(ends[b - 1]) if b else 0.0
            opened, inside, examined = b, before + np.cumsum(part), examined + len(part)
            inside[-1] = ends[b]  # the same sum, added up in another order
        at = int(np.searchsorted(inside, target, side="left"))
        positions.append(b * block + at)
        keys.append(key_below(float(weights[b * block + at]), threshold, rng))
        target = max(inside[at] + weight_jump(threshold, rng), np.nextafter(inside[at], np.inf))
    opened_blocks = len({p // block for p in positions})
    return Walk(np.array(positions, dtype=np.int64), np.array(keys), examined, len(ends) - opened_blocks)


def uniform_fill(n: int, threshold: float, rng: np.random.Generator) -> Walk:
    """Positions that enter among n items, each with chance ``threshold``, drawn by jumps alone; no item is looked at."""
    positions, at = [], -1
    while True:
        at += 1 + item_jump(threshold, rng)
        if at >= n:
            break
        positions.append(at)
    hits = np.array(positions, dtype=np.int64)
    return Walk(hits, (1 - rng.random(len(hits))) * threshold, len(hits))


class Sequential:
    """A sample of k from one stream, whose threshold falls with every insertion; the stream comes in parts of any size, and k items are held."""

    def __init__(self, k: int, seed: int, weighted: bool):
        self.k, self.rng, self.weighted = k, np.random.default_rng(seed), weighted
        self.heap: list[tuple[float, int]] = []
        self.left: float | None = None  # of the jump under way: weight, or items, still to pass over
        self.seen = 0
        self.log: list[int] = []

    def _enter(self, at: int, key: float) -> None:
        if len(self.heap) < self.k:
            heapq.heappush(self.heap, (-key, at))
        else:
            heapq.heapreplace(self.heap, (-key, at))
        self.log.append(at)

    def _jump(self) -> None:
        t = -self.heap[0][0]
        self.left = weight_jump(t, self.rng) if self.weighted else item_jump(t, self.rng)

    def add(self, weights: np.ndarray) -> None:
        """The next part; a uniform sample looks at its length only."""
        n, at = len(weights), 0
        m = min(n, self.k - len(self.heap))
        if m > 0:
            u = 1 - self.rng.random(m)
            for i, key in enumerate((-np.log(u) / weights[:m] if self.weighted else u).tolist()):
                self._enter(self.seen + i, key)
            at = m
        if len(self.heap) == self.k:
            if self.left is None:
                self._jump()
            total = np.cumsum(weights) if self.weighted else None
            done = float(total[at - 1]) if self.weighted and at else 0.0
            while at < n:
                if self.weighted:
                    spot = max(at, int(np.searchsorted(total, done + self.left, side="left")))
                    if spot >= n:
                        self.left -= float(total[-1]) - done
                        break
                    key, done = key_below(float(weights[spot]), -self.heap[0][0], self.rng), float(total[spot])
                else:
                    spot = at + int(self.left)
                    if spot >= n:
                        self.left -= n - at
                        break
                    key = unit(self.rng) * -self.heap[0][0]
                self._enter(self.seen + spot, key)
                at = spot + 1
                self._jump()
        self.seen += n

    def sample(self) -> tuple[np.ndarray, np.ndarray]:
        """(positions, keys) in the order of keys."""
        kept = sorted((-v, i) for v, i in self.heap)
        return np.array([i for _, i in kept], dtype=np.int64), np.array([v for v, _ in kept])


def sequential(weights: np.ndarray | None, n: int, k: int, seed: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(positions, keys, positions in the order inserted) of a sample of k from one stream."""
    one = Sequential(k, seed, weights is not None)
    one.add(np.ones(n) if weights is None else weights)
    return *one.sample(), np.array(one.log, dtype=np.int64)


def batched(weights: np.ndarray, k: int, batch: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """(positions, keys) by mini-batches on one processing element: the threshold is fixed within a batch. With one item a batch it is the sequential sampler."""
    rng = np.random.default_rng(seed)
    held: list[tuple[float, int]] = []
    for at in range(0, len(weights), batch):
        part = weights[at : at + batch]
        if len(held) < k:
            new = zip((-np.log(1 - rng.random(len(part))) / part).tolist(), range(at, at + len(part)), strict=True)
        else:
            walk = weighted_fill(part, held[-1][0], rng)
            new = zip(walk.keys.tolist(), (at + walk.positions).tolist(), strict=True)
        held = sorted([*held, *new])[:k]
    return np.array([i for _, i in held], dtype=np.int64), np.array([v for v, _ in held])
