"""Laws of the jump kernels and of local runs; numpy only."""

import numpy as np
import pytest

from streamsample.functions import skips
from streamsample.operators import localres
from streamsample.operators.estimate import inclusion_law, largest_z, ordered_law
from streamsample.plans import cost

WEIGHTS = np.arange(1.0, 8.0)


@pytest.mark.parametrize("block", [1, 3, 32])
def test_weighted_fill_includes_each_item_with_its_chance(block):
    t, trials, rng = 0.08, 6000, np.random.default_rng(1)
    counts = np.zeros(len(WEIGHTS))
    for _ in range(trials):
        walk = skips.weighted_fill(WEIGHTS, t, rng, block)
        assert len(set(walk.positions.tolist())) == len(walk.positions) and (walk.keys < t).all()
        counts[walk.positions] += 1
    assert largest_z(counts, -np.expm1(-t * WEIGHTS), trials) < 4.5


def test_uniform_fill_includes_each_item_with_the_threshold():
    trials, rng, counts = 6000, np.random.default_rng(2), np.zeros(9)
    for _ in range(trials):
        counts[skips.uniform_fill(9, 0.2, rng).positions] += 1
    assert largest_z(counts, np.full(9, 0.2), trials) < 4.5
    assert skips.item_jump(1.0, rng) == 0


def test_power_and_exponential_jumps_are_one_law():
    rng, t = np.random.default_rng(3), 0.3
    a = np.sort([skips.weight_jump(t, rng) for _ in range(20000)])
    b = np.sort([skips.power_jump(np.exp(-t), rng) for _ in range(20000)])
    assert np.max(np.abs(np.searchsorted(a, b) / 20000 - np.arange(20000) / 20000)) < 0.02


def test_conditional_key_keeps_its_digits():
    rng, t, w = np.random.default_rng(4), 1e-17, 1.0
    keys = np.array([skips.key_below(w, t, rng) for _ in range(4000)])
    assert (keys >= 0).all() and (keys <= t).all() and abs(keys.mean() / t - 0.5) < 0.03


@pytest.mark.parametrize("weights", [WEIGHTS, None])
def test_sequential_sampler_follows_the_definition(weights):
    k, trials, counts, first = 2, 6000, np.zeros(7), np.zeros(7)
    for seed in range(trials):
        at, keys, _ = skips.sequential(weights, 7, k, seed)
        assert len(at) == k and (np.diff(keys) >= 0).all()
        counts[at] += 1
        first[at[0]] += 1
    w = WEIGHTS if weights is not None else np.ones(7)
    assert largest_z(counts, inclusion_law(w, k), trials) < 4.5
    assert largest_z(first, w / w.sum(), trials) < 4.5


def test_frozen_threshold_over_batches_follows_the_definition():
    """Two partitions, three batches, left-over jumps dropped."""
    batches, k, trials, counts = [([0], [1, 2]), ([3, 4], []), ([5], [6])], 2, 6000, np.zeros(7)
    rng = np.random.default_rng(5)
    for _ in range(trials):
        held, t = [], None
        for batch in batches:
            for part in batch:
                w = WEIGHTS[part] if part else np.zeros(0)
                if t is None:
                    held += list(zip((-np.log(1 - rng.random(len(w))) / w).tolist(), part, strict=True)) if part else []
                else:
                    walk = skips.weighted_fill(w, t, rng)
                    held += [(float(v), part[i]) for v, i in zip(walk.keys, walk.positions, strict=True)]
            held = sorted(held)[:k]
            t = held[-1][0] if len(held) == k else None
        counts[[i for _, i in held]] += 1
    assert largest_z(counts, inclusion_law(WEIGHTS, k), trials) < 4.5


def test_laws_sum_to_one():
    law = ordered_law(WEIGHTS, 2)
    assert abs(sum(law.values()) - 1) < 1e-12 and abs(inclusion_law(WEIGHTS, 2).sum() - 2) < 1e-12


def test_local_runs():
    rng = np.random.default_rng(6)
    run = localres.insert_many((np.zeros(0), np.zeros(0, dtype=int)), rng.random(50), np.arange(50))
    assert (np.diff(run[0]) >= 0).all() and localres.rank(run, run[0][10]) == 10 and localres.kth(run, 11)[0] == run[0][10]
    low, high = localres.split(run, run[0][10])
    assert len(low[0]) == 11
    for a, b in ((low, high), (high, low)):
        assert (localres.join(a, b)[0] == run[0]).all()


def test_first_batch_cap_keeps_the_smallest():
    rng = np.random.default_rng(7)
    keys, one = rng.random(20000), localres.FirstBatch(100)
    one.add(keys, np.arange(20000).astype(object))
    assert 100 <= len(one.keys) <= localres.cap_limits(100)[1]
    assert (np.sort(one.keys)[:100] == np.sort(keys)[:100]).all()
    assert localres.cap_limits(10_000) == (15_000, 11_000)


def test_insertions_match_the_exact_sum():
    n, k, p, b, rng = 60_000, 500, 4, 500, np.random.default_rng(8)
    inserted, held, t = np.zeros(p), np.zeros(0), None
    for _ in range(n // (p * b)):
        new = rng.random((p, b))
        hit = new < t if t is not None else np.ones((p, b), dtype=bool)
        inserted += hit.sum(axis=1)
        held = np.sort(np.concatenate([held, new[hit]]))[:k]
        t = held[-1] if len(held) == k else None
    expected = cost.expected_insertions(n, k, p, b)
    assert abs(inserted.mean() - expected) < 5 * np.sqrt(expected / p)
    assert inserted.max() < max(cost.max_insertions_bound(n, k, p), expected + b) * 1.2


def test_cost_formulas_keep_their_order():
    args = {"b": 10_000, "b_star": 50, "k": 100_000, "alpha": 100.0, "beta": 0.5}
    assert cost.predict("pivot", p=5120, **args) < cost.predict("gather", p=5120, **args)
    small = args | {"k": 1000, "b_star": 1}
    assert cost.predict("gather", p=16, **small) < cost.predict("pivot", p=16, select="pivot", **small)
    assert cost.monitoring_messages(10**6, 1000, 16) > 1000
