"""Claims about compactors, samplers, tuples and merges, as executable properties."""

import itertools
from dataclasses import replace
from fractions import Fraction

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from rankloom.functions.coins import Coins
from rankloom.operators.kernel import Sketch, Trials, WeightedSampler, compact
from rankloom.operators.measure import cap2_equivalence, uniformity
from rankloom.operators.merge import fold, merge_many
from rankloom.operators.tuples import TupleSummary
from rankloom.plans.params import MERGEABLE, VARIANTS, max_height, plan
from rankloom.plans.schedule import banded, capacities, equal, geometric, level_weight
from rankloom.sources.ordered import ordered_values


def sup_error(sketch, data):
    v, w, _ = sketch.points()
    cum = np.concatenate([[0], np.cumsum(w)])
    x = np.unique(np.concatenate([data, v]))
    truth, s = np.sort(data), "right"
    at = np.abs(cum[np.searchsorted(v, x, s)] - np.searchsorted(truth, x, s)).max()
    below = np.abs(cum[np.searchsorted(v, x, "left")] - np.searchsorted(truth, x, "left")).max()
    return max(at, below)


def fed(chosen, data, scope=1, batches=20, start=0, seed=5):
    s = Sketch(chosen, seed, scope, start, data.dtype)
    for part in np.array_split(data, batches):
        s.insert(part)
    return s


@pytest.mark.parametrize("size", range(2, 13))
@pytest.mark.parametrize("odd", [True, False])
def test_compaction_moves_ranks_by_one_weight_or_none(size, odd):
    items = np.arange(size, dtype=float)
    kept, held = compact(items, odd)
    for x in range(-1, size):
        before = int((items <= x).sum())
        after = 2 * int((kept <= x).sum()) + int((held <= x).sum())
        assert abs(after - before) <= before % 2
    assert 2 * len(kept) + len(held) == size


def test_compaction_worked_example():
    items = np.array([3.0, 8, 11, 20, 24, 31])
    odd, even = compact(items, True)[0], compact(items, False)[0]
    assert 2 * (odd <= 12).sum() == 4 and 2 * (even <= 12).sum() == 2
    assert 2 * (odd <= 20).sum() == 2 * (even <= 20).sum() == 4


def test_mean_over_all_coins_is_the_exact_rank():
    items = np.arange(8.0)
    for x in range(8):
        total = 0
        for coins in itertools.product((True, False), repeat=3):
            left, weight = items, 1
            for c in coins:
                left, weight = compact(left, c)[0], weight * 2
            total += weight * int((left <= x).sum())
        assert total == 8 * (x + 1)


@pytest.mark.parametrize("height", [1, 2, 3, 4])
def test_chain_of_two_item_compactors_is_a_uniform_pick(height):
    assert set(cap2_equivalence(height).values()) == {1}


def test_block_pick_is_uniform():
    seen = np.zeros(8)
    for seed in range(2000):
        s = WeightedSampler(3, np.random.default_rng(seed))
        seen[int(s.update_many(np.arange(8.0))[0])] += 1
    assert uniformity(seen.tolist()) < 24.3


class Scripted:
    """A generator whose draws take all branches with their exact chances."""

    def __init__(self, draw):
        self.draw = draw

    def random(self):
        return self.draw


@pytest.mark.parametrize("v,w", [(v, w) for v in range(0, 8) for w in range(1, 8)])
def test_weighted_sampler_is_unbiased(v, w):
    """Expected emitted and stored weight of each item equals what came in, in all three cases."""
    grid = 840
    expected = {"old": Fraction(0), "new": Fraction(0)}
    for i in range(grid):
        s = WeightedSampler(3, Scripted((i + 0.5) / grid))
        s.item, s.weight = "old", v
        for item in s.update("new", w):
            expected[item] += Fraction(8, grid)
        if s.weight:
            expected[s.item] += Fraction(s.weight, grid)
    assert expected["old"] == v and expected["new"] == w


def test_incomplete_block_keeps_its_weight():
    s = WeightedSampler(3, np.random.default_rng(0))
    assert len(s.update_many(np.arange(19.0))) == 2 and s.weight == 3


@pytest.mark.parametrize("variant", list(VARIANTS))
@pytest.mark.parametrize("order", ["ascending", "descending", "ends", "blocks", "random"])
def test_all_quantiles_within_eps_for_any_order(variant, order):
    data = ordered_values(30_000, order)
    chosen = plan(variant, 0.02, 1e-6, n=len(data))
    start = 2 if variant == "sampled-tuple" else 0
    s = fed(chosen, data, start=start)
    assert sup_error(s, data) <= 0.02 * len(data)
    assert s.n == len(data)


@pytest.mark.parametrize("variant", sorted(MERGEABLE))
def test_merge_in_any_tree_keeps_guarantee_and_mass(variant):
    data = ordered_values(40_000, "random", 3)
    chosen = plan(variant, 0.02, 1e-6, n=len(data))
    cuts = [0, 100, 5000, 5001, 20_000, 39_000, 40_000]
    parts = lambda: [fed(chosen, data[a:b], i) for i, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False))]
    star = merge_many(parts())
    chain = parts()[0]
    for p in parts()[1:]:
        chain = merge_many([chain, p])
    p = parts()
    balanced = merge_many([merge_many(p[:3]), merge_many(p[3:])])
    for merged in (star, chain, balanced):
        assert merged.n == len(data)
        assert sup_error(merged, data) <= 0.02 * len(data)
        if not merged.sampler.height:
            assert merged.points()[1].sum() == len(data)


def test_unequal_samplers_merge():
    data = ordered_values(200_000, "random", 1)
    chosen = plan("geo-wsampled", 0.15, 1e-6, k=24)
    big, little = fed(chosen, data[:190_000], 1, 400), fed(chosen, data[190_000:], 2, 10)
    assert big.sampler.height > little.sampler.height
    merged = merge_many([little, big])
    assert merged.n == len(data) and sup_error(merged, data) <= 0.15 * len(data)
    assert abs(merged.points()[1].sum() - len(data)) <= 0.1 * len(data)


def test_mergeability_guards():
    a, b = (fed(plan(v, 0.05), ordered_values(100, "random")) for v in ("geo", "banded"))
    with pytest.raises(ValueError):
        merge_many([a, b])
    with pytest.raises(ValueError):
        merge_many([fed(plan("tuple-summary", 0.05), ordered_values(100, "random")) for _ in range(2)])


def test_one_way_merge_error():
    data = ordered_values(20_000, "blocks")
    chosen = plan("tuple-summary", 0.02, mode="single")
    merged = fold([fed(chosen, part, i) for i, part in enumerate(np.array_split(data, 7))])
    assert sup_error(merged, data) <= 2 * 0.02 * len(data)


@pytest.mark.parametrize("variant", ["sampled-tuple", "tuple-topped"])
@pytest.mark.parametrize("cuts", [[100_000, 200_000, 300_000], [150_000, 299_999], [200, 299_000], [299_990]])
def test_fold_answers_above_samplers_and_levels_of_its_parts(variant, cuts):
    data = ordered_values(300_000, "blocks")
    chosen = plan(variant, 0.1, 1e-6, "single", n=len(data))
    parts = [fed(chosen, part, i, 50, start=5 if variant == "sampled-tuple" else 0) for i, part in enumerate(np.split(data, cuts))]
    above = max(min(s.tops) for s in parts)
    merged = fold(parts)
    assert merged.n == len(data) and merged.points()[1].sum() == len(data)
    assert (merged.sampler.height == 5 if variant == "sampled-tuple" else min(merged.tops) >= above > 0)
    error = sup_error(merged, data)
    assert error <= 0.1 * len(data) and error <= merged.certified(1e-6)


def test_fold_of_unequal_samplers():
    data = ordered_values(40_000, "random", 2)
    chosen = plan("sampled-tuple", 0.05, 1e-6, "single", n=len(data))
    merged = fold([fed(chosen, part, i, start=i) for i, part in enumerate(np.split(data, [10_001, 20_007]))])
    assert merged.n == len(data) and merged.points()[1].sum() == len(data)
    assert sup_error(merged, data) <= 0.05 * len(data)


@settings(max_examples=60, deadline=None)
@given(st.lists(st.lists(st.integers(0, 50), min_size=1, max_size=60), min_size=1, max_size=12))
def test_tuple_bounds_hold(batches):
    t, seen = TupleSummary(0.1, np.int64), []
    for b in batches:
        t.insert(np.array(b))
        seen += b
        truth = np.sort(seen)
        first, last = np.searchsorted(truth, t.values, "left") + 1, np.searchsorted(truth, t.values, "right")
        assert (t.low <= last).all() and (t.high >= first).all()
        v, est = t.estimates()
        for x in set(seen):
            at = np.searchsorted(v, x, "right")
            guess = est[at - 1] if at else 0
            assert abs(guess - (truth <= x).sum()) <= 0.1 * len(seen) + 1


def test_tuple_summary_stays_small():
    t = TupleSummary(0.01)
    for part in np.array_split(ordered_values(200_000, "random"), 100):
        t.insert(part)
    assert t.size <= 120 and t.n == 200_000


def test_tuple_top_rotates():
    chosen = plan("tuple-topped", 0.05, 0.01, k=32)
    s = fed(chosen, ordered_values(300_000, "random"), batches=3000)
    assert all(h % chosen.band == 0 for h in s.tops) and min(s.tops) > 0
    assert sup_error(s, ordered_values(300_000, "random")) <= 0.1 * 300_000


def test_schedules():
    g = geometric(600, 2 / 3, 20)
    assert sum(g) <= 600 * 3 + 2 * 20 + 20 and min(g) >= 2 and g == sorted(g)
    assert all(a >= b for a, b in zip(geometric(600, 2 / 3, 10), geometric(600, 2 / 3, 11)[:10], strict=True))
    assert equal(5, 3) == [5, 5, 5]
    top, band = banded(100, 2 / 3, 10, 3, "top"), banded(100, 2 / 3, 10, 3, "band")
    assert top[-3:] == band[-3:] == [100] * 3 and top[6] < band[6]
    assert capacities("banded", 100, 2 / 3, 10, 3) == band and level_weight(4) == 8


def test_height_and_compactions_within_bounds():
    data = ordered_values(100_000, "random")
    s = fed(plan("geo", 0.05, 0.01, k=100), data, batches=5000)
    assert s.height <= max_height(len(data), 100) + 1
    assert s.err_abs == sum(m * level_weight(h) for h, m in s.compactions.items())
    assert sup_error(s, data) <= s.err_abs


def test_variance_proxy_bound():
    n, k, c = 100_000, 100, 2 / 3
    s = fed(plan("geo", 0.05, 0.01, k=k), ordered_values(n, "random"), batches=5000)
    assert s.err_sq <= n * c * 2**s.height / (k * (2 * c - 1))


def test_failure_rate_and_bias_with_control():
    data = ordered_values(5000, "random")
    errors = {"fair": [], "fixed_odd": []}
    for policy in errors:
        for seed in range(120):
            s = Sketch(plan("geo", 0.1, 0.1, "single", k=32), seed, 1)
            s.coins.policy = policy
            for part in np.array_split(data, 50):
                s.insert(part)
            errors[policy].append(s.rank(2500) - 2501)
    fair = np.array(errors["fair"])
    assert (np.abs(fair) > 500).mean() <= 0.1 + 4 * np.sqrt(0.09 / 120)
    assert abs(fair.mean()) <= 4 * fair.std() / np.sqrt(120)
    assert abs(np.mean(errors["fixed_odd"])) > 4 * fair.std() / np.sqrt(120)


@pytest.mark.parametrize("variant", ["geo", "geo-biased", "equal-fair", "equal-fixed"])
@pytest.mark.parametrize("kind", [float, object])
def test_trials_equal_sketches_one_by_one(variant, kind):
    chosen, data = replace(plan("geo", 0.1, 0.1, "single", k=32), variant=variant), ordered_values(3001, "random")
    if kind is object:
        data = np.array([str(x) for x in data], object)
    trials, alone = Trials(chosen, 42, [5, 6, 7], kind), [Sketch(chosen, 42, scope, dtype=kind) for scope in (5, 6, 7)]
    for part in (data[:0], *np.array_split(data, 70)):
        for s in (trials, *alone):
            s.insert(part, 2)
    for a, b in zip(trials.apart(), alone, strict=True):
        assert (a.n, a.nulls, a.least, a.most, a.flips, a.err_sq, a.err_abs, a.compactions) == (b.n, b.nulls, b.least, b.most, b.flips, b.err_sq, b.err_abs, b.compactions)
        assert {h: sorted(x) for h, x in a.levels.items()} == {h: sorted(x) for h, x in b.levels.items()}
    assert merge_many(trials.apart()).n == 3 * len(data)


def test_trials_refuse_samplers_and_empty_ones_are_empty():
    with pytest.raises(ValueError):
        Trials(plan("geo-wsampled", 0.1, 0.1), 42, [1, 2])
    empty = Trials(plan("geo", 0.1, 0.1), 42, [1, 2])
    assert [s.rank(1.0) for s in empty.apart()] == [0, 0]


@pytest.mark.parametrize("policy", ["fixed_odd", "fixed_even", "alternate", "fair", "biased"])
def test_coins_in_one_go_are_those_one_by_one(policy):
    many, single = Coins(policy, 1, 2, 3), Coins(policy, 1, 2, 3)
    assert [*many.odds(37), *many.odds(600)] == [single.odd() for _ in range(637)]


def test_too_small_sketch_fails():
    data = ordered_values(50_000, "random")
    s = fed(plan("geo", 0.001, 0.01, k=8), data, batches=2000)
    assert sup_error(s, data) > 0.001 * len(data)


@pytest.mark.parametrize("variant", list(VARIANTS))
def test_edges(variant):
    chosen = plan(variant, 0.1, 0.01)
    empty = Sketch(chosen)
    assert empty.rank(1.0) == 0 and empty.value_at_rank(1) is None
    empty.insert(np.zeros(0), nulls=3)
    assert empty.nulls == 3 and empty.n == 0
    one = Sketch(chosen)
    one.insert(np.array([7.0]))
    assert one.rank(7.0) == 1 and one.rank(6.9) == 0
    same = Sketch(chosen)
    same.insert(np.full(10_000, 2.0))
    assert same.rank(2.0) == pytest.approx(10_000, rel=0.01) and same.rank(1.0) == 0
    few = Sketch(plan("geo", 0.1))
    few.insert(np.array([np.nan, 1.0, -np.inf, 3.0]))
    assert few.rank(np.inf) == 3 and few.rank(np.nan) == 4 and few.err_abs == 0


def test_weighted_input_equals_repeats():
    values, weights = np.arange(100.0), np.arange(1, 101)
    s = Sketch(plan("geo", 0.02, 1e-6))
    s.insert_weighted(values, weights)
    assert s.n == weights.sum()
    repeated = np.repeat(values, weights)
    assert sup_error(s, repeated) <= 0.02 * s.n


def test_strings_and_policies():
    words = np.array(["b", "a", "é", "z", "aa"], object)
    s = Sketch(plan("geo", 0.1), dtype=object)
    s.insert(words)
    assert s.value_at_rank(1) == "a" and s.value_at_rank(5) == "é"
    assert [Coins("alternate", 1).odd() for _ in range(1)] == [True]
    assert Coins("fixed_even", 1).odd() is False


def test_equal_seeds_repeat():
    data = ordered_values(20_000, "random")
    a, b = (fed(plan("banded", 0.05), data, scope=9) for _ in range(2))
    assert all(np.array_equal(x, y) for x, y in zip(a.points(), b.points(), strict=True))


def test_exhaustive_small():
    """All 720 orders of six keys and all coin outcomes: the mean estimate of every rank is exact."""

    class Script:
        def __init__(self, bits):
            self.bits, self.used = bits, 0

        def odd(self):
            self.used += 1
            return self.bits[self.used - 1]

    chosen = plan("equal-fair", 0.5, 0.5, "single", k=2)
    for order in itertools.permutations(range(6)):
        totals, outcomes = np.zeros(6), 0
        for bits in itertools.product((True, False), repeat=5):
            s = Sketch(chosen)
            s.coins = Script(bits)
            for x in order:
                s.insert(np.array([float(x)]))
            assert s.coins.used <= 5
            outcomes += 1
            totals += [s.rank(x) for x in range(6)]
        assert np.array_equal(totals, outcomes * np.arange(1, 7))
