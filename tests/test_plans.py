"""Planner, bounds and the paper's table of shapes."""

import math

import pytest

from rankloom.plans.params import SPACE_SHAPES, VARIANTS, band_size, certified_error, deterministic_lower_bound, geometric_k, lower_bound, max_height, plan, planned_items, tail_bound, trivial_lower_bound
from rankloom.plans.schedule import sampled_levels


@pytest.mark.parametrize(
    "eps,delta,paper,safe",
    [(0.1, 0.01, 60, 113), (0.05, 0.01, 120, 226), (0.02, 0.01, 300, 564), (0.01, 0.01, 599, 1128), (0.01, 1e-6, 990, 1867), (0.001, 1e-6, 9897, 18661)],
)
def test_top_capacities(eps, delta, paper, safe):
    assert geometric_k(eps, delta, constants="paper") == paper
    assert geometric_k(eps, delta) == safe


@pytest.mark.parametrize("n,k,height", [(6e4, 599, 9), (6e5, 599, 12), (1e12, 599, 33)])
def test_heights(n, k, height):
    assert max_height(int(n), k) == height


def test_tail_bound_inverts():
    assert tail_bound(100.0, certified_error(100.0, 0.05)) == pytest.approx(0.05)
    assert tail_bound(0.0, 1.0) == 0.0


def test_band_meets_its_inequality():
    s = band_size(0.01, 1e-9, 200)
    need = math.log(2 / 1e-9)
    value = lambda b: 0.01**2 * 200**2 * (1 / 3) * 2**b / (16 / 3)
    assert value(s) >= need > value(s - 1)


def test_auto_prefers_the_smaller_certified_sketch():
    for delta in (0.2, 0.01, 1e-9):
        sizes = {v: planned_items(plan(v, 0.01, delta, "single", 10**12), 10**12) for v in ("geo-wsampled", "banded")}
        assert plan("auto", 0.01, delta, "single", 10**12).variant == min(sizes, key=sizes.get)
    assert plan("auto", 0.01, 1e-300, "single", 10**12).variant == "banded"


def test_all_mode_needs_no_less_than_single():
    for v in VARIANTS:
        assert plan(v, 0.02, 0.01, "all", 10**6).k >= plan(v, 0.02, 0.01, "single", 10**6).k


def test_lower_bounds_lie_below_plans():
    assert lower_bound(0.01, 1e-6) < planned_items(plan("tuple-topped", 0.01, 1e-6, "single", 10**9), 10**9)
    assert deterministic_lower_bound(0.01) > trivial_lower_bound(0.01)


def test_sampled_levels_grow_with_height():
    for rule in ("cap2", "log_eps", "two_s"):
        got = [sampled_levels(rule, h, 600, 2 / 3, 4) for h in range(1, 40)]
        assert got == sorted(got) and got[0] == 0 and got[-1] > 0
    assert sampled_levels("none", 30, 600, 2 / 3) == 0


def test_shapes_order_for_tiny_delta():
    env = {"log2": math.log2, "sqrt": math.sqrt, "pow": pow, "eps": 0.01, "delta": 1e-300, "n": 1e12}
    value = {v: eval(s, env) for (v, m), s in SPACE_SHAPES.items() if m == "single"}
    assert value["tuple-topped"] < value["banded"] < value["equal-fair-sampled"]
    assert value["geo-wsampled"] < value["geo"] < value["equal-fixed"]
