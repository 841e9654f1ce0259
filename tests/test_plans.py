"""Schemes, formulas and planning against known values; no Spark needed but for layouts."""

import math

import numpy as np
import pytest

from sevenfold.operators.leaf import seq_fast
from sevenfold.plans import costs, planner
from sevenfold.plans.layout import LayoutSpec, digits_of, usable_workers
from sevenfold.plans.schemes import SCHEMES, Scheme, compose, plain_stages, scheme_of


@pytest.mark.parametrize("name", sorted(SCHEMES))
def test_scheme_identities(name):
    assert SCHEMES[name].validate()


def test_additions_and_bad_scheme():
    assert (SCHEMES["s7a18"].additions, SCHEMES["s7a15"].additions) == (18, 15)
    u, v, w = (t.copy() for t in SCHEMES["s7a18"].tables)
    u[0, 0] += 1
    with pytest.raises(ValueError):
        scheme_of(Scheme("bad", 2, 7, plain_stages(u), plain_stages(v), plain_stages(w)))
    assert compose(SCHEMES["c8"], SCHEMES["s7a15"]).validate()


@pytest.mark.parametrize("name", ["s7a18", "s7a15", "c8"])
@pytest.mark.parametrize("shape", [(8, 8, 8), (12, 4, 20), (7, 5, 3), (1, 1, 1)])
def test_leaf_kernel(name, shape):
    rng = np.random.default_rng(0)
    a, b = rng.integers(-9, 9, shape[:2]), rng.integers(-9, 9, shape[1:])
    assert (seq_fast(a, b, 3, name) == a @ b).all()


GOLDEN = [(56, 7, 3696, 4032, 36), (224, 7, 59136, 64512, 36), (224, 49, 17856, 25344, 72), (672, 7, 532224, 580608, 36), (672, 49, 160704, 228096, 72)]


@pytest.mark.parametrize("n,p,footprint,words,messages", GOLDEN)
def test_wide_costs(n, p, footprint, words, messages):
    k = digits_of(p)
    assert costs.footprint_wide(n, p) == costs.footprint_wide_closed(n, p) == footprint
    assert costs.traffic(n, p, "W" * k) == (words, messages)
    assert costs.words_wide_closed(n, p) == words
    generic = costs.generic_costs(SCHEMES["s7a15"], n, k)
    assert (generic["footprint"], generic["words"], generic["messages"]) == (footprint, words, messages)


@pytest.mark.parametrize("n,p,m,closed,least,footprints,words,messages", [(224, 49, 12544, 1, 1, (7536, 7536), 44352, 504), (224, 49, 9216, 2, 1, (4956, 7536), 77616, 3528), (672, 49, 82944, 2, 1, (44604, 67824), 698544, 3528)])
def test_budgeted_costs(n, p, m, closed, least, footprints, words, messages):
    assert (planner.depth_closed(n, p, m), planner.depth_min(n, p, m)) == (closed, least)
    assert tuple(costs.footprint_budgeted(n, p, x) for x in (closed, least)) == footprints
    assert costs.traffic(n, p, "S" * closed + "WW") == (words, messages)
    assert footprints[0] <= 127 / 144 * m
    bounds = costs.budgeted_bounds(n, p, m)
    assert words <= bounds["words_sound"] and messages <= bounds["messages_sound"]
    if bounds["exact_levels"] == closed:
        assert words <= bounds["words_printed"] and messages <= bounds["messages_printed"] + 1e-6
    else:
        assert words > bounds["words_printed"]  # rounding up breaks the printed form


def test_flops_closed_forms():
    for n in (2, 4, 16):
        assert math.isclose(costs.sequential_flops(n, "s7a18"), 7 * n**costs.OMEGA - 6 * n * n)
        assert math.isclose(costs.sequential_flops(n), 6 * n**costs.OMEGA - 5 * n * n)
    assert math.isclose(costs.flops(64, 7, "W"), costs.sequential_flops(64) / 7)
    assert math.isclose(costs.flops(64, 7, "SW"), costs.sequential_flops(64) / 7)


def test_excess_exponents():
    at = lambda method, p, m: costs.method_cost(method, 1e6, p, m, 1)
    slope = lambda f: math.log(f(7.0**8) / f(7.0**6)) / math.log(49)
    big = 1e13
    assert round(slope(lambda p: at("grid25d", p, big).words / at("hybrid", p, big).words), 3) == 0.046
    assert round(slope(lambda p: at("grid2d_fast", p, big).words / at("hybrid", p, big).words), 3) == 0.212
    assert round(slope(lambda p: at("grid25d_fast", p, big).flops / at("hybrid", p, big).flops), 3) == 0.064
    assert round(slope(lambda p: at("grid2d_fast", p, big).flops / at("hybrid", p, big).flops), 3) == 0.096


def test_strong_scaling_is_flat_inside_the_range():
    n, m = 94080, 1e6
    rows = planner.scaling_profile(n, [2**k for k in range(14, 23)], m)
    flat = [r["words_p"] for r in rows if r["in_range"]]
    assert len(flat) >= 2 and max(flat) / min(flat) < 1.0001
    assert rows[-1]["words_p"] > 1.05 * flat[0]


def test_planner():
    assert planner.valid_25d(64) == [(64, 1), (64, 4)] and (32, 2) in planner.valid_25d(32)
    assert usable_workers(48)[0] == 42 and usable_workers(50)[0] == 49
    assert planner.plan_greedy(224, 49, 1e9) == "WW" and planner.plan_greedy(224, 49, 9216)[0] == "S"
    found = planner.plan_search(672, 7, 1e6, 3)
    assert found[0][0] <= found[-1][0] and {s.count("W") for _, s in found} == {1}
    assert planner.choose_multiplier(1000, 49, 1e6, costs.Machine(), nnz=(1000, 1000)) == "sql"
    assert "fast" not in planner.choose_multiplier(10**5, 2401, 1e8, costs.Machine(), finite=False)
    assert math.isclose(costs.effective_gflops(94080, 692.0, 49)[1], 49.1, rel_tol=0.01)


def test_layout():
    spec = LayoutSpec(4 * 49 * 3, 49, 2)
    assert spec.check().block == (21, 21)
    with pytest.raises(ValueError, match="nearest valid n"):
        LayoutSpec(50, 49, 2).check()
    assert spec.after("W") == LayoutSpec(spec.n // 2, 7, 1) and spec.after("S").workers == 49
