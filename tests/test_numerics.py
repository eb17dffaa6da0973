import math

import numpy as np
import pytest

from distinct_bounds.functions import bounds, planner, solvers, special
from distinct_bounds.operators import hashing, simulate
from distinct_bounds.spec import SketchSpec


def test_worked_example_bits():
    bits = f"{0xD012F681:032b}"
    assert hashing.fields_from_bits(bits, SketchSpec(c0=1, r0=4, z0=6, layout="prefix")) == (14, 0, 2)
    assert hashing.fields_from_bits(bits, SketchSpec(c0=1, r0=4, z0=6, layout="prefix", row_bits="lsb")) == (12, 0, 2)


@pytest.mark.parametrize("p", [0.5, 1 / 16, 1 / 256, 2.0**-12, 1.0])
@pytest.mark.parametrize("n", [1, 2, 7, 50, 400, 3000])
def test_harmonic_function_is_its_sum(p, n):
    k = np.arange(1, n + 1)
    exact = ((1 - (1 - p) ** k) / k).sum()
    assert special.hp(n, p)[0] == pytest.approx(exact, rel=1e-11)
    if p < 1:
        assert special.hp_quad(n, p)[0] == pytest.approx(exact, rel=1e-11)


def test_harmonic_function_identities():
    assert special.hp(0, 0.25)[0] == 0
    assert special.hp(1, 1 / 16)[0] == pytest.approx(0.0625, rel=1e-13)
    assert special.hp(2, 1 / 4)[0] == pytest.approx(0.46875, rel=1e-13)
    x = np.array([0.1, 1.0, 10, 100, 1e6, 1e12])
    assert (np.diff(special.hp(x, 1 / 16)) > 0).all() and (special.hp(x, 0.5) > special.hp(x, 0.25)).all()
    # expectation of the harmonic number of a binomial count
    n, p = 30, 0.25
    weights = [math.comb(n, m) * p**m * (1 - p) ** (n - m) for m in range(n + 1)]
    assert special.hp(n, p)[0] == pytest.approx(sum(w * sum(1 / j for j in range(1, m + 1)) for m, w in enumerate(weights)), rel=1e-12)


@pytest.mark.parametrize("p", [0.5, 1 / 16, 1 / 1024, 1.0])
def test_derivatives(p):
    for x in (0.4, 3.0, 60.0, 5000.0):
        e = 1e-4 * x
        assert special.hp(x, p, 1)[0] == pytest.approx((special.hp(x + e, p)[0] - special.hp(x - e, p)[0]) / (2 * e), rel=1e-5)
        assert special.hp(x, p, 2)[0] == pytest.approx((special.hp(x + e, p, 1)[0] - special.hp(x - e, p, 1)[0]) / (2 * e), rel=1e-5)


def test_polygamma_and_transcendent():
    assert special.psi1(1) == pytest.approx(-special.EULER, abs=1e-14)
    assert special.psi1(1, 1) == pytest.approx(math.pi**2 / 6, rel=1e-13)
    assert special.psi1(1, 2) == pytest.approx(-2.4041138063191885, rel=1e-12)
    z, a, m = 0.9, 2.5, 4
    direct = z**m * special.lerch(z, 2, a + m)[0] + sum(z**n / (a + n) ** 2 for n in range(m))
    assert special.lerch(z, 2, a)[0] == pytest.approx(direct, rel=1e-12)
    x = np.array([0.01, 0.5, 3.0])
    tail = [sum((1 - 1 / 16) ** (v + j + 1) / (v + j + 1) for j in range(5000)) for v in x]
    assert np.allclose(special.hp_tail(x, 1 / 16), tail, rtol=1e-10)
    assert (np.array(tail) < special.e1_bound(-x * math.log(15 / 16))).all()
    assert special.gamma_product(0.4, 200_000, -1) == pytest.approx(math.gamma(0.6) * math.exp(-special.EULER * 0.4), rel=1e-5)


@pytest.mark.parametrize("y", [-40.0, -5.0, -1.0, -0.3, 0.0, 0.7, 5.0, 30.0])
def test_digamma_inverse(y):
    t = solvers.psi_inverse_trace(y)
    assert t.bracket[0] <= t.root <= t.bracket[1] * (1 + 1e-12) and t.iterations <= 12
    assert special.psi1(t.root) == pytest.approx(y, abs=1e-9 * max(1, abs(y)))


@pytest.mark.parametrize("y", [1e-4, 0.01, 0.036, 0.3, 2.9, 3.1, 20.0])
def test_half_widths_in_brackets_and_equal_to_their_dual(y):
    for trace, dual, exponent in ((solvers.h_up_trace, solvers.h_up_dual, solvers.exponent_up), (solvers.h_down_trace, solvers.h_down_dual, solvers.exponent_down)):
        roots = {m: trace(y, m) for m in solvers.METHODS}
        low, high = roots["halley"].bracket
        assert low < roots["halley"].root < high
        assert roots["halley"].root == pytest.approx(dual(y), rel=1e-7, abs=1e-9)
        assert roots["bisect"].root == pytest.approx(roots["halley"].root, rel=1e-9)
        assert roots["newton"].root == pytest.approx(roots["halley"].root, rel=1e-9)
        assert max(roots["halley"].iterations, roots["newton"].iterations) < roots["bisect"].iterations
        assert exponent(roots["halley"].root)[0] == pytest.approx(y, rel=1e-9)
        h, e = roots["halley"].root, 1e-5
        assert exponent(h)[1] == pytest.approx((exponent(h + e)[0] - exponent(h - e)[0]) / (2 * e), rel=1e-4)


@pytest.mark.parametrize("alpha,slots,down,up", [(0.9, 1, 5.0696, 2.1199), (0.9, 4, 1.9988, 1.2662), (0.9, 16, 0.8843, 0.7016), (0.9, 64, 0.4163, 0.3706), (0.9, 256, 0.2020, 0.1906), (0.95, 64, 0.4649, 0.4088)])
def test_half_widths(alpha, slots, down, up):
    got = bounds.budget(alpha, slots)
    assert got == (pytest.approx(down, abs=6e-5), pytest.approx(up, abs=6e-5))
    assert bounds.levels(*got, slots)[2] == pytest.approx(alpha, abs=1e-10)


@pytest.mark.parametrize("alpha,slots,tail", [(0.9, 1, 0.08796), (0.9, 4, 0.07462), (0.9, 64, 0.05691), (0.99, 1, 0.009078), (0.99, 64, 0.005842)])
def test_shortest_interval(alpha, slots, tail):
    down, up, x = bounds.log_shortest(alpha, slots)
    assert x == pytest.approx(tail, rel=1e-3)
    assert bounds.levels(down, up, slots)[2] == pytest.approx(alpha, abs=1e-9)
    others = [bounds._half(v, slots, "lower") + bounds._half(1 - alpha - v, slots, "upper") for v in np.linspace(0.05, 0.95, 19) * (1 - alpha)]
    assert down + up <= min(others) + 1e-9 and down + up <= sum(bounds.budget(alpha, slots)) + 1e-12
    assert bounds.shortest_share(alpha, slots).iterations <= 8


@pytest.mark.parametrize("p", [1.0, 0.5, 1 / 16, 1 / 256, 2.0**-14])
def test_inverse_of_the_harmonic_function(p):
    x = np.array([0.01, 0.5, 3, 40, 1e3, 1e6, 1e12])
    y = special.hp(x, p)
    assert np.allclose(solvers.hp_inverse_vec(y, p), x, rtol=1e-7)
    for v, t in zip(x[:5], y[:5], strict=True):
        trace = solvers.hp_inverse_trace(float(t), p)
        assert trace.bracket[0] <= v * (1 + 1e-9) and v <= trace.bracket[1] * (1 + 1e-9) + 1e-9
        assert trace.root == pytest.approx(v, rel=1e-7)
    assert solvers.hp_inverse_vec(np.array([0.0, np.nan]), p)[0] == 0


def test_limit_form_bounds_the_finite_one():
    for t in (0.1, 0.5, 0.9):
        r = bounds.product_ratio(np.array([1, 5, 50, 1000]), t, -1)
        assert (np.diff(r) > 0).all() and r[-1] < 100
    m = simulate.occupancies(simulate.generator(1), 500, SketchSpec())
    for side in ("lower", "upper"):
        h = bounds._half(0.1, 64, side)
        assert 0 < bounds.finite_tail(m, h, side) < 0.1
    for h in (0.05, 0.4, 1.5):
        assert bounds.gumbel_exponent(h, "lower") == pytest.approx(solvers.exponent_down(h)[0], rel=1e-9)
        assert bounds.gumbel_exponent(h, "upper") == pytest.approx(solvers.exponent_up(h)[0], rel=1e-9)


def test_moments_of_slot_maxima():
    rng = simulate.generator(3)
    y = simulate.slot_maxima(rng, np.full(200_000, 20))
    assert np.exp(0.2 * y).mean() == pytest.approx(bounds.mgf_slot(0.2, 20), rel=0.01)
    assert y.mean() == pytest.approx(bounds.mean_given([20]), rel=0.01)


@pytest.mark.parametrize("q,df,p", [(17.608, 15, 0.2838), (10.597, 15, 0.7808), (298.91, 255, 0.03062), (286.51, 255, 0.08521), (8.7522, 12, 0.7239), (7.1689, 12, 0.8463)])
def test_chi_square_tails(q, df, p):
    assert special.chi_square_tail(q, df) == pytest.approx(p, abs=1e-3)


def test_f_tails_and_quantiles():
    assert special.f_tail(0.437, 3, 60) == pytest.approx(0.728, abs=1e-3)
    assert special.f_tail(1.095, 3, 60) == pytest.approx(0.358, abs=1e-3)
    assert special.f_tail(0.0004698 * 998 / (1 - 0.0004698), 1, 998) == pytest.approx(0.494, abs=1e-3)
    assert special.normal_quantile(0.975) == pytest.approx(1.959963984540054, rel=1e-12)


def test_planner():
    assert planner.overflow_chance(SketchSpec(), 1e6) < 1e-8
    assert planner.bit_budget(SketchSpec(), 1e12) > 60
    with pytest.raises(ValueError):
        planner.check(SketchSpec(), 1e14)
    n = planner.slots_for_width(0.8, 0.9)
    assert sum(bounds.log_shortest(0.9, n)[:2]) <= 0.8 < sum(bounds.log_shortest(0.9, n - 1)[:2])
    assert planner.memory_bits(SketchSpec(), 1e6) < 64 * 16 and planner.hashes_per_object(SketchSpec()) == 1


def test_coverage_by_simulation():
    spec = SketchSpec()
    est = simulate.estimate_spread(spec, 5000, 2000)
    assert np.median(est) == pytest.approx(5000, rel=0.05)


def test_spec_is_checked():
    for bad in (dict(c0=0), dict(r0=17), dict(r0=3), dict(c0=9), dict(family="crc")):
        with pytest.raises(ValueError):
            SketchSpec(**bad)
    assert SketchSpec().fingerprint() != SketchSpec(z0=4).fingerprint()
