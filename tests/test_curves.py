import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from vecquant.functions import curves, fastmath

X = np.linspace(-0.7, 1.3, 401)
PAIRS = {"unif": (0.0, 0.0), "kuma": (2.0, 3.0), "logi": (4.0, 0.1), "logi2": (5.0, 0.1), "pwl": (5.0, 0.1)}


@pytest.mark.parametrize("curve", PAIRS)
def test_ends_order_and_inverse(curve):
    lo, hi = X.min(), X.max()
    h = curves.bend(curve, X, lo, hi, *PAIRS[curve])
    assert abs(h[0]) < 1e-12 and abs(h[-1] - 1) < 1e-12 and (np.diff(h) > 0).all()
    assert np.abs(curves.unbend(curve, h, lo, hi, *PAIRS[curve]) - X).max() < 1e-9


def test_special_parameters():
    u = np.linspace(0, 1, 101)
    assert np.allclose(curves.kumaraswamy(u, 1.0, 1.0), u)
    assert np.allclose(curves.logistic(X, 3.0, 0.2), curves.logistic2(X, 3.0 / np.log(2), 0.2))
    alpha, x0 = curves.raw_parameters(4.0, 0.1, 0.4)
    assert np.allclose(curves.logistic(X / 0.4, 4.0, 0.1), curves.logistic(X, alpha, x0))


def test_piecewise_log_stays_close_below_and_meets_powers_of_two():
    z = np.linspace(0.01, 100, 200_001)
    gap = np.log2(z) - curves.pwl_log2(z)
    assert gap.min() > -1e-12 and gap.max() < 0.0861
    p = 2.0 ** np.arange(-20, 20)
    assert np.array_equal(curves.pwl_log2(p), np.log2(p))
    assert np.allclose(curves.pwl_exp2(curves.pwl_log2(z)), z)
    assert 2.999 < curves.pwl_log2(np.array(7.999999999999999)) <= 3


def test_density_is_the_derivative():
    u = np.linspace(0.05, 0.95, 50)
    slope = (curves.kumaraswamy(u + 1e-6, 2.0, 3.0) - curves.kumaraswamy(u - 1e-6, 2.0, 3.0)) / 2e-6
    assert np.allclose(slope, curves.kumaraswamy_density(u, 2.0, 3.0), rtol=1e-5)


@pytest.mark.parametrize("form", ["explog", "poly"])
def test_power_forms(form):
    u = np.linspace(0, 1, 101)
    assert np.allclose(curves.power(u, 2.5, form), u**2.5, atol=1e-8)


def test_polynomials():
    assert np.allclose(fastmath.exp_poly(X * 5), np.exp(X * 5), rtol=1e-9)
    assert np.allclose(fastmath.log_poly(np.linspace(0.01, 50, 999)), np.log(np.linspace(0.01, 50, 999)), atol=1e-9)


@settings(max_examples=60, deadline=None)
@given(st.lists(st.floats(-100, 100, width=32), min_size=2, max_size=40), st.sampled_from([4, 8]))
def test_uniform_error_is_at_most_half_a_step(values, bits):
    x = np.array(values, dtype=float)
    lo, hi = x.min(), x.max()
    back = curves.reconstruct("unif", x, lo, hi, 0.0, 0.0, bits)
    assert np.abs(x - back).max() <= (hi - lo) / (2 * (2**bits - 1)) + 1e-9


def test_projection():
    p0, p1 = curves.project("logi", np.array(-1.0), np.array(9.0), np.array(-0.5), np.array(1.5))
    assert p0 == curves.FLOOR and p1 == 0.75
    assert curves.project("logi", np.array(1.0), np.array(9.0), np.array(-0.5), np.array(1.5), "raw")[1] == 1.5
    assert curves.project("kuma", np.array(-1.0), np.array(-2.0), np.array(0.0), np.array(1.0)) == (curves.FLOOR, curves.FLOOR)


@pytest.mark.parametrize("bits", [4, 8])
@pytest.mark.parametrize("curve", curves.NAMES)
def test_losses_by_levels_are_the_losses(curve, bits):
    rng = np.random.default_rng(7)
    x = rng.standard_normal((12, 300))
    x[0], x[1], x[2, 0], x[3], x[4] = 3.0, np.repeat([0.0, 1.0], 150), 1e4, np.round(x[3], 1), 1e6 + 1e-3 * x[4]
    lo, hi = x.min(axis=1, keepdims=True), x.max(axis=1, keepdims=True)
    p0 = np.abs(rng.normal(curves.START[curve][0], 3 * curves.SPREAD[curve][0], (12, 9)))
    p1 = rng.normal(curves.START[curve][1], curves.SPREAD[curve][1], (12, 9))
    p0, p1 = curves.project(curve, p0, p1, lo, hi)
    some = np.array([11, 1, 2, 3, 4, 5])
    found = curves.Ordered(x, lo, hi).loss(curve, some, p0[some], p1[some], bits)
    plain = curves.loss(curve, x[some][:, None], lo[some][:, None], hi[some][:, None], p0[some][..., None], p1[some][..., None], bits)
    assert np.allclose(found, plain, rtol=1e-6, atol=0)


@pytest.mark.parametrize("bits", [4, 8])
def test_held_losses_are_the_losses(bits):
    rng = np.random.default_rng(8)
    x = rng.standard_normal((40, 192))
    x[0], x[1], x[2, 0], x[3], x[4] = np.repeat([0.0, 1.0], 96), x[1] + 50, 1e4, np.round(x[3], 1), -1 - np.abs(x[4])
    lo, hi = x.min(axis=1, keepdims=True), x.max(axis=1, keepdims=True)
    p0, p1 = curves.project("logi", np.abs(rng.normal(4, 6, (40, 12))), rng.normal(0, 0.5, (40, 12)), lo, hi)
    p0[5] = curves.FLOOR, *np.geomspace(1e-3, 900, 11)
    rows = np.array([39, *range(30)])
    plain = curves.loss("logi", x[rows][:, None], lo[rows][:, None], hi[rows][:, None], p0[rows][..., None], p1[rows][..., None], bits)
    held = curves.Held(x, lo, hi)
    for _ in range(2):  # the kept memory holds nothing over
        assert np.allclose(held.loss("logi", rows, p0[rows], p1[rows], bits), plain, rtol=1e-6, atol=1e-20)  # two values are met but for rounding
    alone = curves.Held(x[7:8], lo[7:8], hi[7:8]).loss("logi", np.array([0]), p0[7:8], p1[7:8], bits)
    assert np.array_equal(alone[0], held.loss("logi", np.arange(40), p0, p1, bits)[7])


def test_piecewise_linear_levels_where_odds_have_no_end():
    rng = np.random.default_rng(5)
    x = rng.standard_normal((3, 700))
    lo, hi = x.min(axis=1, keepdims=True), x.max(axis=1, keepdims=True)
    p0 = np.array([[0.5, 4.0, 60.0, 900.0, 5000.0]] * 3)
    p1 = np.zeros((3, 5))
    found = curves.Ordered(x, lo, hi).loss("pwl", np.arange(3), p0, p1, 8)
    plain = curves.loss("pwl", x[:, None, :], lo[:, None, :], hi[:, None, :], p0[..., None], p1[..., None], 8)
    assert (np.isfinite(found) == np.isfinite(plain)).all()
    good = np.isfinite(plain)
    assert np.allclose(found[good], plain[good], rtol=1e-8)


def test_logistic_rows_of_768_values_are_measured_by_levels(monkeypatch):
    from vecquant.operators import fit

    x = np.random.default_rng(6).standard_normal((4, 768))
    monkeypatch.setattr(curves.Held, "_loss", None)
    by_levels = fit.evolve_rows(x, np.arange(4), fit.Search(bits=8))
    monkeypatch.undo()
    monkeypatch.setitem(fit._BY_LEVELS, ("logi", 8), 1024)
    by_values = fit.evolve_rows(x, np.arange(4), fit.Search(bits=8))
    assert np.allclose(by_levels["gain"], by_values["gain"], rtol=1e-6) and (by_levels["iters"] == by_values["iters"]).all()
