"""The start-up solver, smoothing and the online kernel, against dense versions and their own invariants."""

import numpy as np
import pytest

from cellstream import experiments
from cellstream.baselines import methods
from cellstream.baselines.registry import CAPABILITIES, FLAGS, MAKERS
from cellstream.functions import lts_fit
from cellstream.model import HyperParams, SeasonState, Snapshot, TensorSpec
from cellstream.operators import metrics
from cellstream.operators.corrupt import apply_dense
from cellstream.plans import smooth_als, startup
from cellstream.sources import planted
from cellstream.streaming import kernel
from cellstream.streaming.fold import Stream

from . import dense_reference as dense


@pytest.fixture
def window():
    rng = np.random.default_rng(1)
    factors = [rng.random((4, 2)), rng.random((5, 2)), rng.random((9, 2))]
    y = np.einsum("ir,jr,tr->ijt", *factors) + 0.1 * rng.standard_normal((4, 5, 9))
    mask = rng.random(y.shape) > 0.3
    return factors, y, mask, np.argwhere(mask), y[mask]


def test_row_systems_equal_dense(window):
    factors, y, mask, idx, v = window
    for n in range(3):
        gram, right = smooth_als.systems(smooth_als.products(factors, idx, n), v, idx[:, n], len(factors[n]))
        for i in range(len(factors[n])):
            g, c = dense.als_row(y, mask, factors, n, i)
            assert np.allclose(gram[i], g) and np.allclose(right[i], c)


def test_row_update_is_stationary(window):
    """After a row solve the objective's gradient in that row is zero, and moving it raises the objective."""
    factors, y, mask, idx, v = window
    o = np.zeros_like(y)
    gram, right = smooth_als.systems(smooth_als.products(factors, idx, 0), v, idx[:, 0], 4)
    factors[0] = smooth_als.solve_rows(gram, right, factors[0])
    best = dense.objective(y, mask, o, factors, 3, 0.2, 0.3, 1.0)
    for i in range(4):
        for r in range(2):
            for e in (1e-3, -1e-3):
                moved = [u.copy() for u in factors]
                moved[0][i, r] += e
                assert dense.objective(y, mask, o, moved, 3, 0.2, 0.3, 1.0) >= best - 1e-12


@pytest.mark.parametrize("steps", [4, 6, 7, 9])
def test_time_rows_minimize(window, steps):
    """The joint solve is the minimum over all time rows, for windows shorter and longer than two seasons; sweeps approach it."""
    factors, y, mask, idx, v = window
    on = idx[:, 2] < steps
    idx, v = idx[on], v[on]
    gram, right = smooth_als.systems(smooth_als.products(factors, idx, 2), v, idx[:, 2], steps)
    w = factors[2][:steps]
    joint = smooth_als.time_rows(gram, right, w, 3, 0.2, 0.3, "joint")
    sweep = w
    for _ in range(300):
        sweep = smooth_als.time_rows(gram, right, sweep, 3, 0.2, 0.3)
    assert np.allclose(joint, sweep, atol=1e-6)
    full = [*factors[:2], joint]
    cost = lambda f: dense.objective(y[..., :steps], mask[..., :steps], 0 * y[..., :steps], f, 3, 0.2, 0.3, 1.0)
    rng = np.random.default_rng(0)
    assert all(cost([*factors[:2], joint + 1e-2 * rng.standard_normal(joint.shape)]) > cost(full) for _ in range(20))


def test_printed_cases_are_neighbour_counts():
    """First, early, middle, late and last rows have the printed weights."""
    steps, m, l1, l2 = 9, 3, 2.0, 5.0
    w = np.random.default_rng(0).random((steps, 1))
    gram, right = np.ones((steps, 1, 1)), np.zeros((steps, 1))
    got = smooth_als.time_rows(gram, right, w, m, l1, l2, "jacobi")[:, 0]
    w = w[:, 0]
    assert np.isclose(got[0], (l1 * w[1] + l2 * w[3]) / (1 + l1 + l2))
    assert np.isclose(got[1], (l1 * (w[0] + w[2]) + l2 * w[4]) / (1 + 2 * l1 + l2))
    assert np.isclose(got[4], (l1 * (w[3] + w[5]) + l2 * (w[1] + w[7])) / (1 + 2 * (l1 + l2)))
    assert np.isclose(got[7], (l1 * (w[6] + w[8]) + l2 * w[4]) / (1 + 2 * l1 + l2))
    assert np.isclose(got[8], (l1 * w[7] + l2 * w[5]) / (1 + l1 + l2))


def test_normalize_and_degenerate_rows(window):
    factors, y, mask, idx, v = window
    before = np.einsum("ir,jr,tr->ijt", *factors)
    smooth_als.normalize(factors, 0)
    assert np.allclose(np.linalg.norm(factors[0], axis=0), 1) and np.allclose(np.einsum("ir,jr,tr->ijt", *factors), before)
    factors[1][:] = 0
    smooth_als.normalize(factors, 1)
    assert np.isfinite(factors[2]).all()
    old = np.array([[1.0, 2.0]])
    assert (smooth_als.solve_rows(np.zeros((1, 2, 2)), np.zeros((1, 2)), old) == old).all()
    h = np.array([[1.0, 1.0]])
    x = smooth_als.solve_rows(h[:, :, None] * h[:, None, :], 3 * h, old)
    assert np.allclose(x.sum(), 3)


def test_relative_change_from_gram_matrices(window):
    factors = window[0]
    new = [u + 0.1 for u in factors]
    a, b = (np.einsum("ir,jr,tr->ijt", *f) for f in (factors, new))
    assert np.isclose(smooth_als.relative_change(new, factors), np.linalg.norm(b - a) / np.linalg.norm(a))


def test_plain_is_smooth_without_weights(window):
    _, y, mask, idx, v = window
    spec = TensorSpec((4, 5), 3, 2)
    a, _ = startup.run_local(idx, v, spec, HyperParams(max_iter=5), 9, "plain")
    b, _ = startup.run_local(idx, v, spec, HyperParams(lambda1=0, lambda2=0, max_iter=5), 9)
    assert all(np.array_equal(x, y_) for x, y_ in zip(a, b))


def test_smoothing_fits_its_own_series_and_beats_a_grid():
    m, t = 5, np.arange(40)
    season = np.array([1.0, -2.0, 0.5, 1.5, -1.0])
    y = 3 + 0.2 * t + season[t % m]
    sse, _, _ = lts_fit.run(y, m, np.array([0.3, 0.2, 0.1]), (3 - 0.2, 0.2, season))
    assert sse < 1e-18
    y = y + np.random.default_rng(0).standard_normal(40)
    init = lts_fit.start(y, m)
    p, sse, state = lts_fit.fit(y, m)
    grid = min(lts_fit.run(y, m, np.array([a, b, g]), init)[0] for a in np.linspace(0, 1, 11) for b in np.linspace(0, 1, 11) for g in np.linspace(0, 1, 11))
    assert sse <= grid * (1 + 1e-3) and ((p >= 0) & (p <= 1)).all()
    q, e = np.array([0.4, 0.3, 0.2]), 1e-6
    for k in range(3):
        d = np.eye(3)[k] * e
        numeric = (lts_fit.run(y, m, q + d, init)[0] - lts_fit.run(y, m, q - d, init)[0]) / (2 * e)
        assert abs(numeric - lts_fit.run(y, m, q, init)[1][k]) < 1e-3 * (1 + abs(numeric))


def make_state(rng, sizes=(4, 5), m=3, rank=2):
    p = rng.random(rank)
    return Snapshot([rng.random((s, rank)) for s in sizes], SeasonState(rng.random(rank), rng.random(rank) / 10, rng.random((m, rank)), p, p / 2, p / 3), rng.random((m, rank)), 7)


def test_online_step_is_a_gradient_step():
    """Fixed step: factors and time vector move by minus mu times the numeric gradient of the step's cost."""
    rng = np.random.default_rng(3)
    state = make_state(rng)
    mask = rng.random((4, 5)) > 0.3
    y = rng.random((4, 5)) * 3
    idx = np.argwhere(mask)
    hp = HyperParams(lambda1=0.3, lambda2=0.2, mu=0.01, step_rule="fixed")
    new, out = kernel.advance(state, idx, y[mask], hp)
    o = np.zeros_like(y)
    o[mask] = out["outlier"]
    before, ago, w = state.ring[7 % 3], state.ring[8 % 3], kernel.predict_time(state)
    cost = lambda f, v: dense.step_cost(y, mask, o, f, v, before, ago, 0.3, 0.2)
    e = 1e-6
    for n in range(2):
        for at in np.ndindex(*state.factors[n].shape):
            up, down = [u.copy() for u in state.factors], [u.copy() for u in state.factors]
            up[n][at] += e
            down[n][at] -= e
            g = (cost(up, w) - cost(down, w)) / (2 * e)
            assert abs(new.factors[n][at] - (state.factors[n][at] - 0.01 * g)) < 1e-6
    for r in range(2):
        d = np.eye(2)[r] * e
        g = (cost(state.factors, w + d) - cost(state.factors, w - d)) / (2 * e)
        assert abs(new.ring[8 % 3][r] - (w[r] - 0.01 * g)) < 1e-6


def test_rejection_and_scales():
    rng = np.random.default_rng(4)
    state = make_state(rng)
    idx = np.argwhere(np.ones((4, 5)))
    y = rng.standard_normal(20) * 50
    hp = HyperParams()
    new, out = kernel.advance(state, idx, y, hp)
    r = y - out["y_hat"] - out["outlier"]
    sigma = hp.lambda3 * hp.floor
    assert (np.abs(r) <= 2 * sigma + 1e-12).all()
    assert (out["outlier"][np.abs(y - out["y_hat"]) < 2 * sigma] == 0).all()
    ratio = out["sigma2"] / sigma**2
    assert (ratio >= 1 - hp.phi - 1e-12).all() and (ratio <= 1 - hp.phi + hp.phi * 2.52 + 1e-12).all()
    assert len(new.scales) == 20 and not state.scales


def test_empty_slice_and_time_vector_pull():
    state = make_state(np.random.default_rng(5))
    new, _ = kernel.advance(state, np.empty((0, 2), np.int64), np.empty(0), HyperParams(lambda1=0.1, lambda2=0.1))
    assert all((a == b).all() for a, b in zip(new.factors, state.factors)) and new.t == 8


def test_forecast_repeats_without_trend():
    state = make_state(np.random.default_rng(6))
    state.season.trend[:] = 0
    assert np.allclose(kernel.forecast_time(state, 2), kernel.forecast_time(state, 5))
    assert np.allclose(kernel.forecast_time(state, 1), kernel.predict_time(state))


def test_divergence_is_told():
    state = make_state(np.random.default_rng(7))
    idx = np.argwhere(np.ones((4, 5)))
    with pytest.raises(kernel.Diverged):
        for _ in range(400):
            state, _ = kernel.advance(state, idx, 1e3 * np.ones(20), HyperParams(step_rule="fixed", mu=5.0, lambda3=1e5))


def test_short_streams_and_replays():
    spec, hp = TensorSpec((4, 5), 3, 2), HyperParams(max_iter=5)
    s = Stream(spec, hp, 1)
    idx = np.argwhere(np.ones((4, 5)))
    with pytest.raises(ValueError):
        s.begin()
    for t in range(9):
        assert s.feed(t, idx, np.ones(20)) == []
    assert s.feed(11, idx, np.ones(20))[-1][1] == 11 and s.state.t == 11
    before = s.state.ring.copy()
    assert s.feed(11, idx, 5 * np.ones(20)) == [] and (s.state.ring == before).all()


@pytest.mark.parametrize("level", [(20, 10, 2), (70, 20, 5)])
def test_imputation_wins(level):
    """Lowest running error of the imputing methods, mean of three seeds, on the monthly flow shape."""
    mean = {m: np.mean([experiments.planted_run(m, "flow_month", level, seed)["rae"] for seed in (1, 2, 3)]) for m in experiments.IMPUTERS}
    assert min(mean, key=mean.get) == "robust_seasonal", mean


def test_forecasting_wins():
    mean = {m: np.mean([experiments.planted_forecast(m, "flow_month", 20, seed)["afe"] for seed in (1, 2, 3)]) for m in experiments.FORECASTERS}
    assert min(mean, key=mean.get) == "robust_seasonal", mean


def test_smoothness_helps_the_start_up():
    got = {s: np.mean([experiments.start_up(s, (90, 20, 7), seed)[-1][1] for seed in (1, 2)]) for s in ("smooth", "plain")}
    assert got["smooth"] < got["plain"], got


def test_time_grows_with_cells_not_steps():
    times = [min(float(np.median(experiments.scalability((n // 100, 100), 45))) for _ in range(3)) for n in (4_000, 16_000, 64_000)]
    assert times[2] / times[0] < 40
    slope, _, r2 = metrics.slope([4, 16, 64], times)
    assert slope > 0 and r2 > 0.9


def test_capabilities():
    """Flags as published, and methods that behave so."""
    spec = TensorSpec((4, 5), 3, 2)
    idx = np.argwhere(np.ones((4, 5)))
    assert set(MAKERS) == set(CAPABILITIES) - {"robust_seasonal"}
    for name, flags in CAPABILITIES.items():
        f = dict(zip(FLAGS, flags))
        if name == "robust_seasonal":
            assert all(flags)
            continue
        model = MAKERS[name](spec)
        rng = np.random.default_rng(0)
        for t in range(12):
            part = idx if not f["missing"] else idx[rng.random(20) > 0.3]
            model.feed(part, 1 + 0.1 * rng.random(len(part)) + 0.2 * (t % 3))
        if f["forecasting"]:
            assert np.isfinite(model.forecast(idx, 2)).all()
        else:
            with pytest.raises(NotImplementedError):
                model.forecast(idx, 1)
        if f["imputation"]:
            assert np.isfinite(model.impute(idx)).all()
    with pytest.raises(ValueError):
        methods.SeasonalStreamMf(spec).feed(idx[:3], np.ones(3))
    grown = methods.MultiAspectStream(spec)
    grown.feed(idx, np.ones(20))
    grown.feed(np.array([[6, 7]]), np.ones(1))
    assert [len(u) for u in grown.factors] == [7, 8]


def test_factor_match_ignores_order_sign_and_scale():
    f = np.random.default_rng(0).random((20, 3))
    assert metrics.factor_nre(-3 * f[:, [1, 2, 0]], f) < 1e-9


def test_corruption_shares():
    x, _ = planted.dense((20, 20), 50, 2, 10, 0)
    y, mask = apply_dense(x, 30, 20, 4, 0)
    assert abs(mask.mean() - 0.7) < 0.02 and abs((y != x).mean() - 0.2) < 0.02
    assert np.isclose(np.abs(y - x).max(), 4 * x.max())


def test_estimated_first_states():
    """First states from least squares: no other states have less error, and the fit's error never rises."""
    rng = np.random.default_rng(4)
    m, n = 4, 40
    y = 3 + 0.2 * np.arange(n) + np.tile([1, -1, 2, -2], n // m) + 0.3 * rng.standard_normal(n)
    p = np.array([0.2, 0.1, 0.3])
    init = lts_fit.first_states(y, m, p)
    best = lts_fit.run(y, m, p, init)[0]
    for k in range(m + 2):
        for e in (-0.05, 0.05):
            moved = [init[0], init[1], init[2].copy()]
            if k < 2:
                moved[k] += e
            else:
                moved[2][k - 2] += e
            assert lts_fit.run(y, m, p, moved)[0] >= best - 1e-9
    assert best <= lts_fit.run(y, m, p, lts_fit.start(y, m))[0]
    assert lts_fit.fit_states(y, m)[1] <= lts_fit.fit(y, m)[1] + 1e-12


def test_drawn_factors_are_spread_and_do_not_hang_on_the_rows_asked():
    from cellstream.plans import smooth_als

    u = smooth_als.initial_factors((4000, 10), 3, 5)[0]
    assert abs(u.mean() - 0.5) < 0.02 and abs(u.std() - 12**-0.5) < 0.01 and abs(np.corrcoef(u.T)[0, 1]) < 0.05
    assert (smooth_als.drawn(0, np.array([17, 3]), 3, 5) == u[[17, 3]]).all()
    z = smooth_als.initial_factors((4000,), 2, 5, "normal")[0]
    assert abs(z.mean()) < 0.04 and abs(z.std() - 1) < 0.04


def test_bayesian_rival_follows_a_clean_stream():
    from cellstream.baselines import methods
    from cellstream.model import TensorSpec
    from cellstream.sources import planted

    x, _ = planted.dense((8, 9), 40, 2, 6, 2)
    idx = experiments.coordinates((8, 9))
    m, errors = methods.BayesRobustStream(TensorSpec((8, 9), 6, 2)), []
    for t in range(40):
        m.feed(idx, x[..., t].ravel())
        errors.append(np.linalg.norm(m.impute(idx) - x[..., t].ravel()) / np.linalg.norm(x[..., t]))
    assert np.median(errors[10:]) < 0.3
