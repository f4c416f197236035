"""Codes, coded descent against central descent, stragglers, baselines, guards."""

import inspect
import itertools

import numpy as np
import pytest

from padgrad.functions.fixedpoint import PRIMES
from padgrad.operators import baselines, gradcode, latency, measures, moments, sharing
from padgrad.operators.training import MODES, CodedDevices, schedule, train_coded
from padgrad.plans import planner


@pytest.mark.parametrize("d,alpha,kind", [(5, 1, "nullspace"), (5, 3, "nullspace"), (6, 4, "nullspace"), (8, 8, "nullspace"), (6, 3, "blocks"), (7, 3, "circulant"), (8, 4, "circulant")])
def test_every_pattern_decodes(d, alpha, kind):
    b = gradcode.build_encoder(d, alpha, 1, kind)
    if kind != "blocks":
        for i in range(d):
            assert sorted(np.flatnonzero(np.abs(b[i]) > 1e-12)) == sorted(gradcode.support(d, alpha, i))
    for arrived in itertools.combinations(range(d), d - alpha + 1):
        assert np.abs(gradcode.decode_vector(b, arrived) @ b - 1).max() < 1e-8


@pytest.mark.parametrize("alpha", [1, 2, 6, 16, 23, 24, 25])
def test_sampled_patterns_at_25(alpha):
    assert gradcode.conditioning(gradcode.build_encoder(25, alpha, 1), alpha, 60)["residual"] < 1e-9


def test_too_few_answers():
    b = gradcode.build_encoder(7, 3, 1)
    with pytest.raises(gradcode.Undecodable):
        gradcode.decode_vector(b, [0, 1, 2, 3])
    f = gradcode.field_encoder(7, 3, PRIMES[0], 1)
    with pytest.raises(gradcode.Undecodable):
        gradcode.field_decode_vector(f, [0, 1, 2, 3], PRIMES[0])


def test_field_code_is_exact():
    p = PRIMES[1]
    b = gradcode.field_encoder(9, 4, p, 2)
    for arrived in itertools.combinations(range(9), 6):
        a = gradcode.field_decode_vector(b, arrived, p).astype(object)
        assert ((a @ b.astype(object)) % p == 1).all()


def test_unrank():
    assert [gradcode.unrank(i, 5, 3) for i in range(10)] == [list(c) for c in itertools.combinations(range(5), 3)]


@pytest.fixture(scope="module")
def problem():
    rng = np.random.default_rng(0)
    n, d, c, D = 300, 6, 2, 10
    x = rng.normal(size=(n, d))
    y = x @ rng.normal(size=(d, c)) + 0.01 * rng.normal(size=(n, c))
    dev = np.minimum(np.arange(n) // 20, D - 1)  # unequal devices
    g = np.stack([x[dev == i].T @ x[dev == i] for i in range(D)])
    h = np.stack([x[dev == i].T @ y[dev == i] for i in range(D)])
    return g, h, n, np.bincount(dev, minlength=D), latency.np_epoch_times(latency.class_rates(D), 50, 1e6, 1e4, 3)


@pytest.mark.parametrize("mode", MODES)
@pytest.mark.parametrize("alpha", [1, 4, 10])
def test_coded_equals_central(problem, mode, alpha):
    g, h, n, _, times = problem
    mu = schedule(0.5)
    want = baselines.train_central(g, h, n, 50, mu=mu).theta
    got = train_coded(g, h, n, alpha, times, mu=mu, mode=mode)
    assert np.abs(got.theta - want).max() < (1e-4 if mode == "literal" else 1e-6)


def test_single_gradient_exact_in_field(problem):
    g, h, n, _, _ = problem
    q = np.round(g * 2**24) / 2**24
    first = np.round(-h * 2**24) / 2**24
    dev = CodedDevices(q, first, 4, "field", 1)
    change = np.round(np.random.default_rng(1).normal(size=h.shape[1:]) * 2**10) / 2**10
    want = (q @ change + first).sum(axis=0)
    assert np.abs(dev.gradient_sum(change, [0, 2, 3, 5, 7, 8, 9]) - want).max() < 1e-9
    with pytest.raises(gradcode.Undecodable):
        dev.gradient_sum(change, [0, 1, 2, 3, 4, 5])


def test_converges_to_closed_form(problem):
    g, h, n, _, times = problem
    long = np.repeat(times, 20, axis=0)
    got = train_coded(g, h, n, 4, long, mu=schedule(0.5, {}))
    assert measures.optimum_gap(got.theta, moments.ridge_solve(g, h, n, 9e-6)) < 1e-6


def test_guards(problem):
    g, h, n, _, times = problem
    with pytest.raises(ValueError):
        train_coded(g, h, n, 4, times, local_steps=2)
    assert "shares" not in inspect.signature(sharing.decode).parameters
    assert "master_seed" not in inspect.signature(sharing.answers).parameters


def test_baselines_agree_where_they_must(problem):
    g, h, n, counts, times = problem
    mu = schedule(0.5)
    want = baselines.train_central(g, h, n, 50, mu=mu).theta
    assert np.allclose(baselines.train_conventional(g, h, counts, times, mu=mu).theta, want)
    assert np.allclose(baselines.train_drop_slowest(g, h, counts, times, 10, mu=mu).theta, want)
    assert np.allclose(baselines.train_stale(g, h, n, times, keep=10, mu=mu).theta, want)
    assert np.allclose(baselines.train_uncoded(g, h, n, times, mu=mu).theta, baselines.train_replicated(g, h, n, times, mu=mu).theta)
    dropped = baselines.train_drop_slowest(g, h, counts, times, 5, mu=mu).theta
    assert np.abs(dropped - want).max() > 1e-4


def test_latency_laws():
    t = latency.np_epoch_times(latency.class_rates(25), 4000, 4e7, 1e-9, 1)
    fast, slow = 4e7 / 25e6, 4e7 / 1.25e6
    assert abs(t[:, 0].mean() / (1.5 * fast) - 1) < 0.05 and abs(t[:, -1].mean() / (1.5 * slow) - 1) < 0.05
    assert np.mean([latency.sends_from_uniform(u, 0.1) for u in np.linspace(1e-6, 1 - 1e-6, 20001)]) == pytest.approx(latency.geometric_mean_sends(0.1), rel=0.01)
    s = np.sort(t, axis=1)
    epoch = [s[:, 25 - a].mean() for a in (1, 6, 16, 23, 25)]
    assert epoch == sorted(epoch, reverse=True)
    share = [latency.np_sharing_time(latency.class_rates(25), a, 200, 10, 48, 1) for a in (6, 16, 23, 25)]
    assert share == sorted(share)


def test_planner():
    assert planner.use_moments(10**9, 2000, 10, 500)
    assert not planner.use_moments(100, 2000, 10, 1)
    assert planner.moment_tasks(800_000, 10**14, 2000, 10) < 400_000 and planner.moment_tasks(8, 10**9, 64, 10) == 8
    assert planner.lanes_suffice(2000) and planner.decoder_plan(25, 16) == "on_demand" and planner.epoch_engine(25, 64, 10) == "local"
