"""State algebra, draws and functions against dense or numeric twins."""

import math

import numpy as np
import pytest

from gradvb.draws import DrawSource, direction_numbers, scramble, sobol, star_discrepancy_l2, to_unit
from gradvb.families import CholeskyState, DiagonalState, FactorState, Gaussian, NormalPrior, RankOneState, bordered_inverse, init_state, rank_one_inverse
from gradvb.fit import StepSize, warm_start, window_change
from gradvb.functions.scalars import norm_cdf_np, norm_ppf_np
from gradvb.models import GaussianModel, Logit, Poisson, Probit
from gradvb.sums import Sums


def state(d=5, seed=0):
    rng = np.random.default_rng(seed)
    return RankOneState(rng.normal(size=d), rng.normal(size=d), 0.7)


def all_states():
    rng = np.random.default_rng(1)
    root = np.tril(rng.normal(size=(4, 4)) * 0.2) + np.eye(4)
    return [state(4), FactorState(rng.normal(size=4), rng.normal(size=(4, 2)), 0.5), CholeskyState(rng.normal(size=4), root), DiagonalState(rng.normal(size=4), np.array([0.3, 1.0, 0.6, 2.0]))]


def test_natural_direction_of_one_factor_is_the_dense_solve():
    s = state()
    g = np.random.default_rng(2).normal(size=11)
    assert np.allclose(s.natural(g), np.linalg.solve(s.fisher(), g), rtol=1e-12)
    assert np.allclose(s.solve(g[:5]), np.linalg.solve(s.cov(), g[:5]))
    assert np.isclose(s.logdet(), np.linalg.slogdet(s.cov())[1])


@pytest.mark.parametrize("s", all_states(), ids=lambda s: type(s).__name__)
def test_analytic_part_matches_finite_differences(s):
    prior, h = NormalPrior(3.0), 1e-6
    value, grad = s.analytic_part(prior)
    base, general = Gaussian.analytic_part(s, prior)
    assert np.isclose(value, base) and np.allclose(grad, general)
    for k in range(len(grad)):
        e = np.zeros(len(grad))
        e[k] = h
        slope = (s.moved(e).analytic_part(prior)[0] - s.moved(-e).analytic_part(prior)[0]) / (2 * h)
        assert np.isclose(slope, grad[k], atol=1e-5)


def test_entropy_enters_with_a_plus():
    """With the opposite sign the gradient in c would point the other way."""
    s, prior = state(), NormalPrior(50.0)
    grad = s.analytic_part(prior)[1][-1]
    d, bb = 5, s.b @ s.b
    turned = -d * s.c / prior.var - (d - bb / (s.c**2 + bb)) / s.c
    assert grad > 0 > turned


@pytest.mark.parametrize("s", all_states(), ids=lambda s: type(s).__name__)
def test_score_has_the_fisher_matrix_as_covariance(s):
    rng = np.random.default_rng(3)
    theta = s.sample(rng.normal(size=(200_000, s.noise_dim())))
    score = s.score(theta)
    assert np.abs(score.mean(axis=0)).max() < 0.05 * np.sqrt(np.diag(s.fisher())).max()
    got, want = np.cov(score.T), s.fisher()
    assert np.abs(got - want).max() < 0.03 * np.abs(want).max()


def test_singular_cases_are_refused():
    with pytest.raises(ValueError):
        RankOneState(np.zeros(1), np.ones(1), 1.0)
    with pytest.raises(ValueError):
        RankOneState(np.zeros(3), np.zeros(3), 1.0)
    with pytest.raises(ValueError):
        state().moved(np.append(np.zeros(10), -1.0))


def test_inverse_identities():
    rng = np.random.default_rng(4)
    a = rng.normal(size=(4, 4))
    a = a @ a.T + np.eye(4)
    u, v = rng.normal(size=4), rng.normal(size=4)
    assert np.allclose(rank_one_inverse(np.linalg.inv(a), u, v), np.linalg.inv(a + np.outer(u, v)))
    whole = np.block([[a, u[:, None]], [u[None, :], np.array([[9.0]])]])
    assert np.allclose(bordered_inverse(np.linalg.inv(a), u, 9.0), np.linalg.inv(whole))


def test_start_from_information():
    rng = np.random.default_rng(5)
    a = rng.normal(size=(4, 4))
    info = a @ a.T + np.eye(4)
    s = init_state(np.zeros(4), info, 3.0)
    assert np.isclose(np.trace(s.cov()), np.trace(np.linalg.inv(3 * info)))
    assert s.b[np.abs(s.b).argmax()] > 0


def test_warm_start_finds_the_best_member_for_a_normal_target():
    info = np.array([[1900.0, 560, 540, 990], [560, 2450, 170, 280], [540, 170, 2130, 270], [990, 280, 270, 850]]) * 10
    anchor = Sums(np.zeros(4), 1000, 0.0, np.array([3.0, -2.0, 1.0, 0.5]), -info)
    s = warm_start(init_state(np.zeros(4), info, 1.0), anchor, NormalPrior(50.0), 4000)
    assert np.allclose(s.mu, np.linalg.solve(info + np.eye(4) / 50, anchor.grad), atol=1e-6)
    data = np.concatenate([anchor.grad + anchor.hess @ s.mu, 0.5 * np.einsum("ij,pji->p", anchor.hess, s.cov_basis())])
    assert np.abs(s.natural(s.analytic_part(NormalPrior(50.0))[1] + data)).max() < 1e-6


def test_net_margins_and_stratification():
    p = sobol(256, 13)
    for j in range(13):
        assert len(set((p[:, j] >> np.uint64(24)).tolist())) == 256
    cells = set(zip((p[:, 0] >> np.uint64(28)).tolist(), (p[:, 1] >> np.uint64(28)).tolist(), strict=True))
    assert len(cells) == 256
    assert int(direction_numbers(0)[0]) == 2**31


@pytest.mark.parametrize("kind", ["nested", "linear", "shift"])
def test_scrambles_keep_strata_and_centre(kind):
    means = []
    for seed in range(40):
        u = to_unit(scramble(sobol(64, 4), seed, kind))
        for j in range(4):
            assert len(set(np.floor(u[:, j] * 64).astype(int).tolist())) == 64
        means.append(u[5])
    spread = np.std(means, axis=0) / np.sqrt(len(means))
    assert (np.abs(np.mean(means, axis=0) - 0.5) < 4.5 * spread).all()


def test_quasi_random_draws_beat_plain_ones():
    values = {k: np.var([np.exp(0.3 * DrawSource(k, s).normals(256, 5, 1).sum(axis=1)).mean() for s in range(30)]) for k in ("mc", "rqmc")}
    assert values["rqmc"] < 0.5 * values["mc"]
    rng = np.random.default_rng(0)
    assert star_discrepancy_l2(to_unit(sobol(256, 3))) < star_discrepancy_l2(rng.random((256, 3)))
    with pytest.warns(UserWarning):
        DrawSource("rqmc", 1).normals(100, 3, 0)


def test_normal_functions():
    x = np.linspace(-8, 8, 321)
    assert np.abs(norm_cdf_np(x) - [0.5 * math.erfc(-v / math.sqrt(2)) for v in x]).max() < 1e-14
    u = np.array([1e-12, 1e-5, 0.02, 0.3, 0.5, 0.9, 1 - 1e-9])
    assert np.allclose(norm_cdf_np(norm_ppf_np(u)), u, rtol=1e-9)


@pytest.mark.parametrize("model", [Logit(), GaussianModel(1.3), Poisson(), Probit()], ids=lambda m: type(m).__name__)
def test_row_terms_are_derivatives(model):
    z, y, h = np.linspace(-2, 2, 9), np.array([0, 1, 0, 1, 1, 0, 1, 0, 1.0]), 1e-5
    value, first, second = model.block(z, y)
    up, down = model.block(z + h, y), model.block(z - h, y)
    assert np.allclose((up[0] - down[0]) / (2 * h), first, atol=1e-7)
    assert np.allclose((up[1] - down[1]) / (2 * h), second, atol=1e-6)


def test_steps_and_window():
    assert StepSize()(0) == 1 and StepSize()(3) == 0.25
    with pytest.raises(ValueError):
        StepSize("power", power=0.4)(1)
    assert window_change([1, 2, 3, 4, 5], 5) is None
    assert np.isclose(window_change([1, 2, 3, 4, 5, 6], 5), 1.0)


def test_bound_curves_as_the_fisher_matrix_at_the_target():
    """For a normal target inside the family, the bound's second derivative at the optimum is minus the Fisher matrix."""
    precision = np.array([[3.0, 0.6, -0.2], [0.6, 2.0, 0.4], [-0.2, 0.4, 1.5]])
    best, prior, h = CholeskyState(np.zeros(3), np.linalg.cholesky(np.linalg.inv(precision))), NormalPrior(1e12), 1e-5

    def gradient(s):
        data = np.concatenate([-precision @ s.mu, -0.5 * np.einsum("ij,pji->p", precision, s.cov_basis())])
        return s.analytic_part(prior)[1] + data

    assert np.abs(gradient(best)).max() < 1e-9
    n = len(gradient(best))
    curve = np.array([(gradient(best.moved(h * np.eye(n)[k])) - gradient(best.moved(-h * np.eye(n)[k]))) / (2 * h) for k in range(n)])
    assert np.allclose(curve, -best.fisher(), atol=1e-5)


def test_plain_steps_may_turn_the_sign_of_c():
    """A state that allows both signs goes on where the other refuses, and is the same distribution."""
    at = (np.array([0.1, -0.2, 0.3]), np.array([0.2, 0.1, -0.1]))
    plus, minus = RankOneState(*at, 0.3), RankOneState(*at, 0.3, signed=True).moved(np.array([0.0] * 6 + [-0.6]))
    with pytest.raises(ValueError):
        plus.moved(np.array([0.0] * 6 + [-0.6]))
    assert minus.c == pytest.approx(-0.3) and np.allclose(plus.cov(), minus.cov()) and plus.logdet() == pytest.approx(minus.logdet())
    mirror = np.array([1.0] * 6 + [-1.0])
    gradient = np.arange(1.0, 8.0)
    assert np.allclose(minus.natural(gradient * mirror), plus.natural(gradient) * mirror)
    assert np.allclose(minus.analytic_part(NormalPrior())[1], plus.analytic_part(NormalPrior())[1] * mirror)
