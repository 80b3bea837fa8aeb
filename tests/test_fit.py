"""Estimators are unbiased, and fits agree with exact ones and with planted truth."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from gradvb.baselines import divide_and_combine, laplace, rw_mcmc
from gradvb.designs import FLIGHT_BETA, event_flights, flights, nest_panels, w3_panels
from gradvb.estimators import SampleProvider, block_kernel, column_kernel, from_frame, remainders, sufficient_cells
from gradvb.families import NormalPrior
from gradvb.fit import FitConfig, ascend, prepare
from gradvb.models import Logit, Probit
from gradvb.panel import Integrator, debiased_score, laplace_proposal, panel_sums, panel_terms, to_block
from gradvb.sampling import build_store, draw_indices, stratified, tile_counts, with_replacement
from gradvb.sums import Sums, chunk_rollup, exact_sums, fit_mle
from gradvb.sources.tables import explain_text

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def obs(spark):
    return flights(spark, SF).cache()


@pytest.fixture(scope="module")
def ready(obs):
    return prepare(obs, cfg=FitConfig(tiles=8))


def test_planted_counts_and_fit(obs):
    assert obs.agg(F.sum("y")).first()[0] == 1309
    assert np.allclose(fit_mle(obs).theta, (-1.6709, -0.1229, 0.0238, 0.8268), atol=2e-4)
    best, sd = laplace(obs)
    assert (np.abs((best.theta - FLIGHT_BETA) / sd) < 4).all()


def test_column_and_block_sums_agree(obs):
    theta = np.array(FLIGHT_BETA)
    s = exact_sums(obs, theta)
    grad, ll, _, n = from_frame(block_kernel(obs, theta[None, :], None, None, Logit(), "none"), theta[None, :], None, "none")
    assert np.allclose(grad[0], s.grad) and np.isclose(ll[0], s.loglik)
    p = exact_sums(obs, theta, Probit(), 1)
    grad, ll, _, _ = from_frame(block_kernel(obs, theta[None, :], None, None, Probit(), "none"), theta[None, :], None, "none")
    assert np.allclose(grad[0], p.grad) and np.isclose(ll[0], p.loglik)


def test_all_samples_of_one_average_to_the_exact_gradient(spark):
    """Enumeration: the mean over every sample of one row is the full gradient, whatever the surrogate."""
    tiny = event_flights(spark, SF).orderBy("obs_key").limit(200).toPandas()
    x, y = tiny[[f"x{k}" for k in range(4)]].to_numpy(), tiny["y"].to_numpy()
    anchor_at, theta = np.array([-1.4, -0.3, 0.1, 0.6]), np.array([[-1.6, -0.1, 0.2, 0.8]])
    model = Logit()
    _, a, b = model.block(x @ anchor_at, y)
    anchor = Sums(anchor_at, 200, float(model.block(x @ anchor_at, y)[0].sum()), x.T @ a, (x * b[:, None]).T @ x)
    exact = x.T @ model.block(x @ theta[0], y)[1]
    from gradvb.estimators import assemble

    for surrogate in ("none", "constant", "linear"):
        singles = [assemble(theta, anchor, *(v * 200 for v in remainders(x[i : i + 1], y[i : i + 1], np.ones(1), theta, anchor, model, surrogate)[::2]), surrogate)[0][0] for i in range(200)]
        assert np.allclose(np.mean(singles, axis=0), exact)


def test_column_kernel_gives_the_block_kernels_remainders(obs, ready):
    thetas = ready.anchor.theta + np.array([[0.02, 0, 0.01, 0], [0, -0.03, 0, 0.02]])
    sample = obs.limit(500)
    got = {r.draw_id: [r[f"g{j}"] for j in range(4)] for r in column_kernel(sample, thetas, ready.anchor, 2.0).collect()}
    x = sample.toPandas()
    want = 2 * remainders(x[[f"x{k}" for k in range(4)]].to_numpy(), x["y"].to_numpy(), np.ones(500), thetas, ready.anchor, Logit(), "linear")[0]
    assert np.allclose([got[0], got[1]], want, atol=1e-8)


def test_index_draws_are_multinomial_and_seeded():
    counts = {0: 10, 3: 30, 5: 60}
    tile, row = draw_indices(counts, 20_000, 4, 1)
    assert len(tile) == 20_000 and all(row[tile == t].max() == n - 1 for t, n in counts.items())
    assert np.allclose([np.mean(tile == t) for t in counts], [0.1, 0.3, 0.6], atol=0.02)
    again = draw_indices(counts, 20_000, 4, 1)
    assert (again[1] == row).all() and not (draw_indices(counts, 20_000, 4, 2)[1] == row).all()


def test_store_sample_and_weights(obs):
    store = build_store(obs, 8).cache()
    counts = tile_counts(store)
    assert sum(counts.values()) == 6000
    got, weight = with_replacement(store, counts, 300, 1)
    assert got.agg(F.sum("w")).first()[0] == 300 and weight == 20
    per, _ = with_replacement(store, counts, 50, 1, 0, 4)
    assert {r.draw_id: r.w for r in per.groupBy("draw_id").agg(F.sum("w").alias("w")).collect()} == {k: 50.0 for k in range(4)}
    strata = stratified(store.withColumnRenamed("tile", "chunk_id"), 0.1, 3)
    assert np.isclose(strata.agg(F.sum("w")).first()[0], 6000)
    with pytest.raises(ValueError):
        SampleProvider(store, None, 6001, counts=counts)


def test_rollup_total_is_the_sum_of_chunks(obs):
    rows = chunk_rollup(build_store(obs, 4).withColumnRenamed("tile", "chunk_id"), FLIGHT_BETA).collect()
    total = next(r for r in rows if r.chunk_id is None)
    assert total.n == sum(r.n for r in rows if r.chunk_id is not None)
    assert np.isclose(total.g0, sum(r.g0 for r in rows if r.chunk_id is not None))


def test_estimates_are_unbiased_and_the_surrogate_cuts_variance(obs, ready):
    theta = (ready.anchor.theta + 0.03)[None, :]
    exact = exact_sums(obs, theta[0], order=1).grad
    spread = {}
    for surrogate in ("none", "linear"):
        p = SampleProvider(ready.store, ready.anchor, 100, surrogate=surrogate, block=200, counts=ready.counts)
        got = np.array([p.estimate(theta, t).grad[0] for t in range(200)])
        z = (got.mean(axis=0) - exact) / (got.std(axis=0, ddof=1) / np.sqrt(200))
        assert (np.abs(z) < 4.5).all()
        spread[surrogate] = got.std(axis=0)
    assert (spread["linear"] < 0.05 * spread["none"]).all()


@pytest.mark.parametrize("scheme", ["replacement", "chunks", "tile", "slice"])
def test_engines_and_schemes_agree_with_exact_vb(obs, ready, scheme):
    settled = FitConfig(tolerance=1e-7).settled()
    exact = ascend(sufficient_cells(obs), ready.start(settled), None, settled, curvature=ready.anchor.hess)
    cfg = FitConfig(m=0.25 if scheme == "tile" else 0.05, tolerance=1e-5, scheme=scheme, max_iter=8 if scheme == "tile" else 60, s=64).settled()
    fit = ascend(ready.provider(cfg), ready.start(cfg), None, cfg)
    mean, sd = exact.state.marginals()
    got_mean, got_sd = fit.state.marginals()
    assert fit.status in ("settled", "max_iter")
    assert (np.abs(got_mean - mean) < 0.35 * sd).all() and np.allclose(got_sd, sd, rtol=0.25)


def test_driver_and_spark_engines_give_the_same_estimates(ready):
    thetas = ready.anchor.theta + np.random.default_rng(0).normal(size=(8, 4)) * 0.05
    a = SampleProvider(ready.store, ready.anchor, 200, engine="driver", counts=ready.counts).estimate(thetas, 3)
    b = SampleProvider(ready.store, ready.anchor, 200, engine="spark", counts=ready.counts).estimate(thetas, 3)
    assert np.allclose(a.grad, b.grad) and np.allclose(a.loglik, b.loglik)


def test_score_function_and_reparameterised_gradients_have_one_mean(ready):
    from gradvb.draws import DrawSource
    from gradvb.fit import bound_gradient

    p = SampleProvider(ready.store, ready.anchor, 0.1, counts=ready.counts)
    state, out = ready.start(FitConfig().settled()), {"reparam": [], "score": []}
    for t in range(40):
        eps = DrawSource("mc", t).normals(256, state.noise_dim(), 0)
        thetas = state.sample(eps)
        got = p.estimate(thetas, 0)
        for kind in out:
            out[kind].append(bound_gradient(state, eps, thetas, got.grad, got.loglik, NormalPrior(), FitConfig(estimator=kind)))
    gap = np.mean(out["reparam"], axis=0) - np.mean(out["score"], axis=0)
    se = np.sqrt((np.var(out["reparam"], axis=0, ddof=1) + np.var(out["score"], axis=0, ddof=1)) / 40)
    assert (np.abs(gap) < 4.5 * se).all()


def test_chain_agrees_with_the_fit(obs, ready):
    cfg = FitConfig(m=0.1, tolerance=1e-6).settled()
    mean, sd = ascend(ready.provider(cfg), ready.start(cfg), None, cfg).state.marginals()
    chain = rw_mcmc(obs, iters=30_000, burn=10_000)
    assert (np.abs(chain.draws.mean(axis=0) - mean) < 0.15 * chain.draws.std(axis=0)).all()
    assert np.allclose(sd[[0, 3]], chain.draws.std(axis=0)[[0, 3]], rtol=0.1)  # one factor understates the other two
    assert 0.1 < chain.accepted.mean() < 0.6


def test_divide_and_combine_moves_with_chunks_but_sums_do_not(obs):
    few, _ = divide_and_combine(obs, 2)
    many, _ = divide_and_combine(obs, 24)
    whole = fit_mle(obs).theta
    assert np.abs(few - whole).max() < np.abs(many - whole).max()


def test_scan_reads_only_what_the_design_needs(spark):
    plan = explain_text(flights(spark, SF))
    assert "l_tax" not in plan and "l_quantity" in plan and "ReadSchema" in plan


@pytest.fixture(scope="module")
def panels(spark):
    return nest_panels(w3_panels(spark, SF).drop("panel_rank")).cache()


def test_panel_derivatives_by_quadrature(panels):
    rows = panels.limit(20).collect()
    block = to_block([r.panel_id for r in rows], [r.y for r in rows], [r.x for r in rows])
    how, theta, h = Integrator("quadrature", 40), np.append(np.linspace(-0.5, 0.5, 11), 0.3), 1e-5
    nodes = how.nodes(block, theta)
    _, score, bend = panel_terms(block, theta, how, nodes, True)
    for k in range(12):
        e = np.zeros(12)
        e[k] = h
        up, down = panel_terms(block, theta + e, how, nodes), panel_terms(block, theta - e, how, nodes)
        assert np.allclose((up[0] - down[0]) / (2 * h), score[:, k], atol=1e-5)
        assert np.allclose((up[1] - down[1]) / (2 * h), bend[:, :, k], atol=1e-4)


def test_common_draws_shrink_panel_remainders(panels):
    rows = panels.collect()
    block = to_block([r.panel_id for r in rows], [r.y for r in rows], [r.x for r in rows])
    how = Integrator("prior", 256, "mc")
    anchor = np.append(np.full(11, 0.4), 0.2)
    theta = anchor + 0.05
    same, other = how.nodes(block, anchor), Integrator("prior", 256, "mc", 77).nodes(block, anchor)
    _, s0, h0 = panel_terms(block, anchor, how, same, True)
    near = panel_terms(block, theta, how, same)[1] - s0 - h0 @ (theta - anchor)
    far = panel_terms(block, theta, how, other)[1] - s0 - h0 @ (theta - anchor)
    assert near[:, :11].std() < 0.3 * far[:, :11].std()


def test_proposals_agree_with_quadrature(panels):
    theta = np.append(np.full(11, 0.3), 0.4)
    truth = panel_sums(panels, theta, Integrator("quadrature", 40))
    for kind in ("prior", "laplace", "defensive"):
        got = panel_sums(panels, theta, Integrator(kind, 512, "rqmc"))
        assert abs(got.loglik - truth.loglik) < 0.2
        assert np.abs(got.grad - truth.grad).max() < 1.0


def test_debiased_scores_average_to_the_truth(panels):
    rows = panels.limit(10).collect()
    block = to_block([r.panel_id for r in rows], [r.y for r in rows], [r.x for r in rows])
    theta = np.append(np.full(11, 0.3), 0.4)
    how = Integrator("quadrature", 40)
    truth = panel_terms(block, theta, how, how.nodes(block, theta))[1].sum(axis=0)
    got = np.array([debiased_score(block, theta, 16, s).sum(axis=0) for s in range(400)])
    z = (got.mean(axis=0) - truth) / (got.std(axis=0, ddof=1) / np.sqrt(len(got)))
    assert (np.abs(z) < 4.5).all()


def test_laplace_proposal_is_the_mode():
    block = to_block([1, 2], [np.array([1.0, 1.0, 0.0]), np.array([0.0])], [np.ones(3), np.ones(1)])
    mode, sd = laplace_proposal(block, np.array([0.2, 0.1]))
    assert mode[0] > 0 > mode[1] and (sd > 0).all()


def test_separated_data_stays_finite(spark):
    rows = [(str(k), float(k > 20), 1.0, k / 40) for k in range(41)]
    best = fit_mle(spark.createDataFrame(rows, "obs_key string, y double, x0 double, x1 double"))
    assert np.isfinite(best.theta).all()


def test_fetches_of_samples_are_bounded_and_change_no_estimate(spark, monkeypatch):
    """A block of iterations brings no more rows to the driver than allowed, by Arrow also where the session has it off."""
    from gradvb import estimators

    ready = prepare(flights(spark, SF))
    theta = ready.anchor.theta[None, :] + 0.01
    named = "spark.sql.execution.arrow.pyspark.enabled"
    before = spark.conf.get(named)
    try:
        for scheme in ("replacement", "slice", "chunks"):
            spark.conf.set(named, "true")
            wide = SampleProvider(ready.store, ready.anchor, 100, scheme=scheme, counts=ready.counts, block=6)
            spark.conf.set(named, "false")
            with monkeypatch.context() as patch:
                patch.setattr(estimators, "FETCH_ROWS", 250)
                narrow = SampleProvider(ready.store, ready.anchor, 100, scheme=scheme, counts=ready.counts, block=6)
            assert (wide.block, narrow.block) == (6, 2)
            for t in range(5):
                assert np.allclose(wide.estimate(theta, t).grad, narrow.estimate(theta, t).grad)
            assert sum(len(y) for _, y, _ in narrow.held.values()) <= 250
    finally:
        spark.conf.set(named, before)
        ready.store.unpersist()


def test_a_small_store_is_held_and_gives_the_fetched_samples_without_jobs(spark):
    ready = prepare(flights(spark, SF))
    thetas = ready.anchor.theta[None, :] + np.array([[0.01], [-0.02]])
    try:
        for scheme in ("replacement", "slice", "chunks"):
            kept, fetched = (SampleProvider(ready.store, ready.anchor, 100, scheme=scheme, counts=ready.counts, hold=hold) for hold in (True, False))
            for t in range(3):
                a, b = kept.estimate(thetas, t), fetched.estimate(thetas, t)
                assert np.allclose(a.grad, b.grad) and np.allclose(a.loglik, b.loglik) and np.isclose(a.variance, b.variance) and a.rows == b.rows
            kept.store = None
            kept.estimate(thetas, 50)
    finally:
        ready.store.unpersist()
