"""Methods, baselines and measures end to end, on small tables."""

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from gradvb import baselines, measures
from gradvb.designs import flights, nest_panels, w3_panels
from gradvb.estimators import SampleProvider
from gradvb.families import NormalPrior
from gradvb.fit import FitConfig, StepSize, ascend, choose_factors, first_state, prepare, replicate
from gradvb.functions.transforms import TRANSFORMS, Transformed
from gradvb.models import Logit, NumericModel
from gradvb.panel import Integrator, PanelProvider, fit_ngvb_panels, fit_panel_anchor, panel_sums, rank_panels
from gradvb.plans.chunks import ChunkReader, exact_map, reduce_chunks, reduced_estimate
from gradvb.sampling import build_store, lay_out, slice_ranges, slice_sample, spread_indices, tile_counts, with_replacement
from gradvb.sources.tables import explain_text
from gradvb.sums import exact_sums, fit_anchor, fit_mle

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def obs(spark):
    return flights(spark, SF).cache()


@pytest.fixture(scope="module")
def ready(obs):
    return prepare(obs)


@pytest.fixture(scope="module")
def panels(spark):
    return rank_panels(nest_panels(w3_panels(spark, SF).drop("panel_rank")), 8).cache()


# layout and samples


def test_steps_and_defaults():
    cfg = FitConfig()
    assert (cfg.start, cfg.bound_steps, cfg.tiles) == ("subset", False, 0)
    assert [cfg.step(t) for t in range(3)] == [1 / 5, 1 / 6, 1 / 7] and StepSize()(0) == 1
    assert cfg.settled().start == "warm" and cfg.settled().bound_steps


def test_plain_loop_moves_from_the_subset_towards_the_exact_fit(obs, ready):
    cfg = FitConfig(m=0.1, tolerance=1e-7)
    fit = ascend(ready.provider(cfg), ready.start(cfg), None, cfg, ready.anchor.theta)
    best = fit_mle(obs).theta
    assert fit.status == "settled" and 15 <= fit.iterations <= 70
    assert np.linalg.norm(fit.state.mu - best) < 0.5 * np.linalg.norm(ready.anchor.theta - best)


def test_written_store_is_pruned(spark, obs):
    store = lay_out(obs, 4, cached_rows=0)
    counts = tile_counts(store)
    assert sum(counts.values()) == 6000 and len(counts) == 4
    rows, weight = slice_sample(store, counts, 100, 1, range(2))
    plan = explain_text(rows)
    assert "PartitionFilters" in plan and "tile" in plan and "GreaterThanOrEqual(row_idx" in plan
    assert weight == 60 and {r.iteration: r.n for r in rows.groupBy("iteration").agg(F.count("*").alias("n")).collect()} == {0: 100, 1: 100}
    assert len(rows.inputFiles()) >= 4  # the table's files; the filter on tiles leaves out folders at run time


def test_slices_cover_every_row_alike():
    counts, seen = {0: 30, 1: 20, 5: 50}, np.zeros(100)
    first = {0: 0, 1: 30, 5: 50}
    for t in range(4000):
        for tile, lo, hi in slice_ranges(counts, 15, 3, t):
            assert 0 <= lo < hi <= counts[tile]
            seen[first[tile] + lo : first[tile] + hi] += 1
    assert np.allclose(seen / 4000, 0.15, atol=0.03)


def test_indices_drawn_by_executors(obs, monkeypatch):
    store = build_store(obs, 8).cache()
    counts = tile_counts(store)
    index = spread_indices(store, counts, 30_000, 4, 1).toPandas()
    assert index["w"].sum() == 30_000 and all(index[index["tile"] == t]["row_idx"].max() < n for t, n in counts.items())
    assert abs(index["w"].mean() - 30_000 / 6000) < 0.2 and index["w"].var() < 8
    again = spread_indices(store, counts, 30_000, 4, 1).toPandas()
    assert (index.sort_values(["tile", "row_idx"])["w"].to_numpy() == again.sort_values(["tile", "row_idx"])["w"].to_numpy()).all()
    monkeypatch.setattr("gradvb.sampling.BROADCAST_INDEX", 100)
    got, weight = with_replacement(store, counts, 300, 1, 0, 4)
    assert weight == 20 and {r.draw_id: r.w for r in got.groupBy("draw_id").agg(F.sum("w").alias("w")).collect()} == {k: 300.0 for k in range(4)}


def test_slice_estimates_are_unbiased(obs, ready):
    theta = (ready.anchor.theta + 0.03)[None, :]
    exact = exact_sums(obs, theta[0], order=1).grad
    p = SampleProvider(ready.store, ready.anchor, 200, scheme="slice", surrogate="none", block=200, counts=ready.counts)
    got = np.array([p.estimate(theta, t).grad[0] for t in range(200)])
    assert (np.abs((got.mean(axis=0) - exact) / (got.std(axis=0, ddof=1) / np.sqrt(200))) < 4.5).all()


def test_windows_of_panels_hold_a_tile_each(panels):
    assert "SinglePartition" not in explain_text(panels)
    assert panels.groupBy("tile").agg((F.max("row_idx") + 1 == F.count("*")).alias("whole")).where("not whole").isEmpty()


# chunks


def test_reader_map_and_reduce(obs, ready):
    theta = ready.anchor.theta + 0.02
    want = exact_sums(obs, theta, order=1)
    for chunks in (1, 3, 7):
        got = reduce_chunks(ChunkReader.split(obs, chunks).map(exact_map(theta))).first()
        assert got.n == 6000 and np.isclose(got.ll, want.loglik) and np.allclose([got[f"g{k}"] for k in range(4)], want.grad)
    apart = ChunkReader.of([obs.where("x1 = 0"), obs.where("x1 = 1")])
    runs = np.array([reduced_estimate(apart, theta[None, :], ready.anchor, 0.2, t)[0][0] for t in range(12)])
    z = (runs.mean(axis=0) - want.grad) / (runs.std(axis=0, ddof=1) / np.sqrt(12))
    assert (np.abs(z) < 6).all()


# models and parameters


def test_transforms_and_their_slopes():
    z = np.linspace(-3, 3, 25)
    for t in TRANSFORMS.values():
        natural = t.back_np(z)
        assert np.allclose(t.forward_np(natural), z)
        slope = (t.back_np(z + 1e-6) - t.back_np(z - 1e-6)) / 2e-6
        assert np.allclose(np.log(slope), t.log_slope_np(z), atol=1e-6)
    both = Transformed(("positive", "unit"))
    mean, sd = both.marginals(np.array([0.1, 0.0]), np.array([0.2, 0.5]))
    assert np.allclose(mean[0], np.exp(0.1 + 0.02), rtol=1e-3) and np.isclose(mean[1], 0.5) and (sd > 0).all()
    assert np.allclose(both.to_real(both.to_natural(np.array([[0.3, -1.0]]))), [[0.3, -1.0]])


def test_numeric_gradients_fit_like_derivatives(obs):
    from gradvb.functions.scalars import softplus, softplus_np

    numeric = NumericModel(lambda z, y: y * z - softplus(z), lambda z, y: y * z - softplus_np(z))
    cfg = FitConfig(m=0.1, tolerance=1e-6, s=64).settled()
    means = []
    for model in (Logit(), numeric):
        own = prepare(obs, model, cfg)
        means.append(ascend(own.provider(cfg), own.start(cfg), None, cfg).state.mu)
    assert np.allclose(*means, atol=1e-4)


def test_factors_and_repeats(ready):
    cfg = FitConfig(m=0.05, tolerance=1e-5, s=64).settled()
    fits = choose_factors(ready, [1, 2], cfg)
    assert fits[2].trace[-1]["lb"] > fits[1].trace[-1]["lb"] - 1
    runs = replicate(lambda seed: ascend(ready.provider(cfg, seed), ready.start(cfg), None, replace(cfg, seed=seed)), [1, 2, 3])
    mu = np.array([r.state.mu for r in runs])
    assert mu.std(axis=0).max() > 0 and (mu.std(axis=0) < 0.3 * runs[0].state.marginals()[1]).all()


def test_anchor_by_a_chain(obs):
    by_chain, by_mle = fit_anchor(obs, fraction=0.5, method="mcmc"), fit_anchor(obs, fraction=0.5)
    sd = np.sqrt(np.diag(np.linalg.inv(-by_mle.hess)))
    assert (np.abs(by_chain.theta - by_mle.theta) < 0.5 * sd).all()


# baselines


def test_subsampling_chain_and_plain_subsampling(obs, ready):
    exact = ready.anchor
    sd = np.sqrt(np.diag(np.linalg.inv(-exact.hess)))
    provider = SampleProvider(ready.store, exact, 0.1, block=500, counts=ready.counts)
    chain = baselines.subsample_mcmc(provider, exact, 3000, 500)
    assert 0.05 < chain.accepted.mean() < 0.7 and (np.abs(chain.draws.mean(axis=0) - fit_mle(obs).theta) < 0.6 * sd).all()
    cfg = FitConfig(tolerance=1e-7, max_iter=25)
    plain = baselines.plain_subsampling(ready.store, ready.counts, ready.start(cfg), 0.02, cfg)
    corrected = ascend(ready.provider(replace(cfg, m=0.02)), ready.start(cfg), None, cfg)
    assert plain.status != "settled" and np.mean([t["grad_var"] for t in plain.trace]) > 50 * np.mean([t["grad_var"] for t in corrected.trace])


def test_predecessor_on_rows(obs, ready):
    cfg = FitConfig(m=0.1, max_iter=12, tolerance=1e-9, s=64).settled()
    provider = SampleProvider(ready.store, ready.anchor, 0.1, block=64, counts=ready.counts, engine="driver")
    noisy = baselines.AugmentedRows(provider)
    theta = np.tile(ready.anchor.theta + 0.05, (64, 1))
    ll = noisy.estimate(theta, 0).loglik
    exact = exact_sums(obs, theta[0], order=0).loglik
    assert ll.std() > 0 and abs(ll.mean() - exact) < 4 * ll.std() / 8 + 0.05
    fit = baselines.fit_levb(noisy, ready.start(cfg), None, cfg, ready.anchor.hess)
    mean, sd = fit.state.marginals()
    assert (np.abs(mean - fit_mle(obs).theta) < 0.5 * sd).all()


def test_pseudo_marginal_chain_and_its_draws(panels):
    exact = Integrator("quadrature", 20)
    start = fit_panel_anchor(panels, exact, 1.0)
    count, seen = baselines.tune_is_count(panels, start.theta, start=8, repeats=8)
    assert seen[-1][1] <= 1 and all(var > 1 for _, var in seen[:-1]) and count == seen[-1][0]
    rows = panels.collect()
    from gradvb.panel import to_block

    block = to_block([r.panel_id for r in rows], [r.y for r in rows], [r.x for r in rows])
    chain = baselines.pm_mcmc(block, start, n_is=max(count, 64), iters=1000, burn=300)
    sd = np.sqrt(np.diag(np.linalg.inv(-start.hess)))
    assert 0.05 < chain.accepted.mean() < 0.6 and (np.abs(chain.draws.mean(axis=0) - start.theta) < 1.0 * sd + 0.2).all()


def test_predecessor_on_panels_has_noise_of_its_own(panels):
    theta = np.append(np.full(11, 0.3), 0.4)
    provider = baselines.AugmentedPanels(panels, 146, 12, 32)
    got = provider.estimate(np.tile(theta, (40, 1)), 1).loglik
    exact = panel_sums(panels, theta, Integrator("quadrature", 40)).loglik
    assert len(set(got.round(6).tolist())) == 40
    assert abs(got.mean() + 0.5 * got.var(ddof=1) - exact) < 4 * got.std(ddof=1) / np.sqrt(40) + 0.5


# panels


def test_panel_fit_agrees_with_quadrature(panels):
    cfg = FitConfig(draws="rqmc", s=128, tolerance=1e-5, max_iter=12).settled()
    truth = fit_ngvb_panels(panels, Integrator("quadrature", 20), 146, None, replace(cfg, tolerance=1e-6), 1.0)
    fit = fit_ngvb_panels(panels, Integrator("prior", 256, "rqmc"), 73, None, cfg, 1.0)
    mean, sd = truth.state.marginals()
    assert (np.abs(fit.state.mu - mean) < 0.3 * sd).all() and np.allclose(fit.state.marginals()[1], sd, rtol=0.3)


def test_integration_draws_are_fresh_in_each_estimate(panels):
    """Repeats differ through their integrals; even draws leave smaller errors than plain ones, and frozen ones none to see."""
    subset = fit_panel_anchor(panels, Integrator("quadrature", 20), 1.0)
    theta = (subset.theta + 0.1)[None, :]
    spread = {}
    for name, how in (("mc", Integrator("prior", 64, "mc")), ("rqmc", Integrator("prior", 64, "rqmc")), ("frozen", Integrator("prior", 64, "mc", fresh=False))):
        provider = PanelProvider(panels, panel_sums(panels, subset.theta, how), how, 146)
        provider.fetch(0)
        whole = provider.held[0]
        got = []
        for t in range(8):
            provider.held = {t: whole}  # the same panels each time
            got.append(provider.estimate(theta, t).grad[0])
        spread[name] = np.std(got, axis=0).mean()
    assert spread["frozen"] < 1e-9 < spread["rqmc"] < 0.7 * spread["mc"]


@pytest.mark.parametrize("kind", ["debiased", "laplace", "quadrature"])
def test_every_integrator_serves_in_a_fit(panels, kind):
    how = Integrator(kind, 20 if kind == "quadrature" else 64, "mc")
    cfg = FitConfig(s=16, max_iter=3, bound_steps=True)
    fit = fit_ngvb_panels(panels, how, 60, None, cfg, 1.0)
    assert fit.status != "diverged" and np.isfinite(fit.state.mu).all()


# measures


def test_measures_of_real_fits(spark, ready):
    cfg = FitConfig(m=0.05, tolerance=1e-5, s=64)
    fits = {("plain", "rqmc"): replicate(lambda seed: ascend(ready.provider(cfg, seed), ready.start(cfg), None, replace(cfg, seed=seed)), [1, 2])}
    frame = measures.replicates_frame(spark, fits)
    assert measures.speedups(frame, "plain").first().speedup == 1.0
    assert measures.stability(frame, 1).agg(F.max("spread")).first()[0] <= 0.1 + 1e-9
    summary = fits[("plain", "rqmc")][0].summary(spark, (-1.613, -0.155, 0.089, 0.764))
    z = {r.param: r.z for r in measures.z_scores(summary).collect()}
    assert len(z) == 4 and all(abs(v) < 5 for v in z.values())


def test_job_costs(spark):
    total, cost = measures.job_cost(spark, lambda: spark.range(1000).repartition(3).selectExpr("sum(id)").first()[0])
    assert total == 499_500 and cost["stages"] >= 2 and cost["shuffle_bytes"] > 0
    state = first_state(*([fit_mle(flights(spark, SF))] * 2), NormalPrior(), FitConfig())
    assert state.dim == 4
