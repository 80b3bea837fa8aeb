"""The experiments: fits, chains and ablations on the workloads; each returns a table of results.

Iterative and random methods have no SQL form; tests hold them against exact fits, quadrature and known
truth. The functions take their sizes as arguments, so the published settings and smaller ones run alike. Registered queries run
whole tables with the published draws, shares, chain lengths and tolerances; fewer than published are the repeats for standard errors
(10, published 100) and the iterates of the subsampling chain (README has the numbers).
"""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from gradvb import baselines, measures
from gradvb.designs import (
    FLIGHT_BETA, FULL_FLIGHT_BETA, PANEL_BETA, PANEL_TAU2, conversation_panels, embedding_design, event_flights, events_panels, flights, indicator, nest_panels, quality_design, supplier_panels, w3_panels,
)
from gradvb.draws import DrawSource, star_discrepancy_l2
from gradvb.estimators import ExactProvider, SampleProvider, sufficient_cells
from gradvb.families import NormalPrior
from gradvb.fit import FitConfig, StepSize, ascend, choose_factors, compare_models, first_state, fit_exact_vb, prepare, replicate
from gradvb.functions.scalars import hash_uniform_sql, norm_cdf_np, sigmoid_np
from gradvb.panel import Integrator, PanelProvider, fit_panel_anchor, panel_anchor, panel_sums, rank_panels
from gradvb.queries.text import linear, w1
from gradvb.queries.text import softplus as softplus_sql
from gradvb.sampling import assign_chunks, tile_counts
from gradvb.sources.tables import load_table
from gradvb.sums import exact_sums, fit_mle

SUMMARY = "arm string, param string, mean double, sd double, anchor double, truth double, iterations int, minutes double, status string"
PANEL_TRUTH = (*PANEL_BETA, float(np.log(PANEL_TAU2)))


def summary_rows(arm: str, fit, truth=None) -> list[tuple]:
    mean, sd = fit.state.marginals()
    pick = lambda v, k: None if v is None else float(v[k])
    return [(arm, f"b{k}", float(mean[k]), float(sd[k]), pick(fit.anchor, k), pick(truth, k), fit.iterations, fit.seconds / 60, fit.status) for k in range(len(mean))]


def chain_rows(arm: str, chain, truth=None) -> list[tuple]:
    d = chain.draws
    return [(arm, f"b{k}", float(d[:, k].mean()), float(d[:, k].std(ddof=1)), None, None if truth is None else float(truth[k]), len(d), chain.seconds / 60, "chain") for k in range(d.shape[1])]


def summary_frame(spark, rows: list[tuple]):
    """The rows as a table, by Arrow: row objects would go through a Python worker on each core."""
    kinds = {"string": pa.string(), "double": pa.float64(), "int": pa.int32()}
    names, types = zip(*(c.split() for c in SUMMARY.split(", ")), strict=True)
    columns = zip(*rows, strict=True) if rows else [()] * len(names)
    return spark.createDataFrame(pa.table({n: pa.array(v, kinds[t]) for n, t, v in zip(names, types, columns, strict=True)}))


def moderate_flights(spark, sf_dir, shares=(0.01, 0.02), chain_iters=30_000, burn=10_000, tolerance=1e-7, response="late_planted", obs=None, settled=True, arms=("mc", "rqmc")):
    """Chain against noisy-gradient fits with plain and quasi-random draws, at two subsample sizes; with ``settled`` also from the settled start.

    The rows are held once, as the store; rows given in ``obs`` (a scan, no join) are read again where they are counted.
    """
    obs = obs if obs is not None else flights(spark, sf_dir, response).cache()
    truth = FLIGHT_BETA if "planted" in response else None
    ready = prepare(obs)
    obs.unpersist()
    rows = []
    for kind in arms:
        for m in shares:
            plain = FitConfig(draws=kind, m=m, tolerance=tolerance)
            for name, cfg in (("", plain), ("_settled", plain.settled()))[: 1 + settled]:
                rows += summary_rows(f"{kind}_{m:g}{name}", ascend(ready.provider(cfg), ready.start(cfg), None, cfg, ready.anchor.theta), truth)
    if chain_iters:
        rows += chain_rows("chain", baselines.rw_mcmc(ready.store, iters=chain_iters, burn=burn), truth)
    ready.store.unpersist()
    return summary_frame(spark, rows)


def full_flights(spark, sf_dir, chunks=(8, 32, 128), share=0.05, tolerance=1e-7, anchor_fraction=0.3, combined=True):
    """Chunked fits at several numbers of chunks, with divide-and-combine beside them: the first must not move with the chunks."""
    obs = flights(spark, sf_dir, beta=FULL_FLIGHT_BETA).cache()
    rows = []
    for k in chunks:
        cfg = FitConfig(m=share, tolerance=tolerance, scheme="chunks", tiles=k, anchor_fraction=anchor_fraction)
        ready = prepare(obs, cfg=cfg)
        fit = ascend(ready.provider(cfg), ready.start(cfg), None, cfg, ready.anchor.theta)
        rows += summary_rows(f"chunks_{k}", fit, FULL_FLIGHT_BETA)
        if combined:
            theta, cov = baselines.divide_and_combine(obs, k)
            rows += [(f"combined_{k}", f"b{j}", float(theta[j]), float(np.sqrt(cov[j, j])), None, FULL_FLIGHT_BETA[j], 1, None, "combined") for j in range(len(theta))]
        ready.store.unpersist()
    obs.unpersist()
    return spark.createDataFrame(rows, SUMMARY)


def panel_fits(spark, sf_dir, sizes=(50, 100, 200), count=256, tolerance=1e-5, panels=None, arms=("mc", "rqmc"), truth=PANEL_TRUTH, settled=False):
    """Panel fits by subsample size and kind of draws; the panel's integral is drawn the same way.

    Steps are bounded: with plain ones, the first would overshoot where the one-factor start is wider than the target. With ``settled`` also from the settled start.
    """
    nested = (panels if panels is not None else nest_panels(w3_panels(spark, sf_dir).drop("panel_rank"))).cache()
    ranked = rank_panels(nested).cache()
    counts = tile_counts(ranked)
    nested.unpersist()
    rows, prior = [], NormalPrior()
    for kind in arms:
        how, cfg = Integrator("prior", count, kind), FitConfig(draws=kind, tolerance=tolerance, bound_steps=True)
        subset, sums = panel_anchor(ranked, how)
        for m in sizes:
            for name, own in (("", cfg), ("_settled", cfg.settled()))[: 1 + settled]:
                provider = PanelProvider(ranked, sums, how, min(m, sums.n), own.seed, own.surrogate, counts=counts)
                rows += summary_rows(f"{kind}_{m}{name}", ascend(provider, first_state(subset, sums, prior, own), prior, own, subset.theta), truth)
    ranked.unpersist()
    return spark.createDataFrame(rows, SUMMARY)


def pseudo_marginal(spark, sf_dir, panels: int | None = None, iters=30_000, burn=10_000, count: int | str = "auto"):
    """Pseudo-marginal chain of the published length on all panels (or the first ``panels``), summed where they lie, with draws tuned to a variance of one, and its diagnostics."""
    nested = nest_panels(w3_panels(spark, sf_dir, panels).drop("panel_rank"))
    nested = nested.repartition(spark.sparkContext.defaultParallelism, "panel_id").cache()
    n = nested.count()
    start = panel_sums(nested, fit_panel_anchor(nested, Integrator("quadrature", 20), 1.0).theta, Integrator("quadrature", 20))
    tuned, seen = baselines.tune_is_count(nested, start.theta, repeats=6, most=1 << 40) if count == "auto" else (int(count), [])
    chain = baselines.pm_mcmc(nested, start, n_is=tuned, iters=iters, burn=burn)
    rows = chain_rows("pseudo_marginal", chain, PANEL_TRUTH)
    rows += [("diagnostics", name, float(v), 0.0, None, None, iters, None, "chain") for name, v in (("panels", n), ("acceptance", chain.accepted.mean()), ("longest_stuck", chain.longest_stuck()), ("tuned_draws", tuned), ("last_variance", seen[-1][1] if seen else np.nan), ("effective_size_b0", measures.effective_size(chain.draws[:, 0])))]
    nested.unpersist()
    return spark.createDataFrame(rows, SUMMARY)


def likelihood_estimate_vb(spark, sf_dir, m=0.02, iters=40, s=64):
    """The predecessor beside the noisy-gradient fit: fitted together with the noise of its likelihood estimates, and, for comparison, with estimates that share their sample."""
    obs = flights(spark, sf_dir).cache()
    ready = prepare(obs)
    cfg = FitConfig(m=m, max_iter=iters, tolerance=1e-6, s=s).settled()
    provider = SampleProvider(ready.store, ready.anchor, m, seed=cfg.seed + 1, block=s, counts=ready.counts, engine="driver")
    fits = {
        "reparam": ascend(ready.provider(cfg), ready.start(cfg), None, cfg, ready.anchor.theta),
        "augmented": baselines.fit_levb(baselines.AugmentedRows(provider), ready.start(cfg), None, cfg),
        "shared_sample": baselines.fit_levb(ready.provider(cfg), ready.start(cfg), None, cfg),
    }
    rows = [r for arm, fit in fits.items() for r in summary_rows(arm, fit, FLIGHT_BETA)]
    ready.store.unpersist()
    obs.unpersist()
    return spark.createDataFrame(rows, SUMMARY)


def levb_panels(spark, sf_dir, count=64, iters=15, s=128):
    """The predecessor on panels: likelihoods of all panels estimated by importance sampling, each draw with noise of its own. Its gradients are noisy, so its steps are small."""
    nested = nest_panels(w3_panels(spark, sf_dir).drop("panel_rank")).repartition(spark.sparkContext.defaultParallelism, "panel_id").cache()
    how = Integrator("quadrature", 20)
    subset = fit_panel_anchor(nested, how)
    sums = panel_sums(nested, subset.theta, how)
    cfg = replace(FitConfig(max_iter=iters, tolerance=1e-5, s=s).settled(), step=StepSize(t0=20.0))
    provider = baselines.AugmentedPanels(nested, sums.n, len(subset.theta), count, cfg.seed, "rqmc")
    fit = baselines.fit_levb(provider, first_state(subset, sums, NormalPrior(), cfg), None, cfg, sums.hess)
    nested.unpersist()
    return spark.createDataFrame(summary_rows("augmented_panels", fit, PANEL_TRUTH), SUMMARY)


def exact_and_plain(spark, sf_dir, m=0.02):
    """Exact-gradient VB, the Laplace normal, plain subsampling (which may diverge) and the corrected fit, from one start."""
    obs = flights(spark, sf_dir).cache()
    cfg = FitConfig(m=m, tolerance=1e-7).settled()
    ready = prepare(obs, cfg=cfg)
    start = ready.start(cfg)
    rows = summary_rows("corrected", ascend(ready.provider(cfg), start, None, cfg, ready.anchor.theta), FLIGHT_BETA)
    cells = sufficient_cells(obs)
    rows += summary_rows("exact_cells", ascend(cells, start, None, cfg, curvature=ready.anchor.hess), FLIGHT_BETA)
    rows += summary_rows("exact_rows", ascend(ExactProvider(obs), start, None, cfg, curvature=ready.anchor.hess), FLIGHT_BETA)
    published = FitConfig(m=m, tolerance=1e-7)
    rows += summary_rows("plain", baselines.plain_subsampling(ready.store, ready.counts, ready.start(published), m, published), FLIGHT_BETA)
    best, sd = baselines.laplace(obs)
    rows += [("laplace", f"b{k}", float(best.theta[k]), float(sd[k]), None, FLIGHT_BETA[k], 1, None, "newton") for k in range(4)]
    obs.unpersist()
    return spark.createDataFrame(rows, SUMMARY)


def subsample_chain(spark, sf_dir, m=0.02, iters=2000, burn=500):
    """Chain on difference estimates of the likelihood."""
    obs = flights(spark, sf_dir).cache()
    ready = prepare(obs)
    provider = SampleProvider(ready.store, ready.anchor, m, block=250, counts=ready.counts)
    chain = baselines.subsample_mcmc(provider, ready.anchor, iters, burn)
    obs.unpersist()
    return spark.createDataFrame(chain_rows("subsample_chain", chain, FLIGHT_BETA), SUMMARY)


def ablations(spark, sf_dir):
    """Surrogate, subsample, pairing, geometry, estimator, step, family, factors and scramble, one changed at a time."""
    obs = flights(spark, sf_dir).cache()
    base = FitConfig(m=0.01, tolerance=1e-6, max_iter=40, scheme="replacement")  # at every size; left open, large tables would get slices
    ready = prepare(obs, cfg=base)
    arms = {
        "base": {}, "surrogate_constant": {"surrogate": "constant"}, "m_doubled": {"m": 0.02}, "mc": {"draws": "mc"}, "few_draws": {"s": 16}, "euclidean": {"geometry": "euclidean"},
        "score_function": {"estimator": "score"}, "no_analytic": {"analytic": False}, "power_steps": {"step": StepSize("power", 1.0, 0.7)}, "hold_then_decay": {"step": StepSize("constant_then_decay")},
        "two_factors": {"factors": 2}, "full": {"family": "full"}, "mean_field": {"family": "diagonal"}, "linear_scramble": {"scrambling": "linear"}, "shift": {"scrambling": "shift"}, "state_rule": {"stop": "state", "tolerance": 1e-4},
    }
    rows = []
    for name, change in arms.items():
        cfg = replace(base, **change)
        rows += summary_rows(name, ascend(ready.provider(cfg), ready.start(cfg), None, cfg, ready.anchor.theta), FLIGHT_BETA)
    for name, cfg in (("slices", replace(base, scheme="slice")), ("per_draw", replace(base, s=64, pairing="per_draw", max_iter=20)), ("tiles", replace(base, scheme="tile", m=0.25, max_iter=20))):
        rows += summary_rows(name, ascend(ready.provider(cfg), ready.start(cfg), None, cfg, ready.anchor.theta), FLIGHT_BETA)
    obs.unpersist()
    return spark.createDataFrame(rows, SUMMARY)


def replications(spark, sf_dir, reps=10, shares=(0.01, 0.02), starts=("warm", "subset")):
    """Monte Carlo standard errors over independent repeats, by draws, subsample size and start.

    From the subset's plain start the errors show what the loop itself adds; from the settled
    start little is left to add.
    """
    obs = flights(spark, sf_dir).cache()
    ready = prepare(obs)
    fits = {}
    for start in starts:
        for kind in ("mc", "rqmc"):
            for m in shares:
                cfg = FitConfig(draws=kind, m=m, tolerance=1e-6)
                cfg = cfg.settled() if start == "warm" else cfg
                runs = replicate(lambda seed, cfg=cfg: ascend(ready.provider(cfg, seed), ready.start(cfg), None, replace(cfg, seed=seed), ready.anchor.theta), list(range(1, reps + 1)))
                fits[(f"{kind}_{m:g}_{start}", kind)] = runs
    obs.unpersist()
    return measures.mc_standard_errors(measures.replicates_frame(spark, fits))


def gradient_variance(spark, sf_dir, repeats=30):
    """Bias in standard errors and variance of repeated gradient estimates, by surrogate and subsample size."""
    obs = flights(spark, sf_dir).cache()
    ready = prepare(obs)
    theta = ready.anchor.theta + 0.02
    exact = exact_sums(obs, theta, order=1).grad
    rows = []
    for surrogate in ("none", "constant", "linear"):
        for m in (0.01, 0.02):
            provider = SampleProvider(ready.store, ready.anchor, m, surrogate=surrogate, block=repeats, counts=ready.counts)
            got = np.array([provider.estimate(theta[None, :], t).grad[0] for t in range(repeats)])
            _, var, z = measures.gradient_quality(got, exact)
            rows += [(surrogate, m, f"b{k}", float(var[k]), float(z[k])) for k in range(4)]
    obs.unpersist()
    return spark.createDataFrame(rows, "surrogate string, m double, param string, variance double, bias_in_se double")


def model_choice(spark, sf_dir):
    """Models with and without each covariate, ranked by their bounds."""
    obs = flights(spark, sf_dir).cache()
    fits = {}
    for name, drop in (("all", None), ("without_rush", 1), ("without_weekend", 2), ("without_distance", 3)):
        keep = [k for k in range(4) if k != drop]
        own = obs.select("obs_key", "y", *(F.col(f"x{k}").alias(f"x{i}") for i, k in enumerate(keep)))
        cfg = FitConfig(m=0.02, tolerance=1e-7).settled()
        ready = prepare(own, cfg=cfg)
        fits[name] = ascend(ready.provider(cfg), ready.start(cfg), None, cfg, ready.anchor.theta)
        ready.store.unpersist()
    obs.unpersist()
    return compare_models(spark, fits)


def densities(spark, sf_dir):
    """Distances between the fit's marginal densities and the chain's kernel estimates."""
    obs = flights(spark, sf_dir).cache()
    ready = prepare(obs)
    cfg = FitConfig(m=0.02, tolerance=1e-7).settled()
    fit = ascend(ready.provider(cfg), ready.start(cfg), None, cfg, ready.anchor.theta)
    chain = baselines.rw_mcmc(obs, iters=30_000, burn=10_000).frame(spark).cache()
    mean, sd = fit.state.marginals()
    out = None
    for k in range(4):
        smooth = measures.kde(chain, f"b{k}", 101).select("x", "pdf")
        other = F.exp(-0.5 * ((F.col("x") - float(mean[k])) / float(sd[k])) ** 2) / float(sd[k] * np.sqrt(2 * np.pi))
        both = smooth.select(F.lit(f"b{k}").alias("param"), "x", "pdf")
        part = measures.density_distance(both, both.withColumn("pdf", other))
        out = part if out is None else out.union(part)
    obs.unpersist()
    return out


def net_quality(spark, sf_dir):
    """Discrepancy of plain and scrambled points, and the variance under both of a smooth mean: the mean chance of an event, over all events and draws of the coefficients."""
    night, weekend = (F.hour("ts") < 6) | (F.hour("ts") >= 22), F.dayofweek("ts").isin(1, 7)
    marks = [indicator(F.coalesce(c, F.lit(False))) for c in (night, weekend, F.col("event_type") == "purchase", F.col("value") > 50)]
    found = load_table(spark, sf_dir, "events").select(*(c.alias(f"x{k}") for k, c in enumerate(marks, 1))).groupBy("x1", "x2", "x3", "x4").count().collect()
    cells = np.array(sorted((r.x1, r.x2, r.x3, r.x4, r["count"]) for r in found), float)
    x, share = np.column_stack([np.ones(len(cells)), cells[:, :4]]), cells[:, 4] / cells[:, 4].sum()
    centre = np.append(FLIGHT_BETA, 0.3)
    rows = []
    for kind in ("mc", "rqmc"):
        for s in (64, 256):
            source = DrawSource(kind, 3)
            z = [source.normals(s, 5, t) for t in range(20)]
            values = [float(share @ sigmoid_np(x @ (centre + 0.3 * v).T).mean(axis=1)) for v in z]
            rows.append((kind, s, float(np.mean([star_discrepancy_l2(norm_cdf_np(v)) for v in z[:5]])), float(np.var(values, ddof=1))))
    return spark.createDataFrame(rows, "draws string, s int, discrepancy double, variance double")


def wide_design(spark, sf_dir):
    """65 parameters: an exact-gradient fit on one class against the rest."""
    obs = embedding_design(spark, sf_dir).cache()
    best = fit_mle(obs, steps=6, cap=8.0)
    from gradvb.families import init_state
    from gradvb.fit import warm_start

    prior = NormalPrior(1.0)
    start = warm_start(init_state(best.theta, -best.hess + np.eye(65), 1.0), best, prior, 50)
    cfg = FitConfig(draws="mc", s=256, tolerance=1e-4).settled()
    fit = fit_exact_vb(obs, start, prior=prior, cfg=cfg)
    obs.unpersist()
    return spark.createDataFrame(summary_rows("embeddings", fit), SUMMARY)


def text_quality(spark, sf_dir):
    """Text labels against length and language."""
    rows = []
    base = quality_design(spark, sf_dir)
    for label in ("quality", "toxic"):
        xs = {"log_chars": F.col("log_chars") / 10, "de": F.col("lang_de"), "es": F.col("lang_es"), "fr": F.col("lang_fr")}
        from gradvb.designs import design

        obs = design(base.withColumn("obs_key", F.col("doc_id").cast("string")), F.col(label), xs, keep=("obs_key",)).cache()
        cfg = FitConfig(m=0.3, tolerance=1e-5, anchor_fraction=1.0, tiles=4).settled()
        ready = prepare(obs, cfg=cfg)
        rows += summary_rows(label, ascend(ready.provider(cfg), ready.start(cfg), None, cfg, ready.anchor.theta))
        obs.unpersist()
    return spark.createDataFrame(rows, SUMMARY)


def natural_panels(make, m: int, tolerance: float = 1e-4):
    """Panels with their own covariates and lengths."""

    def run(spark, sf_dir):
        return panel_fits(spark, sf_dir, (m,), 64, tolerance, nest_panels(make(spark, sf_dir)), ("rqmc",), None)

    return run


def integrator_check(spark, sf_dir):
    """Importance estimates of the log likelihood against quadrature, by proposal and draws: error and seconds of the panel sums."""
    import time

    nested = nest_panels(w3_panels(spark, sf_dir).drop("panel_rank")).cache()
    theta = np.array(PANEL_TRUTH)
    truth = panel_sums(nested, theta, Integrator("quadrature", 40))
    rows = []
    for kind, draws in (("prior", "mc"), ("prior", "rqmc"), ("laplace", "mc"), ("laplace", "rqmc"), ("defensive", "rqmc")):
        began = time.time()
        s = panel_sums(nested, theta, Integrator(kind, 64, draws))
        rows.append((kind, draws, float(s.loglik - truth.loglik), float(np.abs(s.grad - truth.grad).max()), time.time() - began))
    nested.unpersist()
    return spark.createDataFrame(rows, "proposal string, draws string, loglik_error double, score_error double, seconds double")


def chunk_constancy(spark, sf_dir):
    """Sums over chunks do not move with the number of chunks."""
    obs = flights(spark, sf_dir)
    rows = []
    for k in (4, 16, 64):
        chunked = assign_chunks(obs, k)
        s = exact_sums(chunked, FLIGHT_BETA, order=1)
        rows.append((k, len(tile_counts(chunked.withColumnRenamed("chunk_id", "tile"))), s.n, round(float(s.loglik / s.n), 7)))
    return spark.createDataFrame(rows, "chunks int, filled int, n long, loglik_mean double")


def real_costs(spark, sf_dir, reps=3, m=0.02, iters=30_000, burn=10_000):
    """Speed-ups over the chain and stability to two digits, from repeated fits and one chain run here."""
    obs = flights(spark, sf_dir).cache()
    ready = prepare(obs)
    chain = baselines.rw_mcmc(obs, iters=iters, burn=burn)
    fits = {}
    for kind in ("mc", "rqmc"):
        for name, cfg in ((kind, FitConfig(draws=kind, m=m, tolerance=1e-7)), (f"{kind}_settled", FitConfig(draws=kind, m=m, tolerance=1e-7).settled())):
            fits[(name, kind)] = replicate(lambda seed, cfg=cfg: ascend(ready.provider(cfg, seed), ready.start(cfg), None, replace(cfg, seed=seed), ready.anchor.theta), list(range(1, reps + 1)))
    reps_frame = measures.replicates_frame(spark, fits)
    own = [("chain", "mc", 0, f"b{k}", float(chain.draws[:, k].mean()), float(chain.draws[:, k].std(ddof=1)), iters + burn, chain.seconds / 60) for k in range(4)]
    reps_frame = reps_frame.union(spark.createDataFrame(own, reps_frame.schema)).cache()
    cost = measures.speedups(reps_frame, "chain")
    spread = measures.stability(reps_frame).groupBy("method").agg(F.max("spread").alias("spread_two_digits"))
    errors = measures.mc_standard_errors(reps_frame).groupBy("method").agg(F.max("mean_se").alias("largest_mean_se"), F.max("sd_se").alias("largest_sd_se"))
    ready.store.unpersist()
    obs.unpersist()
    return cost.join(spread, "method").join(errors, "method")


def panel_errors(spark, sf_dir, reps=4, m=100, count=64):
    """Monte Carlo standard errors of panel fits over independent repeats, integrals by plain or quasi-random draws."""
    nested = nest_panels(w3_panels(spark, sf_dir).drop("panel_rank"))
    ranked = rank_panels(nested).cache()
    how = Integrator("quadrature", 20)
    subset = fit_panel_anchor(ranked, how)
    prior, fits = NormalPrior(), {}
    for kind in ("mc", "rqmc"):
        cfg, own = FitConfig(draws=kind, tolerance=1e-5, s=64, bound_steps=True), Integrator("prior", count, kind)
        sums = panel_sums(ranked, subset.theta, own)
        run = lambda seed, cfg=cfg, own=own, sums=sums: ascend(PanelProvider(ranked, sums, own, m, seed), first_state(subset, sums, prior, cfg), prior, replace(cfg, seed=seed), subset.theta)
        fits[(kind, kind)] = replicate(run, list(range(1, reps + 1)))
    out = measures.mc_standard_errors(measures.replicates_frame(spark, fits))
    ranked.unpersist()
    return out


def factors_by_bound(spark, sf_dir, factors=(0, 1, 2)):
    """Numbers of factors ranked by the bounds of their fits."""
    obs = flights(spark, sf_dir).cache()
    cfg = FitConfig(m=0.02, tolerance=1e-7).settled()
    ready = prepare(obs, cfg=cfg)
    fits = {f"factors_{k}": f for k, f in choose_factors(ready, [k for k in factors if k], cfg).items()}
    if 0 in factors:
        own = replace(cfg, family="diagonal")
        fits["factors_0"] = ascend(ready.provider(own), ready.start(own), None, own, ready.anchor.theta)
    out = compare_models(spark, fits)
    ready.store.unpersist()
    obs.unpersist()
    return out


def gradient_noise(spark, sf_dir, shares=(0.0025, 0.005, 0.01, 0.02), reps=8):
    """Variance of fitted means over repeats against that of the gradient they came from: the first goes up in proportion to the second."""
    obs = flights(spark, sf_dir).cache()
    cfg = FitConfig(draws="rqmc", tolerance=1e-12, max_iter=15)
    ready = prepare(obs, cfg=cfg)
    rows = []
    for m in shares:
        own = replace(cfg, m=m, surrogate="constant")
        fits = replicate(lambda seed, own=own: ascend(ready.provider(own, seed), ready.start(own), None, own, ready.anchor.theta), list(range(1, reps + 1)))
        rows.append((m, float(np.mean([t["grad_var"] for f in fits for t in f.trace])), float(np.var([f.state.mu for f in fits], axis=0, ddof=1).mean())))
    ready.store.unpersist()
    obs.unpersist()
    return spark.createDataFrame(rows, "m double, gradient_variance double, fit_variance double")


def iteration_costs(spark, sf_dir, m=0.01):
    """What an iteration costs by scheme: stages, rows and bytes read, bytes shuffled, seconds, in fits of the same start."""
    obs = flights(spark, sf_dir).cache()
    ready = prepare(obs)
    thetas = ready.anchor.theta + 0.01 * np.random.default_rng(3).normal(size=(256, 4))
    rows = []
    for scheme, engine, share in (("replacement", "driver", m), ("replacement", "spark", m), ("slice", "driver", m), ("slice", "spark", m), ("tile", "spark", 0.25), ("chunks", "spark", m)):
        provider = SampleProvider(ready.store, ready.anchor, share, scheme=scheme, engine=engine, counts=ready.counts, block=10, hold=False)
        _, cost = measures.job_cost(spark, lambda: [provider.estimate(thetas, t) for t in range(10)])  # noqa: B023
        rows.append((scheme, engine, share, *(cost[c] / 10 for c in ("stages", "rows_read", "bytes_read", "shuffle_bytes", "seconds"))))
    for kind in ("mc", "rqmc"):
        import time

        began = time.time()
        for t in range(10):
            DrawSource(kind, 1).normals(256, 5, t)
        rows.append((f"draws_{kind}", "driver", 0.0, 0.0, 0.0, 0.0, 0.0, (time.time() - began) / 10))
    ready.store.unpersist()
    obs.unpersist()
    return spark.createDataFrame(rows, "scheme string, engine string, share double, stages double, rows_read double, bytes_read double, shuffle_bytes double, seconds double")


def numeric_gradients(spark, sf_dir):
    """The fit of a model that is known by its log likelihood alone, beside the same model with its derivatives."""
    from gradvb.functions.scalars import softplus, softplus_np
    from gradvb.models import Logit, NumericModel

    obs = flights(spark, sf_dir).cache()
    rows = []
    for name, model in (("derivatives", Logit()), ("differences", NumericModel(lambda z, y: y * z - softplus(z), lambda z, y: y * z - softplus_np(z)))):
        cfg = FitConfig(m=0.02, tolerance=1e-6).settled()
        ready = prepare(obs, model, cfg)
        rows += summary_rows(name, ascend(ready.provider(cfg), ready.start(cfg), None, cfg, ready.anchor.theta), FLIGHT_BETA)
        ready.store.unpersist()
    obs.unpersist()
    return spark.createDataFrame(rows, SUMMARY)


QUERIES = {
    "fit_moderate_flights": moderate_flights,
    "fit_moderate_flights_raw": lambda s, d: moderate_flights(s, d, (0.02,), 0, 0, 1e-6, "late_raw"),
    "fit_event_flights": lambda s, d: moderate_flights(s, d, (0.05,), 2000, 1000, 1e-6, obs=event_flights(s, d)),
    "fit_full_flights_chunked": full_flights,
    "fit_panels": panel_fits,
    "fit_panels_large": lambda s, d: panel_fits(s, d, (500,), 256, 1e-6, settled=True),
    "fit_panels_events": natural_panels(events_panels, 50),
    "fit_panels_suppliers": natural_panels(supplier_panels, 20),
    "fit_panels_conversations": natural_panels(conversation_panels, 40),
    "pseudo_marginal_chain": pseudo_marginal,
    "likelihood_estimate_vb": likelihood_estimate_vb,
    "likelihood_estimate_vb_panels": levb_panels,
    "exact_and_plain_vb": exact_and_plain,
    "subsample_chain": subsample_chain,
    "ablations": ablations,
    "replication_errors": replications,
    "replication_errors_panels": panel_errors,
    "speedup_and_stability": real_costs,
    "factors_by_bound": factors_by_bound,
    "gradient_noise": gradient_noise,
    "iteration_costs": iteration_costs,
    "numeric_gradients": numeric_gradients,
    "gradient_variance": gradient_variance,
    "model_choice": model_choice,
    "density_distances": densities,
    "net_quality": net_quality,
    "wide_design": wide_design,
    "text_quality": text_quality,
    "integrator_check": integrator_check,
    "chunk_constancy": chunk_constancy,
}



def chunks_sql() -> str:
    z = linear(FLIGHT_BETA)
    arms = " UNION ALL ".join(f"SELECT {k}::INTEGER AS chunks, count(DISTINCT least(floor({hash_uniform_sql("'chunk'", 'obs_key')} * {k}), {k - 1}))::INTEGER AS filled, count(*) AS n, round(sum(y * ({z}) - {softplus_sql(z)}) / count(*), 7) AS loglik_mean FROM obs" for k in (4, 16, 64))
    return f"WITH {w1()} {arms}"


SQL: dict[str, str] = {"chunk_constancy": chunks_sql()}
