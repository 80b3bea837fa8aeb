"""The methods that the loop is compared with."""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradvb.estimators import Estimate, SampleProvider, assemble, remainder_values, sufficient_cells
from gradvb.families import DiagonalState, Gaussian, NormalPrior
from gradvb.fit import FitConfig, FitResult, ascend
from gradvb.models import Logit, Model
from gradvb.panel import HeldPanels, Integrator, PanelBlock, panel_logliks, panel_values
from gradvb.sampling import assign_chunks
from gradvb.sums import Sums, fit_mle, sum_expressions, unpack, width


@dataclass
class Chain:
    draws: np.ndarray
    loglik: np.ndarray
    accepted: np.ndarray
    seconds: float

    def frame(self, spark: SparkSession) -> DataFrame:
        rows = pd.DataFrame({"iter": np.arange(len(self.draws)), "loglik": self.loglik, "accepted": self.accepted})
        for k in range(self.draws.shape[1]):
            rows[f"b{k}"] = self.draws[:, k]
        return spark.createDataFrame(rows)

    def longest_stuck(self) -> int:
        """Longest run of rejections."""
        run = best = 0
        for a in self.accepted:
            run = 0 if a else run + 1
            best = max(best, run)
        return best


def adaptive_walk(target: Callable[[np.ndarray, int], float], start: np.ndarray, scale: np.ndarray, iters: int, burn: int, seed: int, prior: NormalPrior, adapt: bool = True) -> Chain:
    """Random-walk chain whose proposal follows the running covariance; a share of steps keeps the first scale.

    ``target(theta, step)`` is the log likelihood or an estimate of it; the value of the current
    point is kept, not drawn anew.
    """
    return speculative_walk(lambda points: [target(*p) for p in points], start, scale, iters, burn, seed, prior, adapt)


def speculative_walk(targets: Callable[[list[tuple[np.ndarray, int]]], Sequence[float]], start: np.ndarray, scale: np.ndarray, iters: int, burn: int, seed: int, prior: NormalPrior, adapt: bool = True, ahead: int = 1) -> Chain:
    """``adaptive_walk`` on a target that takes several (theta, step) at once.

    The next ``ahead`` proposals are valued together as if the chain stayed where it is; once one is accepted, or the scale changes, those after it are dropped and
    proposed again. Steps keep their random numbers, so the chain does not depend on ``ahead``.
    """
    rng, d, began = np.random.Generator(np.random.Philox(key=seed)), len(start), time.time()
    theta, here = start.copy(), targets([(start, 0)])[0]
    log_prior = float(prior.log_density(theta)[0])
    mean, cov, root = theta.copy(), scale.copy(), np.linalg.cholesky(scale + 1e-12 * np.eye(d))
    first = root.copy()
    draws, logs, accepted = np.empty((iters, d)), np.empty(iters), np.zeros(iters, bool)
    noise, known = {}, {}
    for t in range(-burn, iters):
        if t not in known:
            steps = range(t, min(t + ahead, iters))
            for k in steps:
                if k not in noise:
                    noise[k] = rng.random() < 0.05, rng.standard_normal(d), np.log(rng.random())
            points = [theta + (first if noise[k][0] else root) @ noise[k][1] * 2.38 / np.sqrt(d) for k in steps]
            values = targets([(p, k + burn + 1) for k, p in zip(steps, points, strict=True)])
            known = dict(zip(steps, zip(points, values, strict=True), strict=True))
        new, there = known.pop(t)
        new_prior = float(prior.log_density(new)[0])
        ok = noise.pop(t)[2] < there + new_prior - here - log_prior
        if ok:
            theta, here, log_prior = new, there, new_prior
            known.clear()
        if adapt and t < 0:
            k = t + burn + 2
            gap = theta - mean
            mean = mean + gap / k
            cov = cov + (np.outer(gap, theta - mean) - cov) / max(k, 2 * d)
            if k % 50 == 0:
                root = np.linalg.cholesky(cov + 1e-10 * np.trace(scale) * np.eye(d))
                known.clear()
        if t >= 0:
            draws[t], logs[t], accepted[t] = theta, here, ok
    return Chain(draws, logs, accepted, time.time() - began)


def rw_mcmc(obs: DataFrame, model: Model | None = None, prior: NormalPrior | None = None, iters: int = 30_000, burn: int = 10_000, seed: int = 1, adapt: bool = True, start: Sums | None = None) -> Chain:
    """Exact chain: the likelihood comes from covariate cells where these are few, else from a pass over the rows each step."""
    model, prior = model or Logit(), prior or NormalPrior()
    try:
        cells = sufficient_cells(obs, model=model)
    except ValueError:
        from gradvb.sums import exact_sums

        start = start or fit_mle(obs, model)
        target = lambda theta, _: exact_sums(obs, theta, model, 0).loglik
    else:
        start = start or cells.fit_mle()
        target = lambda theta, _: cells.loglik(theta)
    return adaptive_walk(target, start.theta, np.linalg.inv(-start.hess), iters, burn, seed, prior, adapt)


def many_estimates(block: PanelBlock | DataFrame | HeldPanels, points: list[tuple[np.ndarray, int]], count: int, draws: str = "mc", kind: str = "prior") -> Sequence[float]:
    """Estimates over all panels at (theta, seed) pairs: of a block here, of nested panels where they lie and by one job. Draws are keyed by panel, so both agree."""
    own = [(theta, Integrator(kind, count, draws, seed)) for theta, seed in points]
    if isinstance(block, HeldPanels):
        return block.logliks(own)
    if isinstance(block, DataFrame):
        return panel_logliks(block, own)
    parts = [block.part(np.arange(lo, min(lo + 500, len(block.ids)))) for lo in range(0, len(block.ids), 500)]
    return [sum(float(panel_values(part, theta, how).sum()) for part in parts) for theta, how in own]


def loglik_estimates(block: PanelBlock | DataFrame, theta: np.ndarray, count: int, seed: int, draws: str = "mc", kind: str = "prior") -> float:
    """One estimate over all panels."""
    return float(many_estimates(block, [(theta, seed)], count, draws, kind)[0])


def tune_is_count(block: PanelBlock | DataFrame, theta: np.ndarray, target: float = 1.0, start: int = 16, most: int = 1 << 14, repeats: int = 12, kind: str = "prior", draws: str = "mc") -> tuple[int, list[tuple[int, float]]]:
    """Least power of two of draws whose log-likelihood estimate varies by at most ``target``; and the variances seen."""
    seen, count = [], start
    while True:
        var = float(np.var(many_estimates(block, [(theta, 1000 + k) for k in range(repeats)], count, draws, kind), ddof=1))
        seen.append((count, var))
        if var <= target or count >= most:
            return count, seen
        count *= 2


#: Draws (panels x draws of a panel) that the proposals of one job take together, and the most such proposals: so much that a job's own cost no longer leads.
AHEAD_DRAWS, AHEAD = 64_000_000, 8


def pm_mcmc(block: PanelBlock | DataFrame, start: Sums, prior: NormalPrior | None = None, n_is: int | str = "auto", iters: int = 30_000, burn: int = 10_000, seed: int = 1, kind: str = "prior", draws: str = "mc", ahead: int | None = None) -> Chain:
    """Pseudo-marginal chain: fresh importance draws for every proposal, the accepted estimate kept.

    Nested panels give the estimates of ``ahead`` proposals by one job, as many as small tables need to hide the job's cost; the chain is the same for any number.
    """
    count = tune_is_count(block, start.theta, kind=kind, draws=draws)[0] if n_is == "auto" else int(n_is)
    if ahead is None:
        ahead = int(np.clip(AHEAD_DRAWS // (start.n * count), 1, AHEAD)) if isinstance(block, DataFrame) else 1
    held = HeldPanels(block) if isinstance(block, DataFrame) else block
    targets = lambda points: many_estimates(held, [(theta, seed * 1_000_003 + t) for theta, t in points], count, draws, kind)
    try:
        return speculative_walk(targets, start.theta, np.linalg.inv(-start.hess), iters, burn, seed, prior or NormalPrior(), ahead=ahead)
    finally:
        if held is not block:
            held.release()


def fit_levb(provider, state: Gaussian, prior: NormalPrior | None = None, cfg: FitConfig | None = None, curvature: np.ndarray | None = None) -> FitResult:
    """Likelihood-estimate VB: score-function gradients that use the estimated likelihood's value only.

    With a provider of this module whose estimates have noise of their own for every draw, the state and that
    noise are fitted together; the target is the exact one only if the noise's variance does not move with the parameters.
    """
    return ascend(provider, state, prior, replace(cfg or FitConfig(), estimator="score"), curvature=curvature)


class AugmentedPanels:
    """Log-likelihood estimates over all panels, each draw with importance draws of its own; no gradients.

    One job an iteration: tasks go through their panels once for all draws and send one sum a draw.
    """

    def __init__(self, panels: DataFrame, n: int, dim: int, count: int, seed: int = 1, draws: str = "mc", kind: str = "prior") -> None:
        self.panels, self.n, self.dim, self.how, self.seed = panels, n, dim, Integrator(kind, count, draws), seed

    def estimate(self, thetas: np.ndarray, iteration: int) -> Estimate:
        points = [(theta, self.how.at(self.seed, iteration, k)) for k, theta in enumerate(thetas)]
        return Estimate(np.zeros((len(thetas), self.dim)), panel_logliks(self.panels, points), float("nan"), self.n)


class AugmentedRows:
    """Log likelihoods from row samples, each draw with a sample of its own, less half their estimated variance, so that the likelihood's estimate is nearly unbiased."""

    def __init__(self, provider: SampleProvider) -> None:
        self.provider, self.n, self.dim, self.taken = provider, provider.n, provider.dim, 0

    def estimate(self, thetas: np.ndarray, iteration: int) -> Estimate:
        p, ll, rows = self.provider, np.zeros(len(thetas)), 0
        for k, theta in enumerate(thetas):
            x, y, w = p.rows(iteration * len(thetas) + k)
            rest = remainder_values(x, y, theta, p.anchor, p.model, p.surrogate)
            here = assemble(theta[None, :], p.anchor, np.zeros((1, p.dim)), np.array([w @ rest]), p.surrogate)[1][0]
            m = max(2.0, w.sum() * p.m / p.n)
            ll[k] = here - 0.5 * p.n**2 / m * float(np.average((rest - np.average(rest, weights=w)) ** 2, weights=w))
            rows += p.touched if p.holds else len(y)
        return Estimate(np.zeros((len(thetas), p.dim)), ll, float("nan"), rows)


def laplace(obs: DataFrame, model: Model | None = None) -> tuple[Sums, np.ndarray]:
    """The maximum and the sds of the normal there."""
    best = fit_mle(obs, model)
    return best, np.sqrt(np.diag(np.linalg.inv(-best.hess)))


def plain_subsampling(store: DataFrame, counts: dict[int, int], state: Gaussian, m: float, cfg: FitConfig | None = None) -> FitResult:
    """The loop without a surrogate; it may well diverge, and then says so."""
    cfg = cfg or FitConfig()
    return ascend(SampleProvider(store, None, m, seed=cfg.seed, surrogate="none", engine=cfg.engine, counts=counts), state, None, cfg)


def divide_and_combine(obs: DataFrame, chunks: int, model: Model | None = None, key: str = "obs_key", salt: str = "chunk", steps: int = 30, cap: float = 25.0) -> tuple[np.ndarray, np.ndarray]:
    """Each chunk fitted by itself, estimates weighted by their information: (estimate, covariance).

    All chunks take their Newton steps together: a step is one aggregate by chunk, at each chunk's own point.
    """
    model, d = model or Logit(), width(obs)
    rows = assign_chunks(obs, chunks, key, salt).select("chunk_id", "y", *(f"x{k}" for k in range(d))).cache()
    spark, theta = obs.sparkSession, {r[0]: np.zeros(d) for r in rows.select("chunk_id").distinct().collect()}

    def sums() -> dict[int, Sums]:
        points = spark.createDataFrame([(c, *map(float, t)) for c, t in theta.items()], "chunk_id int, " + ", ".join(f"t{k} double" for k in range(d)))
        z = F.lit(0.0)
        for k in range(d):
            z = z + F.col(f"t{k}") * F.col(f"x{k}")
        here = rows.join(F.broadcast(points), "chunk_id")
        found = here.groupBy("chunk_id").agg(*sum_expressions(model, np.zeros(d), 2, z)).collect()
        return {r["chunk_id"]: unpack(r, theta[r["chunk_id"]]) for r in found}

    try:
        for _ in range(steps):
            largest, now = 0.0, sums()
            for c, at in now.items():
                step = np.clip(np.linalg.solve(-at.hess + 1e-9 * np.eye(d), at.grad), -5, 5)
                theta[c] = np.clip(theta[c] + step, -cap, cap)
                largest = max(largest, float(np.abs(step).max()))
            if largest < 1e-9:
                break
        infos = {c: -at.hess + 1e-9 * np.eye(d) for c, at in sums().items()}
    finally:
        rows.unpersist()
    cov = np.linalg.inv(sum(infos.values()))
    return cov @ sum(infos[c] @ theta[c] for c in infos), cov


def subsample_mcmc(provider: SampleProvider, start: Sums, iters: int = 2000, burn: int = 500, seed: int = 1, prior: NormalPrior | None = None) -> Chain:
    """Chain on difference estimates of the likelihood, each proposal with a subsample of its own; approximate by design."""
    target = lambda theta, t: float(provider.estimate(theta[None, :], t).loglik[0])
    return adaptive_walk(target, start.theta, np.linalg.inv(-start.hess), iters, burn, seed, prior or NormalPrior())


def best_mean_field(theta: np.ndarray, information: np.ndarray) -> DiagonalState:
    """The mean-field optimum for a normal target."""
    return DiagonalState(theta, 1 / np.sqrt(np.diag(information)))


def quadrature_loglik(panels: DataFrame, theta, nodes: int = 40) -> DataFrame:
    """(panel_id, ll, score) by Gauss-Hermite quadrature: the ground truth for panels."""
    from gradvb.panel import panel_frame

    return panel_frame(panels, theta, Integrator("quadrature", nodes))
