"""The stochastic natural-gradient loop."""

from __future__ import annotations

import time
from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from gradvb.draws import DrawSource
from gradvb.estimators import ExactProvider, HeldStore, SampleProvider, anchor_sums
from gradvb.families import Gaussian, NormalPrior, init_state
from gradvb.models import Logit, Model
from gradvb.plans.planner import plan_fit
from gradvb.sampling import CACHED_ROWS, lay_out, tile_counts
from gradvb.sums import Sums, fit_anchor


@dataclass(frozen=True)
class StepSize:
    """Steps whose sum diverges while that of their squares converges."""

    kind: str = "harmonic"
    t0: float = 1.0
    power: float = 1.0
    hold: int = 5

    def __call__(self, t: int) -> float:
        if self.kind == "harmonic":
            return 1 / (t + self.t0)
        if self.kind == "power":
            if not 0.5 < self.power <= 1:
                raise ValueError("the power must lie in (1/2, 1]")
            return (t + 1 + self.t0) ** -self.power
        if self.kind == "constant_then_decay":
            return 0.5 if t < self.hold else 0.5 / (t - self.hold + 1)
        raise ValueError(f"unknown step {self.kind}")


@dataclass(frozen=True)
class FitConfig:
    """Settings of a fit. As they are, it begins at the subset's estimate and takes the steps as ``step`` gives them.

    ``start="warm"`` first settles the state on the anchor's expansion, ``bound_steps`` cuts natural steps by how much steeper
    the target is than the family; both are additions, and ``settled()`` turns both on. ``tiles=0`` leaves the layout to the planner.
    """

    draws: str = "rqmc"
    s: int = 256
    m: float = 0.01
    tolerance: float = 1e-5
    window: int = 5
    max_iter: int = 100
    stop: str = "bound"
    step: StepSize = field(default_factory=lambda: StepSize(t0=5.0))
    surrogate: str = "linear"
    pairing: str = "shared"
    scheme: str = "auto"
    geometry: str = "natural"
    estimator: str = "reparam"
    analytic: bool = True
    family: str = "factor"
    factors: int = 1
    scrambling: str = "nested"
    start: str = "subset"
    bound_steps: bool = False
    anchor_fraction: float = 0.3
    tiles: int = 0
    engine: str = "auto"
    seed: int = 1
    seconds: float = float("inf")

    def settled(self) -> FitConfig:
        """The same fit from the settled start, with bounded steps that begin at one."""
        return replace(self, start="warm", bound_steps=True, step=StepSize())


def window_change(values: list, window: int):
    """Change of the mean of the last ``window`` values against that one step before; None while too few."""
    if len(values) < window + 1:
        return None
    return np.mean(values[-window:], axis=0) - np.mean(values[-window - 1 : -1], axis=0)


@dataclass
class FitResult:
    state: Gaussian
    anchor: np.ndarray | None
    trace: list[dict]
    status: str
    seconds: float

    @property
    def iterations(self) -> int:
        return len(self.trace)

    @property
    def bound(self) -> float:
        return self.trace[-1]["lb_avg"] if self.trace else float("nan")

    def summary(self, spark: SparkSession, truth=None, names: list[str] | None = None) -> DataFrame:
        mean, sd = self.state.marginals()
        names = names or [f"b{k}" for k in range(len(mean))]
        pick = lambda v, k: None if v is None else float(v[k])
        rows = [(names[k], float(mean[k]), float(sd[k]), pick(self.anchor, k), pick(truth, k)) for k in range(len(mean))]
        return spark.createDataFrame(rows, "param string, mean double, sd double, anchor double, truth double")

    def trace_frame(self, spark: SparkSession) -> DataFrame:
        schema = "iter int, a double, mu array<double>, lb double, lb_n double, lb_avg double, grad_norm double, grad_var double, rows_touched bigint, seconds double"
        return spark.createDataFrame([tuple(r.values()) for r in self.trace], schema)


def bound_gradient(state: Gaussian, eps: np.ndarray, thetas: np.ndarray, grad: np.ndarray, ll: np.ndarray, prior: NormalPrior, cfg: FitConfig) -> np.ndarray:
    """Gradient of the lower bound by the state's parameters."""
    if cfg.estimator == "score":
        score = state.score(thetas)
        height = ll + prior.log_density(thetas) - state.log_density(thetas)
        spread = score - score.mean(axis=0)
        base = (spread * (score * height[:, None])).mean(axis=0) / np.maximum((spread**2).mean(axis=0), 1e-300)
        return (score * (height[:, None] - base)).mean(axis=0)
    if not cfg.analytic:
        pull = np.linalg.solve(state.cov(), (thetas - state.mu).T).T
        return state.data_gradient(eps, grad - thetas / prior.var + pull)
    return state.analytic_part(prior)[1] + state.data_gradient(eps, grad)


def steepness(state: Gaussian, information: np.ndarray) -> float:
    """How much steeper than the family's covariance the target is in its steepest direction; natural steps above 2 / this diverge."""
    return float(np.abs(np.linalg.eigvals(state.cov() @ information)).max())


def warm_start(state: Gaussian, anchor: Sums, prior: NormalPrior, steps: int = 400) -> Gaussian:
    """The loop on the anchor's quadratic expansion alone, whose expectations are closed forms: no data and no draws."""
    information = -anchor.hess + np.eye(len(anchor.theta)) / prior.var
    for _ in range(steps):
        slope = anchor.grad + anchor.hess @ (state.mu - anchor.theta)
        data = np.concatenate([slope, 0.5 * np.einsum("ij,pji->p", anchor.hess, state.cov_basis())])
        direction = state.natural(state.analytic_part(prior)[1] + data)
        size = min(1.0, 1 / steepness(state, information))
        for _ in range(40):
            try:
                state = state.moved(size * direction)
                break
            except ValueError:
                size /= 2
        if np.abs(size * direction).max() < 1e-10:
            break
    return state


def ascend(provider, state: Gaussian, prior: NormalPrior | None = None, cfg: FitConfig | None = None, anchor=None, curvature: np.ndarray | None = None) -> FitResult:
    """Run the loop on any provider of gradient estimates until it settles, diverges or runs out of time.

    ``curvature`` (the Hessian's sum near the target; by default that of the provider's anchor)
    bounds natural steps where ``cfg.bound_steps`` asks for it. A step that leaves the family is halved until it does not.
    """
    prior, cfg = prior or NormalPrior(), cfg or FitConfig()
    if curvature is None and getattr(provider, "anchor", None) is not None:
        curvature = provider.anchor.hess
    source = DrawSource(cfg.draws, cfg.seed, cfg.scrambling)
    trace, bounds, path, status, began = [], [], [], "max_iter", time.time()
    for t in range(cfg.max_iter):
        tick = time.time()
        eps = source.normals(cfg.s, state.noise_dim(), t)
        thetas = state.sample(eps)
        got = provider.estimate(thetas, t)
        gradient = bound_gradient(state, eps, thetas, got.grad, got.loglik, prior, cfg)
        lb = state.analytic_part(prior)[0] + float(got.loglik.mean())
        direction = state.natural(gradient) if cfg.geometry == "natural" else gradient / provider.n
        if not (np.isfinite(direction).all() and np.isfinite(lb)):
            status = "diverged"
            break
        size, moved = cfg.step(t), None
        if cfg.bound_steps and curvature is not None and cfg.geometry == "natural":
            size = min(size, 1 / steepness(state, np.eye(state.dim) / prior.var - curvature))
        for _ in range(40):
            try:
                moved = state.moved(size * direction)
                break
            except ValueError:
                size /= 2
        if moved is None or not np.isfinite(moved.params()).all() or np.abs(moved.mu).max() > 1e6:
            status = "diverged"
            break
        state = moved
        bounds.append(lb / provider.n)
        path.append(state.params())
        trace.append(
            {"iter": t, "a": size, "mu": [float(v) for v in state.mu], "lb": lb, "lb_n": lb / provider.n, "lb_avg": float(np.mean(bounds[-cfg.window :])), "grad_norm": float(np.linalg.norm(gradient)), "grad_var": got.variance, "rows_touched": int(got.rows), "seconds": time.time() - tick}
        )
        change = window_change(bounds if cfg.stop == "bound" else path, cfg.window)
        if change is not None and np.abs(change).max() < cfg.tolerance:
            status = "settled"
            break
        if time.time() - began > cfg.seconds:
            status = "out_of_time"
            break
    return FitResult(state, anchor, trace, status, time.time() - began)


def first_state(subset: Sums, anchor: Sums, prior: NormalPrior, cfg: FitConfig) -> Gaussian:
    """From the subset's information scaled up; ``warm`` then settles it on the anchor's expansion."""
    state = init_state(anchor.theta, -subset.hess, anchor.n / subset.n, cfg.factors, cfg.family)
    return warm_start(state, anchor, prior) if cfg.start == "warm" else state


@dataclass
class Prepared:
    """What fits of one table share: the store, its counts, the subset's fit and the anchor's exact sums."""

    store: DataFrame
    counts: dict[int, int]
    subset: Sums
    anchor: Sums
    model: Model

    def __post_init__(self) -> None:
        self.whole = HeldStore(self.store, self.counts)

    def start(self, cfg: FitConfig, prior: NormalPrior | None = None) -> Gaussian:
        return first_state(self.subset, self.anchor, prior or NormalPrior(), cfg)

    def scheme(self, cfg: FitConfig) -> str:
        """The configured scheme; ``auto`` is the planner's, with slices for stores too large to scan again."""
        if cfg.scheme != "auto":
            return cfg.scheme
        n = sum(self.counts.values())
        planned = plan_fit(n, len(self.anchor.theta), cfg.m, cfg.s).scheme
        return "slice" if planned == "replacement" and n > CACHED_ROWS else planned

    def provider(self, cfg: FitConfig, seed: int | None = None) -> SampleProvider:
        return SampleProvider(self.store, self.anchor, cfg.m, self.model, cfg.seed if seed is None else seed, self.scheme(cfg), cfg.surrogate, cfg.pairing, cfg.engine, counts=self.counts, whole=self.whole)


def prepare(obs: DataFrame, model: Model | None = None, cfg: FitConfig | None = None, key: str = "obs_key", chunk_col: str | None = None) -> Prepared:
    """Lay the table out once, fit the subset, and make the one full pass at the anchor."""
    cfg, model = cfg or FitConfig(), model or Logit()
    store = lay_out(obs, cfg.tiles, key)
    counts = tile_counts(store)
    subset = fit_anchor(store, model, cfg.anchor_fraction, key)
    return Prepared(store, counts, subset, anchor_sums(store, subset.theta, model), model)


def fit_ngvb(obs: DataFrame, model: Model | None = None, prior: NormalPrior | None = None, cfg: FitConfig | None = None, key: str = "obs_key") -> FitResult:
    """Fit by noisy natural gradients: subset fit, one full pass, then small samples only."""
    cfg = cfg or FitConfig()
    ready = prepare(obs, model, cfg, key)
    try:
        return ascend(ready.provider(cfg), ready.start(cfg, prior), prior, cfg, ready.anchor.theta)
    finally:
        ready.store.unpersist()


def fit_exact_vb(obs: DataFrame, start: Gaussian, model: Model | None = None, prior: NormalPrior | None = None, cfg: FitConfig | None = None) -> FitResult:
    """The same loop on all rows: no subsampling error."""
    return ascend(ExactProvider(obs, model), start, prior, cfg)


def compare_models(spark: SparkSession, fits: dict[str, FitResult]) -> DataFrame:
    """Models ranked by their lower bounds."""
    ranked = sorted(fits.items(), key=lambda f: -f[1].trace[-1]["lb"])
    rows = [(k + 1, name, float(f.bound), float(f.trace[-1]["lb"])) for k, (name, f) in enumerate(ranked)]
    return spark.createDataFrame(rows, "rank int, model string, lb_avg_per_row double, lb double")


def choose_factors(ready: Prepared, factors: list[int], cfg: FitConfig | None = None) -> dict[int, FitResult]:
    cfg = cfg or FitConfig()
    out = {}
    for k in factors:
        own = replace(cfg, factors=k)
        out[k] = ascend(ready.provider(own), ready.start(own), None, own, ready.anchor.theta)
    return out


def replicate(fit, seeds: list[int]) -> list[FitResult]:
    """Independent repeats over a shared store; ``fit(seed)`` runs one."""
    return [fit(s) for s in seeds]
