"""Sums of row terms over a table: exact ones, chunked ones, and the anchor's."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gradvb.models import Logit, Model

#: Up to so many parameters sums are columns in generated code, beyond it matrix products of blocks.
COLUMN_DIM = 8


@dataclass(frozen=True)
class Sums:
    """Number of rows, and log likelihood, gradient and Hessian at ``theta``."""

    theta: np.ndarray
    n: int
    loglik: float
    grad: np.ndarray
    hess: np.ndarray | None = None


def width(obs: DataFrame) -> int:
    return sum(1 for c in obs.columns if c[0] == "x" and c[1:].isdigit())


def sum_expressions(model: Model, theta, order: int = 2, z: Column | None = None) -> list[Column]:
    """n, ll, g0.., h0_0.. (upper triangle) as aggregates, at theta or for predictors ``z``; partial sums combine on the map side."""
    d = len(theta)
    ll, first, second = model.column(model.linear(theta) if z is None else z, F.col("y"))
    out = [F.count("*").alias("n"), F.sum(ll).alias("ll")]
    if order >= 1:
        out += [F.sum(first * F.col(f"x{j}")).alias(f"g{j}") for j in range(d)]
    if order >= 2:
        out += [F.sum(second * F.col(f"x{j}") * F.col(f"x{k}")).alias(f"h{j}_{k}") for j in range(d) for k in range(j, d)]
    return out


def unpack(row, theta, order: int = 2) -> Sums:
    d = len(theta)
    value = lambda name: float(row[name] or 0.0)
    grad = np.array([value(f"g{j}") for j in range(d)]) if order >= 1 else np.zeros(d)
    hess = None
    if order >= 2:
        hess = np.zeros((d, d))
        for j in range(d):
            for k in range(j, d):
                hess[j, k] = hess[k, j] = value(f"h{j}_{k}")
    return Sums(np.asarray(theta, float), int(row["n"]), value("ll"), grad, hess)


def matrix(batch: pa.RecordBatch, d: int) -> tuple[np.ndarray, np.ndarray]:
    x = np.column_stack([batch.column(f"x{k}").to_numpy(zero_copy_only=False) for k in range(d)]) if batch.num_rows else np.zeros((0, d))
    return x, batch.column("y").to_numpy(zero_copy_only=False)


def exact_sums(obs: DataFrame, theta, model: Model | None = None, order: int = 2) -> Sums:
    """One pass over the data and one row to the driver."""
    model, d = model or Logit(), len(theta)
    if d <= COLUMN_DIM:
        return unpack(obs.agg(*sum_expressions(model, theta, order)).first(), theta, order)
    theta = np.asarray(theta, float)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, ll, g, h = 0, 0.0, np.zeros(d), np.zeros((d, d))
        for batch in batches:
            x, y = matrix(batch, d)
            l, a, b = model.block(x @ theta, y)
            n, ll, g, h = n + len(y), ll + l.sum(), g + x.T @ a, h + (x * b[:, None]).T @ x
        yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([np.concatenate([[ll], g, h.ravel()])], pa.list_(pa.float64()))], names=["n", "s"])

    parts = obs.select("y", *(f"x{k}" for k in range(d))).mapInArrow(run, "n long, s array<double>")
    rows = parts.select("n", F.posexplode("s").alias("k", "v")).groupBy("k").agg(F.sum("v").alias("v"), F.sum("n").alias("n")).orderBy("k").collect()
    s = np.array([r.v for r in rows])
    return Sums(theta, rows[0].n, s[0], s[1 : d + 1], s[d + 1 :].reshape(d, d))


def chunk_sums(obs: DataFrame, theta, chunk_col: str = "chunk_id", model: Model | None = None, order: int = 1) -> DataFrame:
    """Each chunk's exact sums; their total is the table's whatever the chunks."""
    return obs.groupBy(chunk_col).agg(*sum_expressions(model or Logit(), theta, order))


def chunk_rollup(obs: DataFrame, theta, chunk_col: str = "chunk_id", model: Model | None = None) -> DataFrame:
    """Both levels in one table: a null chunk is the total."""
    return obs.rollup(chunk_col).agg(*sum_expressions(model or Logit(), theta, 1))


def safeguarded_newton(value, start: np.ndarray, steps: int = 30, tol: float = 1e-8) -> Sums:
    """Newton ascent with halved steps; ``value(theta)`` gives Sums of order 2."""
    now = value(start)
    for _ in range(steps):
        info = -now.hess
        ridge = 1e-9 * max(1.0, np.trace(info) / len(info))
        step = np.linalg.solve(info + ridge * np.eye(len(info)), now.grad)
        if not np.isfinite(step).all():
            raise ValueError("the information matrix is singular")
        step *= min(1.0, 10.0 / max(np.abs(step).max(), 1e-300))
        if np.abs(step).max() < tol:
            break
        size = 1.0
        while size > 1e-6:
            new = value(now.theta + size * step)
            if new.loglik >= now.loglik - 1e-9 * abs(now.loglik):
                break
            size /= 2
        now = new
    return now


def fit_mle(obs: DataFrame, model: Model | None = None, start=None, steps: int = 30, cap: float = 25.0) -> Sums:
    """Maximum likelihood by Newton passes; ``cap`` stops separated data from running away."""
    d = width(obs)

    def value(theta: np.ndarray) -> Sums:
        return exact_sums(obs, np.clip(theta, -cap, cap), model)

    return safeguarded_newton(value, np.zeros(d) if start is None else np.asarray(start, float), steps)


def kinds_of(obs: DataFrame, most: int) -> tuple[np.ndarray, np.ndarray] | None:
    """The table's kinds of rows (x, y), sorted, and how many rows each has; None where there are more than ``most`` kinds."""
    names = [*(f"x{k}" for k in range(width(obs))), "y"]
    got = obs.groupBy(*names).agg(F.count("*").cast("double").alias("n")).limit(most + 1).toArrow()
    if got.num_rows > most:
        return None
    kinds = np.column_stack([got.column(c).to_numpy() for c in names])
    order = np.lexsort(kinds.T[::-1])
    return kinds[order], got.column("n").to_numpy()[order]


#: Kinds of rows from which a subset's fit passes over its rows instead.
SUBSET_KINDS = 200_000


def fit_kinds(kinds: np.ndarray, counts: np.ndarray, model: Model, steps: int = 30, cap: float = 25.0) -> Sums:
    """``fit_mle`` of a table's kinds of rows, each with its number of rows: the same to rounding, without a job for each step."""
    x, y = np.ascontiguousarray(kinds[:, :-1]), kinds[:, -1]

    def value(theta: np.ndarray) -> Sums:
        theta = np.clip(theta, -cap, cap)
        l, a, b = (v * counts for v in model.block(x @ theta, y))
        return Sums(theta, int(counts.sum()), float(l.sum()), x.T @ a, (x * b[:, None]).T @ x)

    return safeguarded_newton(value, np.zeros(x.shape[1]), steps)


def fit_anchor(obs: DataFrame, model: Model | None = None, fraction: float = 0.3, key: str = "obs_key", method: str = "mle", seed: int = 3) -> Sums:
    """The expansion point from a hashed subset: its maximum, or the mean of a chain on it; sums are the subset's."""
    from gradvb.functions.scalars import hash_uniform

    part = obs if fraction >= 1 else obs.where(hash_uniform("anchor", F.col(key)) < fraction)
    part = part.select("y", *(f"x{k}" for k in range(width(obs)))).cache()
    try:
        found = kinds_of(part, SUBSET_KINDS) if width(obs) <= COLUMN_DIM else None
        best = fit_kinds(*found, model or Logit()) if found is not None and len(found[1]) else fit_mle(part, model)
        if method == "mcmc":
            from gradvb.baselines import rw_mcmc

            chain = rw_mcmc(part, model=model, iters=2000, burn=500, seed=seed, start=best)
            best = exact_sums(part, chain.draws.mean(axis=0), model)
    finally:
        part.unpersist()
    return best
