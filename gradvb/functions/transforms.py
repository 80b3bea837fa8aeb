"""Maps of constrained parameters to the real line and back, where a normal approximation fits better.

Each has ``forward`` and ``back`` as column expressions, the same as numpy twins, and the log of the derivative of ``back``,
which a log density gains when its parameter is replaced.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from gradvb.functions.scalars import sigmoid, sigmoid_np, softplus, softplus_np


@dataclass(frozen=True)
class Transform:
    forward: Callable[[Column], Column]
    back: Callable[[Column], Column]
    log_slope: Callable[[Column], Column]
    forward_np: Callable[[np.ndarray], np.ndarray]
    back_np: Callable[[np.ndarray], np.ndarray]
    log_slope_np: Callable[[np.ndarray], np.ndarray]


#: ``real`` as it is, ``positive`` by logs, ``unit`` (0 to 1) by logits, ``correlation`` (-1 to 1) by the inverse hyperbolic tangent.
TRANSFORMS = {
    "real": Transform(lambda v: v, lambda z: z, lambda z: z * 0.0, lambda v: v, lambda z: z, np.zeros_like),
    "positive": Transform(F.log, F.exp, lambda z: z, np.log, np.exp, lambda z: z),
    "unit": Transform(lambda v: F.log(v / (1 - v)), sigmoid, lambda z: -softplus(z) - softplus(-z), lambda v: np.log(v / (1 - v)), sigmoid_np, lambda z: -softplus_np(z) - softplus_np(-z)),
    "correlation": Transform(
        lambda v: 0.5 * F.log((1 + v) / (1 - v)), lambda z: 2 * sigmoid(2 * z) - 1, lambda z: F.log(F.lit(4.0)) - softplus(2 * z) - softplus(-2 * z),
        lambda v: 0.5 * np.log((1 + v) / (1 - v)), lambda z: 2 * sigmoid_np(2 * z) - 1, lambda z: np.log(4.0) - softplus_np(2 * z) - softplus_np(-2 * z),
    ),
}


@dataclass(frozen=True)
class Transformed:
    """A vector whose entries have transforms by name: between natural values and the real line, with the density's correction."""

    names: tuple[str, ...]

    def to_real(self, values: np.ndarray) -> np.ndarray:
        return np.stack([TRANSFORMS[n].forward_np(values[..., k]) for k, n in enumerate(self.names)], axis=-1)

    def to_natural(self, z: np.ndarray) -> np.ndarray:
        return np.stack([TRANSFORMS[n].back_np(z[..., k]) for k, n in enumerate(self.names)], axis=-1)

    def log_slope(self, z: np.ndarray) -> np.ndarray:
        return sum(TRANSFORMS[n].log_slope_np(z[..., k]) for k, n in enumerate(self.names))

    def marginals(self, mean: np.ndarray, sd: np.ndarray, draws: int = 4096) -> tuple[np.ndarray, np.ndarray]:
        """Means and sds of the natural values, by even normal quantiles of each entry."""
        from gradvb.functions.scalars import norm_ppf_np

        z = mean + sd * norm_ppf_np((np.arange(draws) + 0.5) / draws)[:, None]
        natural = self.to_natural(z)
        return natural.mean(axis=0), natural.std(axis=0)
