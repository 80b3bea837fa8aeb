"""Observation models: row terms as column expressions and as numpy twins.

Every model here is linear in its parameters, so a row's gradient is a scalar times x and its
Hessian another scalar times x x'. ``column`` and ``block`` give (log likelihood, first, second).
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from gradvb.functions.scalars import norm_cdf, norm_cdf_np, norm_pdf, sigmoid, softplus


class Model:
    def column(self, z: Column, y: Column) -> tuple[Column, Column, Column]:
        raise NotImplementedError

    def block(self, z: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        raise NotImplementedError

    def pair(self, z: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The first two of ``block``, as arrays that the caller may change."""
        return tuple(np.array(v) for v in self.block(z, y)[:2])

    def values(self, z: np.ndarray, y: np.ndarray) -> np.ndarray:
        """The log likelihood alone."""
        return self.block(z, y)[0]

    @staticmethod
    def linear(theta) -> Column:
        out = F.lit(float(theta[0])) * F.col("x0")
        for k, t in enumerate(theta[1:], 1):
            out = out + F.lit(float(t)) * F.col(f"x{k}")
        return out


@dataclass(frozen=True)
class Logit(Model):
    """Binary response, logistic link."""

    def column(self, z, y):
        p = sigmoid(z)
        return y * z - softplus(z), y - p, -p * (1 - p)

    def block(self, z, y):
        e = np.exp(-np.abs(z))  # for sigmoid and softplus alike
        p = np.where(z >= 0, 1, e) / (1 + e)
        return y * z - (np.maximum(z, 0) + np.log1p(e)), y - p, -p * (1 - p)

    def pair(self, z, y):
        e = np.abs(z)
        np.negative(e, out=e)
        np.exp(e, out=e)
        p = np.where(z >= 0, 1, e)
        spare = 1 + e
        p /= spare
        value = np.maximum(z, 0)
        value += np.log1p(e, out=e)
        return np.subtract(np.multiply(y, z, out=spare), value, out=value), np.subtract(y, p, out=p)

    def values(self, z, y):
        return y * z - (np.maximum(z, 0) + np.log1p(np.exp(-np.abs(z))))


@dataclass(frozen=True)
class GaussianModel(Model):
    """Normal response of a known sd."""

    sd: float = 1.0

    def column(self, z, y):
        r = (y - z) / self.sd
        return -0.5 * r * r - math.log(self.sd * math.sqrt(2 * math.pi)), r / self.sd, F.lit(-1 / self.sd**2)

    def block(self, z, y):
        r = (y - z) / self.sd
        return -0.5 * r * r - math.log(self.sd * math.sqrt(2 * math.pi)), r / self.sd, np.full_like(r, -1 / self.sd**2)


@dataclass(frozen=True)
class Poisson(Model):
    """Counts, log link; the factorial, which no parameter moves, is left out."""

    def column(self, z, y):
        m = F.exp(z)
        return y * z - m, y - m, -m

    def block(self, z, y):
        m = np.exp(z)
        return y * z - m, y - m, -m


@dataclass(frozen=True)
class Probit(Model):
    """Binary response, normal link."""

    def column(self, z, y):
        s = 2 * y - 1
        p = norm_cdf(s * z)
        a = s * norm_pdf(z) / p
        return F.log(p), a, -a * (a + z)

    def block(self, z, y):
        s = 2 * y - 1
        p = norm_cdf_np(s * z)
        a = s * np.exp(-0.5 * z * z) / math.sqrt(2 * math.pi) / p
        return np.log(p), a, -a * (a + z)


@dataclass(frozen=True)
class NumericModel(Model):
    """A model known by its log likelihood alone, as a column expression and as a numpy function of (z, y); derivatives by central differences."""

    log_column: Callable[[Column, Column], Column]
    log_block: Callable[[np.ndarray, np.ndarray], np.ndarray]
    step: float = 1e-3

    def column(self, z, y):
        h, here = self.step, self.log_column(z, y)
        up, down = self.log_column(z + h, y), self.log_column(z - h, y)
        return here, (up - down) / (2 * h), (up - 2 * here + down) / h**2

    def block(self, z, y):
        h, here = self.step, self.log_block(z, y)
        up, down = self.log_block(z + h, y), self.log_block(z - h, y)
        return here, (up - down) / (2 * h), (up - 2 * here + down) / h**2
