"""Gaussian variational families, their natural gradients and the analytic part of the lower bound."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class NormalPrior:
    """Independent normal prior with mean zero."""

    var: float = 50.0

    def log_density(self, theta: np.ndarray) -> np.ndarray:
        theta = np.atleast_2d(theta)
        return -0.5 * (theta**2).sum(axis=1) / self.var - 0.5 * theta.shape[1] * np.log(2 * np.pi * self.var)


class Gaussian:
    """What all families share; a family gives its covariance parameters' derivatives and its root."""

    mu: np.ndarray

    @property
    def dim(self) -> int:
        return len(self.mu)

    def cov(self) -> np.ndarray:
        raise NotImplementedError

    def cov_basis(self) -> np.ndarray:
        """The covariance's derivative by each of its parameters, stacked."""
        raise NotImplementedError

    def noise_dim(self) -> int:
        return self.dim

    def marginals(self) -> tuple[np.ndarray, np.ndarray]:
        return self.mu, np.sqrt(np.diag(self.cov()))

    def log_density(self, theta: np.ndarray) -> np.ndarray:
        r = np.atleast_2d(theta) - self.mu
        _, logdet = np.linalg.slogdet(self.cov())
        return -0.5 * (r * np.linalg.solve(self.cov(), r.T).T).sum(axis=1) - 0.5 * logdet - 0.5 * self.dim * np.log(2 * np.pi)

    def score(self, theta: np.ndarray) -> np.ndarray:
        """Gradient of the log density by all parameters, a row per theta."""
        r = np.atleast_2d(theta) - self.mu
        precision = np.linalg.inv(self.cov())
        u = r @ precision
        basis = self.cov_basis()
        quad = 0.5 * np.einsum("si,pij,sj->sp", u, basis, u) - 0.5 * np.einsum("ij,pji->p", precision, basis)
        return np.hstack([u, quad])

    def fisher(self) -> np.ndarray:
        precision = np.linalg.inv(self.cov())
        basis = np.einsum("ij,pjk->pik", precision, self.cov_basis())
        lower = 0.5 * np.einsum("pij,qji->pq", basis, basis)
        d, p = self.dim, len(lower)
        out = np.zeros((d + p, d + p))
        out[:d, :d], out[d:, d:] = precision, lower
        return out

    def analytic_part(self, prior: NormalPrior) -> tuple[float, np.ndarray]:
        """Expected log prior plus entropy, and its gradient by all parameters; no draws are needed."""
        cov, d = self.cov(), self.dim
        _, logdet = np.linalg.slogdet(cov)
        value = -0.5 * (self.mu @ self.mu + np.trace(cov)) / prior.var + 0.5 * logdet + 0.5 * d * (1 - np.log(prior.var))
        slope = 0.5 * np.linalg.inv(cov) - 0.5 * np.eye(d) / prior.var
        return float(value), np.concatenate([-self.mu / prior.var, np.einsum("ij,pji->p", slope, self.cov_basis())])

    def natural(self, gradient: np.ndarray) -> np.ndarray:
        return np.linalg.solve(self.fisher(), gradient)


@dataclass
class RankOneState(Gaussian):
    """Covariance B B' + c^2 I: one factor and one common variance, 2d + 1 numbers.

    ``signed`` lets c be negative, which is the same distribution with mirrored noise; loops keep it positive.
    """

    mu: np.ndarray
    b: np.ndarray
    c: float
    signed: bool = False

    def __post_init__(self) -> None:
        if len(self.mu) < 2:
            raise ValueError("one factor needs two dimensions at least; take DiagonalState for one")
        if not self.b @ self.b > 0:
            raise ValueError("the factor must not vanish")
        if not (self.c > 0 or self.signed and self.c < 0):
            raise ValueError("c must be positive")

    def params(self) -> np.ndarray:
        return np.concatenate([self.mu, self.b, [self.c]])

    def moved(self, step: np.ndarray) -> RankOneState:
        d = self.dim
        return RankOneState(self.mu + step[:d], self.b + step[d : 2 * d], float(self.c + step[2 * d]), self.signed)

    def cov(self) -> np.ndarray:
        return np.outer(self.b, self.b) + self.c**2 * np.eye(self.dim)

    def solve(self, v: np.ndarray) -> np.ndarray:
        """Covariance inverse times v in O(d)."""
        return (v - self.b * (self.b @ v) / (self.c**2 + self.b @ self.b)) / self.c**2

    def logdet(self) -> float:
        return float(2 * self.dim * np.log(abs(self.c)) + np.log1p(self.b @ self.b / self.c**2))

    def cov_basis(self) -> np.ndarray:
        d = self.dim
        eye = np.eye(d)
        by_b = np.einsum("pi,j->pij", eye, self.b)
        return np.concatenate([by_b + by_b.transpose(0, 2, 1), 2 * self.c * eye[None]])

    def noise_dim(self) -> int:
        return self.dim + 1

    def sample(self, eps: np.ndarray) -> np.ndarray:
        return self.mu + eps[:, :1] * self.b + self.c * eps[:, 1:]

    def data_gradient(self, eps: np.ndarray, g: np.ndarray) -> np.ndarray:
        """Reparameterised gradient of the expected log likelihood from gradients at the sampled points."""
        return np.concatenate([g.mean(axis=0), (eps[:, :1] * g).mean(axis=0), [(eps[:, 1:] * g).sum(axis=1).mean()]])

    def marginals(self) -> tuple[np.ndarray, np.ndarray]:
        return self.mu, np.sqrt(self.b**2 + self.c**2)

    def analytic_part(self, prior: NormalPrior) -> tuple[float, np.ndarray]:
        d, bb = self.dim, self.b @ self.b
        value = -0.5 * (self.mu @ self.mu + bb + d * self.c**2) / prior.var + 0.5 * self.logdet() + 0.5 * d * (1 - np.log(prior.var))
        a = 1 / (self.c**2 + bb)
        return float(value), np.concatenate([-self.mu / prior.var, (a - 1 / prior.var) * self.b, [-d * self.c / prior.var + (d - a * bb) / self.c]])

    def natural(self, gradient: np.ndarray) -> np.ndarray:
        """Inverse Fisher matrix times the gradient in O(d)."""
        d, bb, cc = self.dim, self.b @ self.b, self.c**2
        g_mu, g_b, g_c = gradient[:d], gradient[d : 2 * d], gradient[2 * d]
        rho, kappa, spread = 1 + cc / bb, self.c / bb, 2 * (d - 1) / cc
        along = self.b @ g_b
        by_mu = self.b * (self.b @ g_mu) + cc * g_mu
        by_b = (rho - 0.5 * rho**2 + kappa**2 / spread) * along * self.b + cc * rho * g_b - kappa / spread * g_c * self.b
        return np.concatenate([by_mu, by_b, [(g_c - kappa * along) / spread]])


@dataclass
class FactorState(Gaussian):
    """Covariance B B' + c^2 I with k factors."""

    mu: np.ndarray
    b: np.ndarray
    c: float

    def params(self) -> np.ndarray:
        return np.concatenate([self.mu, self.b.ravel(), [self.c]])

    def moved(self, step: np.ndarray) -> FactorState:
        d, size = self.dim, self.b.size
        return FactorState(self.mu + step[:d], self.b + step[d : d + size].reshape(self.b.shape), float(self.c + step[-1]))

    def cov(self) -> np.ndarray:
        return self.b @ self.b.T + self.c**2 * np.eye(self.dim)

    def cov_basis(self) -> np.ndarray:
        d, k = self.b.shape
        out = np.zeros((d * k, d, d))
        for i in range(d):
            for j in range(k):
                out[i * k + j, i, :] += self.b[:, j]
                out[i * k + j, :, i] += self.b[:, j]
        return np.concatenate([out, 2 * self.c * np.eye(d)[None]])

    def noise_dim(self) -> int:
        return self.dim + self.b.shape[1]

    def sample(self, eps: np.ndarray) -> np.ndarray:
        k = self.b.shape[1]
        return self.mu + eps[:, :k] @ self.b.T + self.c * eps[:, k:]

    def data_gradient(self, eps: np.ndarray, g: np.ndarray) -> np.ndarray:
        k = self.b.shape[1]
        return np.concatenate([g.mean(axis=0), (g.T @ eps[:, :k] / len(g)).ravel(), [(eps[:, k:] * g).sum(axis=1).mean()]])

    def natural(self, gradient: np.ndarray) -> np.ndarray:
        """Rotations of the factors leave the covariance as it is, so the Fisher matrix is solved in the least-squares sense."""
        return np.linalg.lstsq(self.fisher(), gradient, rcond=1e-10)[0]


@dataclass
class CholeskyState(Gaussian):
    """Full covariance by its Cholesky root."""

    mu: np.ndarray
    root: np.ndarray

    def params(self) -> np.ndarray:
        return np.concatenate([self.mu, self.root[np.tril_indices(self.dim)]])

    def moved(self, step: np.ndarray) -> CholeskyState:
        root = self.root.copy()
        root[np.tril_indices(self.dim)] += step[self.dim :]
        if (np.diag(root) <= 0).any():
            raise ValueError("the root's diagonal must be positive")
        return CholeskyState(self.mu + step[: self.dim], root)

    def cov(self) -> np.ndarray:
        return self.root @ self.root.T

    def cov_basis(self) -> np.ndarray:
        rows, cols = np.tril_indices(self.dim)
        out = np.zeros((len(rows), self.dim, self.dim))
        for p, (i, j) in enumerate(zip(rows, cols, strict=True)):
            out[p, i, :] += self.root[:, j]
            out[p, :, i] += self.root[:, j]
        return out

    def sample(self, eps: np.ndarray) -> np.ndarray:
        return self.mu + eps @ self.root.T

    def data_gradient(self, eps: np.ndarray, g: np.ndarray) -> np.ndarray:
        return np.concatenate([g.mean(axis=0), (g.T @ eps / len(g))[np.tril_indices(self.dim)]])


@dataclass
class DiagonalState(Gaussian):
    """Mean field: independent coordinates; also the family for a single parameter."""

    mu: np.ndarray
    sd: np.ndarray

    def params(self) -> np.ndarray:
        return np.concatenate([self.mu, self.sd])

    def moved(self, step: np.ndarray) -> DiagonalState:
        sd = self.sd + step[self.dim :]
        if (sd <= 0).any():
            raise ValueError("sds must be positive")
        return DiagonalState(self.mu + step[: self.dim], sd)

    def cov(self) -> np.ndarray:
        return np.diag(self.sd**2)

    def cov_basis(self) -> np.ndarray:
        out = np.zeros((self.dim, self.dim, self.dim))
        out[np.arange(self.dim), np.arange(self.dim), np.arange(self.dim)] = 2 * self.sd
        return out

    def sample(self, eps: np.ndarray) -> np.ndarray:
        return self.mu + eps * self.sd

    def data_gradient(self, eps: np.ndarray, g: np.ndarray) -> np.ndarray:
        return np.concatenate([g.mean(axis=0), (eps * g).mean(axis=0)])

    def natural(self, gradient: np.ndarray) -> np.ndarray:
        d = self.dim
        return np.concatenate([self.sd**2 * gradient[:d], 0.5 * self.sd**2 * gradient[d:]])


def rank_one_inverse(a_inverse: np.ndarray, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Inverse of A + u v' from that of A."""
    left, right = a_inverse @ u, v @ a_inverse
    return a_inverse - np.outer(left, right) / (1 + v @ left)


def bordered_inverse(a_inverse: np.ndarray, edge: np.ndarray, corner: float) -> np.ndarray:
    """Inverse of the symmetric matrix A bordered by a column and a corner."""
    side = a_inverse @ edge
    rest = 1 / (corner - edge @ side)
    return np.block([[a_inverse + rest * np.outer(side, side), -rest * side[:, None]], [-rest * side[None, :], np.array([[rest]])]])


def init_state(theta: np.ndarray, information: np.ndarray, scale: float, factors: int = 1, family: str = "factor") -> Gaussian:
    """A start from a fit on a subset: its information scaled up, the largest eigenpairs as factors, the rest averaged."""
    cov = np.linalg.inv(scale * information)
    if family == "full":
        return CholeskyState(theta, np.linalg.cholesky(cov))
    if family == "diagonal" or len(theta) == 1:
        return DiagonalState(theta, np.sqrt(np.diag(cov)))
    values, vectors = np.linalg.eigh(cov)
    b = vectors[:, ::-1][:, :factors] * np.sqrt(values[::-1][:factors])
    b = b * np.sign(b[np.abs(b).argmax(axis=0), np.arange(factors)])
    c = float(np.sqrt(max(np.trace(cov - b @ b.T), 1e-12 * np.trace(cov)) / len(theta)))
    return RankOneState(theta, b[:, 0], c) if factors == 1 else FactorState(theta, b, c)
