"""Unbiased estimates of the log-likelihood gradient from samples, corrected by the anchor's expansion."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gradvb.models import Logit, Model
from gradvb.sampling import draw_indices, index_frame, slice_ranges, slice_sample, tile_counts, tile_sample, with_replacement
from gradvb.sums import Sums, exact_sums, kinds_of, matrix, safeguarded_newton, width

#: A driver engine holds at most this many numbers of sampled rows; beyond it each iteration is a Spark job.
DRIVER_NUMBERS = 20_000_000
#: Sampled rows that one job brings to the driver, unless a single iteration has more.
FETCH_ROWS = 500_000
SURROGATES = ("none", "constant", "linear")


#: Terms (rows x draws) that are worked at once, so that they stay in the processor's cache.
PIECE = 1 << 16


def remainders(x, y, w, thetas, anchor: Sums | None, model: Model, surrogate: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Weighted sums over rows of what the surrogate leaves: gradients (S x d), their squares, and log likelihoods (S)."""
    size = max(1, PIECE // max(1, len(thetas)))
    if len(y) > size:
        parts = [remainders(x[lo : lo + size], y[lo : lo + size], w[lo : lo + size], thetas, anchor, model, surrogate) for lo in range(0, len(y), size)]
        return tuple(sum(p[1:], p[0]) for p in zip(*parts, strict=True))
    z = x @ thetas.T
    value, first = model.pair(z, y[:, None])
    if surrogate != "none":
        centre = x @ anchor.theta
        v0, a0, b0 = (t[:, None] for t in model.block(centre, y))
        move = np.subtract(z, centre[:, None], out=z)
        spare = a0 * move
        value -= v0
        value -= spare
        first -= a0
        if surrogate == "linear":
            first -= np.multiply(b0, move, out=spare)
            np.square(move, out=move)
            move *= 0.5 * b0
            value -= move
    value *= w[:, None]
    spare = first * w[:, None]
    grad = spare.T @ x
    np.square(first, out=spare)
    spare *= w[:, None]
    return grad, spare.T @ x**2, value.sum(axis=0)


def remainder_values(x, y, theta, anchor: Sums | None, model: Model, surrogate: str) -> np.ndarray:
    """Each row's log likelihood at one theta, less the surrogate."""
    value = model.block(x @ theta, y)[0]
    if surrogate != "none":
        centre = x @ anchor.theta
        v0, a0, b0 = model.block(centre, y)
        move = x @ theta - centre
        value = value - v0 - a0 * move
        if surrogate == "linear":
            value = value - 0.5 * b0 * move**2
    return value


def paired_remainders(x, y, w, draw, thetas, anchor, model, surrogate):
    """As ``remainders``, each row for its own draw only."""
    s, d = thetas.shape
    own = thetas[draw]
    value, first, _ = model.block((x * own).sum(axis=1), y)
    if surrogate != "none":
        centre = x @ anchor.theta
        v0, a0, b0 = model.block(centre, y)
        move = (x * own).sum(axis=1) - centre
        value, first = value - v0 - a0 * move, first - a0
        if surrogate == "linear":
            value, first = value - 0.5 * b0 * move**2, first - b0 * move
    grad, square, ll = np.zeros((s, d)), np.zeros((s, d)), np.bincount(draw, weights=w * value, minlength=s)
    np.add.at(grad, draw, (first * w)[:, None] * x)
    np.add.at(square, draw, (first**2 * w)[:, None] * x**2)
    return grad, square, ll


def assemble(thetas: np.ndarray, anchor: Sums | None, grad: np.ndarray, ll: np.ndarray, surrogate: str) -> tuple[np.ndarray, np.ndarray]:
    """Add the surrogate's exact sums to the weighted remainders."""
    if surrogate == "none":
        return grad, ll
    move = thetas - anchor.theta
    ll = ll + anchor.loglik + move @ anchor.grad
    grad = grad + anchor.grad
    if surrogate == "linear":
        grad = grad + move @ anchor.hess
        ll = ll + 0.5 * np.einsum("si,ij,sj->s", move, anchor.hess, move)
    return grad, ll


def equal_rows(x: np.ndarray, y: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Each kind of row once, with the sum of its rows' weights, which leaves every weighted sum as it is."""
    rows = np.column_stack([x, y])
    mixed = np.zeros(len(rows), np.uint64)
    for column in rows.T:
        mixed = (mixed ^ np.ascontiguousarray(column).view(np.uint64)) * np.uint64(0xBF58476D1CE4E5B9)
        mixed ^= mixed >> np.uint64(29)
    _, at, own = np.unique(mixed, return_index=True, return_inverse=True)
    kinds = rows[at]
    if not (kinds[own] == rows).all():  # unequal rows of one hash
        kinds, own = np.unique(rows, axis=0, return_inverse=True)
    return kinds[:, :-1], kinds[:, -1], np.bincount(own.ravel(), weights=w, minlength=len(kinds))


def block_kernel(sample: DataFrame, thetas: np.ndarray, anchor: Sums | None, weight: float | None, model: Model | None = None, surrogate: str = "linear") -> DataFrame:
    """(draw_id, stats, n): per draw the weighted gradient sums, their squares and the log likelihood, from matrix products.

    Each task adds up all of its rows before anything is shuffled, so a shuffle has (tasks x draws) rows. Equal rows of a batch are summed once, as long as they are many.
    A column ``w`` weighs rows (times ``weight``); a column ``draw_id`` ties rows to draws.
    """
    model, (s, d) = model or Logit(), thetas.shape
    shipped = sample.sparkSession.sparkContext.broadcast((thetas, anchor))
    names = sample.columns
    columns = ["y", *(f"x{k}" for k in range(d)), *(c for c in ("w", "draw_id") if c in names)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        points, at = shipped.value
        total, n, many = np.zeros((s, 2 * d + 1)), 0, s >= 16
        for batch in batches:
            x, y = matrix(batch, d)
            w = batch.column("w").to_numpy(zero_copy_only=False) if "w" in names else np.ones(len(y))
            if "draw_id" in names:
                parts = paired_remainders(x, y, w, batch.column("draw_id").to_numpy(zero_copy_only=False), points, at, model, surrogate)
                total += np.column_stack(parts)
            else:
                if many and len(y):
                    kinds = equal_rows(x, y, w)
                    many = len(kinds[1]) <= len(y) // 2
                    x, y, w = kinds
                total += np.column_stack(remainders(x, y, w, points, at, model, surrogate))
            n += batch.num_rows
        total *= weight or 1.0
        yield pa.RecordBatch.from_arrays([pa.array(range(s), pa.int32()), pa.array(list(total), pa.list_(pa.float64())), pa.array([n] * s, pa.int64())], names=["draw_id", "stats", "n"])

    parts = sample.select(*columns).mapInArrow(run, "draw_id int, stats array<double>, n long")
    return parts.groupBy("draw_id").agg(F.array(*(F.sum(F.get("stats", F.lit(k))) for k in range(2 * d + 1))).alias("stats"), F.sum("n").alias("n"))


def column_kernel(sample: DataFrame, thetas: np.ndarray, anchor: Sums, weight: float, model: Model | None = None) -> DataFrame:
    """(draw_id, g0..): the same remainders by a broadcast join with the draws and generated code; for few draws."""
    model, d = model or Logit(), thetas.shape[1]
    draws = sample.sparkSession.createDataFrame([(k, *map(float, t)) for k, t in enumerate(thetas)], "draw_id int, " + ", ".join(f"t{k} double" for k in range(d)))
    z, move = F.lit(0.0), F.lit(0.0)
    for k in range(d):
        z = z + F.col(f"x{k}") * F.col(f"t{k}")
        move = move + F.col(f"x{k}") * (F.col(f"t{k}") - float(anchor.theta[k]))
    _, first, _ = model.column(z, F.col("y"))
    _, a0, b0 = model.column(model.linear(anchor.theta), F.col("y"))
    rest = sample.crossJoin(F.broadcast(draws)).withColumn("rest", first - a0 - b0 * move)
    return rest.groupBy("draw_id").agg(*((F.lit(weight) * F.sum(F.col("rest") * F.col(f"x{k}"))).alias(f"g{k}") for k in range(d)))


@dataclass
class Estimate:
    """Per draw: gradient and log-likelihood estimates; the gradient's estimated variance; rows touched."""

    grad: np.ndarray
    loglik: np.ndarray
    variance: float
    rows: int


def from_frame(frame: DataFrame, thetas: np.ndarray, anchor: Sums | None, surrogate: str) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    s, d = thetas.shape
    stats = np.zeros((s, 2 * d + 1))
    n = 0
    for r in frame.collect():
        stats[r.draw_id] = r.stats
        n = max(n, r.n)
    grad, ll = assemble(thetas, anchor, stats[:, :d], stats[:, 2 * d], surrogate)
    return grad, ll, stats[:, d : 2 * d], n


class ExactProvider:
    """All rows in every iteration: the target that sampling approximates."""

    def __init__(self, obs: DataFrame, model: Model | None = None) -> None:
        self.obs, self.model, self.dim = obs, model or Logit(), width(obs)
        self.n = obs.count()

    def estimate(self, thetas: np.ndarray, iteration: int) -> Estimate:
        grad, ll, _, n = from_frame(block_kernel(self.obs, thetas, None, None, self.model, "none"), thetas, None, "none")
        return Estimate(grad, ll, 0.0, n)


@dataclass
class CellProvider:
    """All rows as weighted covariate cells; exact where covariates take few values."""

    x: np.ndarray
    ones: np.ndarray
    total: np.ndarray
    model: Model = field(default_factory=Logit)

    def __post_init__(self) -> None:
        self.dim, self.n = self.x.shape[1], int(self.total.sum())

    def estimate(self, thetas: np.ndarray, iteration: int) -> Estimate:
        z = self.x @ thetas.T
        l1, a1, _ = self.model.block(z, np.ones_like(z))
        l0, a0, _ = self.model.block(z, np.zeros_like(z))
        on, off = self.ones[:, None], (self.total - self.ones)[:, None]
        return Estimate((a1 * on + a0 * off).T @ self.x, (l1 * on + l0 * off).sum(axis=0), 0.0, len(self.x))

    def loglik(self, theta: np.ndarray) -> float:
        """The log likelihood alone, in pieces that stay in the processor's cache."""
        total = 0.0
        for lo in range(0, len(self.x), PIECE):
            c = slice(lo, lo + PIECE)
            value = self.model.values((self.x[c] @ theta)[:, None], np.array([1.0, 0.0]))
            total += float((value[:, 0] * self.ones[c] + value[:, 1] * (self.total[c] - self.ones[c])).sum())
        return total

    def sums(self, theta: np.ndarray) -> Sums:
        z, on, off = self.x @ theta, self.ones, self.total - self.ones
        l, a, b = (u * on + v * off for u, v in zip(self.model.block(z, np.ones_like(z)), self.model.block(z, np.zeros_like(z)), strict=True))
        return Sums(theta, self.n, float(l.sum()), self.x.T @ a, (self.x * b[:, None]).T @ self.x)

    def fit_mle(self, steps: int = 30, cap: float = 25.0) -> Sums:
        """As that of rows, to rounding."""
        return safeguarded_newton(lambda theta: self.sums(np.clip(theta, -cap, cap)), np.zeros(self.dim), steps)


def sufficient_cells(obs: DataFrame, limit: int | None = None, model: Model | None = None) -> CellProvider:
    """Counts and successes per covariate cell by one aggregate; refused beyond ``limit`` cells, or so many as the driver has numbers for."""
    xs = [f"x{k}" for k in range(width(obs))]
    limit = limit or DRIVER_NUMBERS // (len(xs) + 2)
    cells = obs.groupBy(*xs).agg(F.count("*").cast("double").alias("n"), F.sum("y").cast("double").alias("ones")).limit(limit + 1).toArrow()
    if cells.num_rows > limit:
        raise ValueError(f"more than {limit} covariate cells; use row sums")
    x, (n, ones) = np.column_stack([cells.column(c).to_numpy() for c in xs]), (cells.column(c).to_numpy() for c in ("n", "ones"))
    order = np.lexsort(x.T[::-1])
    return CellProvider(x[order], ones[order], n[order], model or Logit())


#: A larger store is held by the kinds of its rows, if these are at most so many (and a quarter of the rows): four bytes a row.
HELD_ROWS, HELD_KINDS = 40_000_000, 1_000_000
#: Rows of which one job brings the kinds, in ``FETCH_ROWS``: eight bytes a row, where a row that is fetched has seven times eight or more.
KIND_FETCHES = 8


class HeldStore:
    """A small store as arrays on the driver, so that samples are looked up without a job; fetched once, some tiles at a time.

    A larger one whose rows are of few kinds is held as those kinds and each row's kind, which executors look up.
    """

    def __init__(self, store: DataFrame, counts: dict[int, int]) -> None:
        self.store, self.counts, self.dim = store, counts, width(store)
        self.x: np.ndarray | None = None

    def small(self) -> bool:
        return sum(self.counts.values()) * (self.dim + 3) <= DRIVER_NUMBERS and max(self.counts.values(), default=0) <= FETCH_ROWS

    @cached_property
    def kinds(self) -> np.ndarray | None:
        """The store's kinds of rows (x, y), sorted; None where they are too many."""
        found = kinds_of(self.store, min(HELD_KINDS, sum(self.counts.values()) // 4))
        return None if found is None else found[0]

    def fits(self) -> bool:
        return self.small() or (sum(self.counts.values()) <= HELD_ROWS and self.kinds is not None)

    def groups(self, most: int) -> list[list[int]]:
        """Tiles that are fetched together: up to ``most`` rows, or a single one."""
        groups: list[list[int]] = [[]]
        for t in sorted(self.counts):
            if groups[-1] and sum(self.counts[k] for k in groups[-1]) + self.counts[t] > most:
                groups.append([])
            groups[-1].append(t)
        return groups

    def load(self) -> None:
        if self.x is not None:
            return
        tiles = sorted(self.counts)
        sizes = np.array([self.counts[t] for t in tiles], np.int64)
        self.first = np.zeros(tiles[-1] + 1, np.int64)
        self.first[tiles] = np.cumsum(sizes) - sizes
        if not self.small():
            self.load_kinds(int(sizes.sum()))
            return
        x, y = np.zeros((int(sizes.sum()), self.dim)), np.zeros(int(sizes.sum()))
        for group in self.groups(FETCH_ROWS):
            got = self.store.where(F.col("tile").isin(group)).select("tile", "row_idx", "y", *(f"x{k}" for k in range(self.dim))).toArrow()
            at = self.places(*(got.column(c).to_numpy() for c in ("tile", "row_idx")))
            y[at] = got.column("y").to_numpy()
            for k in range(self.dim):
                x[at, k] = got.column(f"x{k}").to_numpy()
        kinds, self.kind = np.unique(np.column_stack([x, y]), axis=0, return_inverse=True)
        self.kind = self.kind.ravel()
        self.few = len(kinds) <= len(y) // 4
        self.x, self.y = (np.ascontiguousarray(kinds[:, :-1]), kinds[:, -1].copy()) if self.few else (x, y)

    def load_kinds(self, n: int) -> None:
        """Each row's kind: executors send one number a row for its place and kind, at most ``KIND_FETCHES`` times ``FETCH_ROWS`` a job."""
        names, spark, most = [*(f"x{k}" for k in range(self.dim)), "y"], self.store.sparkSession, KIND_FETCHES * FETCH_ROWS
        table = pa.table({c: self.kinds[:, k] for k, c in enumerate(names)} | {"kind": np.arange(len(self.kinds), dtype=np.int64)})
        place = F.get(F.array(*(F.lit(int(v)) for v in self.first)), F.col("tile")) + F.col("row_idx")
        rows = self.store.select("tile", "row_idx", *names).join(F.broadcast(spark.createDataFrame(table)), names)
        self.kind = np.full(n, -1, np.int32)
        for group, lo in ((g, lo) for g in self.groups(most) for lo in range(0, max(self.counts[t] for t in g), most)):
            here = F.col("tile").isin(group) & (F.col("row_idx") >= lo) & (F.col("row_idx") < lo + most)
            at, kind = np.divmod(rows.where(here).select((place * len(self.kinds) + F.col("kind")).alias("at")).toArrow().column("at").to_numpy(), len(self.kinds))
            self.kind[at] = kind
        if self.kind.min(initial=0) < 0:
            raise ValueError("a row of the store has no kind")
        self.few, self.x, self.y = True, np.ascontiguousarray(self.kinds[:, :-1]), self.kinds[:, -1].copy()

    def sample(self, at: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Rows at places, with their weights; where equal rows are many, each kind once with the sum of its rows' weights, which leaves every weighted sum as it is."""
        if not self.few:
            return self.x[at], self.y[at], w
        total = np.bincount(self.kind[at], weights=w, minlength=len(self.y))
        has = np.flatnonzero(total)
        return self.x[has], self.y[has], total[has]

    def places(self, tile: np.ndarray, row: np.ndarray) -> np.ndarray:
        return self.first[tile] + row


class SampleProvider:
    """A fresh sample each iteration, corrected by the anchor's exact sums.

    ``store`` has tile and row_idx (or for chunks, chunk_id in the place of tile). ``scheme``:
    ``replacement`` (m uniform draws), ``chunks`` (a fixed share m_k of each chunk, weight n_k / m_k each),
    ``tile`` (whole tiles) or ``slice`` (m rows that follow each other in the store's random order; with the last two an iteration reads
    its sample alone, not the store). ``pairing``: all draws share a sample, or each has its own. ``engine``:
    ``driver`` fetches the bounded samples of several iterations by one job and works them in
    memory; ``spark`` runs a job each iteration and returns sums only; ``auto`` goes by size. The driver engine holds a store of at most
    ``DRIVER_NUMBERS``, or of few kinds of rows, whole (``whole`` shares it among providers; without ``hold`` it never does) and takes the same samples from it.
    """

    def __init__(
        self, store: DataFrame, anchor: Sums | None, m: float, model: Model | None = None, seed: int = 1, scheme: str = "replacement", surrogate: str = "linear",
        pairing: str = "shared", engine: str = "auto", block: int = 10, counts: dict[int, int] | None = None,
        hold: bool = True, whole: HeldStore | None = None,
    ) -> None:
        if surrogate not in SURROGATES:
            raise ValueError(f"unknown surrogate {surrogate}")
        self.model, self.anchor, self.seed = model or Logit(), anchor, seed
        self.scheme, self.surrogate, self.pairing = scheme, surrogate, pairing
        self.store = store.withColumnRenamed("chunk_id", "tile") if scheme == "chunks" and "tile" not in store.columns else store
        self.counts = counts or tile_counts(self.store)
        self.n, self.dim = sum(self.counts.values()), width(store)
        self.m = max(1, round(m * self.n)) if m < 1 else int(m)
        if self.m > self.n:
            raise ValueError(f"a sample of {self.m} from {self.n} rows")
        self.block = max(1, min(block, FETCH_ROWS // self.m))
        self.whole = whole if whole is not None and whole.counts == self.counts else HeldStore(self.store, self.counts)
        numbers = self.m * block * (self.dim + 3)
        if hold and self.whole.fits():
            numbers = 0  # nothing is fetched for a block
        self.engine = engine if engine != "auto" else "driver" if scheme != "tile" and pairing == "shared" and numbers <= DRIVER_NUMBERS else "spark"
        self.held: dict[int, tuple] = {}
        self.holds = hold and self.engine == "driver" and self.whole.fits()

    def indices(self, iteration: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        if self.scheme == "chunks":
            tiles, rows, weights = [], [], []
            for t, n in sorted(self.counts.items()):
                m_k = max(1, round(self.m * n / self.n))
                tile, row = draw_indices({t: n}, m_k, self.seed, iteration, t)
                tiles.append(tile)
                rows.append(row)
                weights.append(np.full(m_k, n / m_k))
            return np.concatenate(tiles), np.concatenate(rows), np.concatenate(weights)
        tile, row = draw_indices(self.counts, self.m, self.seed, iteration)
        return tile, row, np.full(self.m, self.n / self.m)

    def fetch(self, first: int) -> None:
        """The rows of a block of iterations by one join with the list of their indices."""
        import pandas as pd

        xs = [f"x{k}" for k in range(self.dim)]
        self.held = {}
        if self.scheme == "slice":
            rows, weight = slice_sample(self.store, self.counts, self.m, self.seed, range(first, first + self.block))
            got = rows.select("iteration", "y", *xs).toArrow().to_pandas()
            self.held = {k: (g[xs].to_numpy(float), g["y"].to_numpy(float), np.full(len(g), weight)) for k, g in got.groupby("iteration")}
            return
        parts = []
        for k in range(first, first + self.block):
            tile, row, w = self.indices(k)
            parts.append(pd.DataFrame({"iteration": np.int32(k), "tile": tile.astype(np.int32), "row_idx": row, "w": w}))
        index = pd.concat(parts).groupby(["iteration", "tile", "row_idx"], as_index=False)["w"].sum()
        frame = index_frame(self.store.sparkSession, index).withColumn("tile", F.col("tile").cast("int"))
        got = self.store.select("tile", "row_idx", "y", *xs).join(F.broadcast(frame), ["tile", "row_idx"]).select("iteration", "w", "y", *xs).toArrow().to_pandas()
        self.held = {k: (g[xs].to_numpy(float), g["y"].to_numpy(float), g["w"].to_numpy(float)) for k, g in got.groupby("iteration")}

    def looked_up(self, iteration: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The sample that ``fetch`` would bring, from the store held here."""
        self.whole.load()
        if self.scheme == "slice":
            at = np.concatenate([np.arange(lo, hi) + self.whole.first[tile] for tile, lo, hi in slice_ranges(self.counts, self.m, self.seed, iteration)])
            self.touched = len(at)
            return self.whole.sample(at, np.full(len(at), self.n / self.m))
        tile, row, w = self.indices(iteration)
        at, own = np.unique(self.whole.places(tile, row), return_inverse=True)
        self.touched = len(at)
        return self.whole.sample(at, np.bincount(own, weights=w))

    def rows(self, iteration: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The iteration's sample (x, y, w) in memory; the driver engine's."""
        if self.holds:
            return self.looked_up(iteration)
        if iteration not in self.held:
            self.fetch(iteration)
        return self.held[iteration]

    def estimate(self, thetas: np.ndarray, iteration: int) -> Estimate:
        if self.engine == "driver":
            x, y, w = self.rows(iteration)
            grad, square, ll = remainders(x, y, w, thetas, self.anchor, self.model, self.surrogate)
            rows = self.touched if self.holds else len(y)
            grad_rest, square = grad, square
            grad, ll = assemble(thetas, self.anchor, grad, ll, self.surrogate)
        else:
            frame, weight = self.sample(iteration, len(thetas))
            frame = block_kernel(frame, thetas, self.anchor, weight, self.model, self.surrogate)
            grad, ll, square, rows = from_frame(frame, thetas, self.anchor, self.surrogate)
            grad_rest = None
        variance = square * self.n / max(1, self.m)
        if grad_rest is not None:
            variance = variance - grad_rest**2 / max(1, self.m)
        return Estimate(grad, ll, float(np.maximum(variance, 0).mean()), rows)

    def sample(self, iteration: int, draws: int) -> tuple[DataFrame, float | None]:
        if self.scheme == "slice":
            return slice_sample(self.store, self.counts, self.m, self.seed, range(iteration, iteration + 1))
        if self.scheme == "tile":
            tiles = len(self.counts)
            return tile_sample(self.store, tiles, max(1, round(self.m / self.n * tiles)), self.seed, iteration)
        if self.scheme == "chunks":
            import pandas as pd

            tile, row, w = self.indices(iteration)
            index = pd.DataFrame({"tile": tile.astype(np.int32), "row_idx": row, "w": w}).groupby(["tile", "row_idx"], as_index=False)["w"].sum()
            frame = index_frame(self.store.sparkSession, index).withColumn("tile", F.col("tile").cast("int"))
            return self.store.join(F.broadcast(frame), ["tile", "row_idx"]), None
        return with_replacement(self.store, self.counts, self.m, self.seed, iteration, draws if self.pairing == "per_draw" else None)


def anchor_sums(obs: DataFrame, theta, model: Model | None = None) -> Sums:
    """The only full pass of a fit: log likelihood, gradient and Hessian at the anchor."""
    return exact_sums(obs, theta, model, 2)
