"""The contract of chunked work: a reader gives chunks, a map estimates on one of them, a reduce adds the estimates up.

The parts of this contract can lie in different stores: only the map's results, a row for each chunk and draw, ever meet.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gradvb.estimators import SampleProvider, assemble
from gradvb.models import Logit, Model
from gradvb.sampling import build_store, tile_counts
from gradvb.sums import Sums, sum_expressions, width


@dataclass
class ChunkReader:
    """Chunks of a table, at random by a hash of its key, or given as tables of their own."""

    parts: dict[int, DataFrame]

    @classmethod
    def split(cls, obs: DataFrame, chunks: int, key: str = "obs_key") -> ChunkReader:
        """One layout of the table; a chunk is a filter on its number."""
        store = build_store(obs, chunks, key).cache()
        return cls({k: store.where(F.col("tile") == k) for k in sorted(tile_counts(store))})

    @classmethod
    def of(cls, tables: Iterable[DataFrame], key: str = "obs_key") -> ChunkReader:
        """Tables that already lie apart, each a chunk."""
        return cls({k: build_store(t, 1, key).withColumn("tile", F.lit(k)) for k, t in enumerate(tables)})

    def map(self, work: Callable[[int, DataFrame], DataFrame]) -> DataFrame:
        """``work`` on every chunk; its rows under each other."""
        return reduce(DataFrame.unionByName, (work(k, part) for k, part in self.parts.items()))


def exact_map(theta, model: Model | None = None, order: int = 1) -> Callable[[int, DataFrame], DataFrame]:
    """A chunk's log likelihood and gradient at theta."""
    return lambda k, part: part.agg(*sum_expressions(model or Logit(), theta, order)).withColumn("chunk_id", F.lit(k))


def sampled_map(thetas: np.ndarray, anchor: Sums, share: float, iteration: int = 0, seed: int = 1, model: Model | None = None) -> Callable[[int, DataFrame], DataFrame]:
    """A chunk's weighted remainders (chunk_id, draw_id, ll, g0..) from a share of its rows."""
    d = len(anchor.theta)

    def work(k: int, part: DataFrame) -> DataFrame:
        rows = part.count()
        own = SampleProvider(part, anchor, max(1, round(share * rows)), model, seed + 7919 * k, engine="spark", counts={k: rows})
        from gradvb.estimators import block_kernel

        frame, weight = own.sample(iteration, len(thetas))
        stats = block_kernel(frame, thetas, anchor, weight, model)
        return stats.select(F.lit(k).alias("chunk_id"), "draw_id", F.get("stats", F.lit(2 * d)).alias("ll"), *(F.get("stats", F.lit(j)).alias(f"g{j}") for j in range(d)))

    return work


def reduce_chunks(mapped: DataFrame, by: str | None = None) -> DataFrame:
    """Sums over chunks of all that was mapped, of the whole or by draw."""
    names = [c for c in mapped.columns if c not in ("chunk_id", by)]
    grouped = mapped.groupBy(by) if by else mapped.groupBy()
    return grouped.agg(*(F.sum(c).alias(c) for c in names))


def reduced_estimate(reader: ChunkReader, thetas: np.ndarray, anchor: Sums, share: float, iteration: int = 0, seed: int = 1, model: Model | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Gradient and log-likelihood estimates of the whole table from the chunks' ones."""
    d = width(next(iter(reader.parts.values())))
    rows = {r.draw_id: r for r in reduce_chunks(reader.map(sampled_map(thetas, anchor, share, iteration, seed, model)), "draw_id").collect()}
    grad = np.array([[rows[s][f"g{j}"] for j in range(d)] for s in range(len(thetas))])
    return assemble(thetas, anchor, grad, np.array([rows[s].ll for s in range(len(thetas))]), "linear")
