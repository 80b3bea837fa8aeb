"""Table functions, vectorised functions and grouped aggregates in Python, for what SQL has no form of."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from gradvb.draws import scramble, sobol


class SobolPoints:
    """Rows (point, dim, u) of a scrambled net; seed 0 leaves it plain."""

    def eval(self, n: int, dims: int, seed: int) -> Iterator[tuple]:
        points = sobol(n, dims) if not seed else scramble(sobol(n, dims), seed)
        for k, row in enumerate(points):
            for j, value in enumerate(row):
                yield k, j, float((int(value) + (0.5 if seed else 0.0)) / 2**32)


class ExplodeDraws:
    """Rows (draw, k, value) of standard normal draws keyed by the seed."""

    def eval(self, draws: int, dims: int, seed: int) -> Iterator[tuple]:
        z = np.random.Generator(np.random.Philox(key=seed)).standard_normal((draws, dims))
        for s in range(draws):
            for k in range(dims):
                yield s, k, float(z[s, k])


class DensityGrid:
    """Rows (x, pdf) of a normal density on an even grid of ``points`` from four sds below the mean to four above."""

    def eval(self, mean: float, sd: float, points: int) -> Iterator[tuple]:
        for x in np.linspace(mean - 4 * sd, mean + 4 * sd, points):
            yield float(x), float(np.exp(-0.5 * ((x - mean) / sd) ** 2) / (sd * np.sqrt(2 * np.pi)))


def register_tables(spark: SparkSession) -> None:
    for name, cls, schema in (
        ("sobol_points", SobolPoints, "point int, dim int, u double"),
        ("explode_draws", ExplodeDraws, "draw int, k int, value double"),
        ("density_grid", DensityGrid, "x double, pdf double"),
    ):
        spark.udtf.register(name, F.udtf(cls, returnType=schema))


def predict_prob(x: Column, mu: list[float]) -> Column:
    """Vectorised probability of an array column of covariates at fixed coefficients."""
    weights = np.asarray(mu, float)

    @F.pandas_udf(DoubleType())
    def probability(v: pd.Series) -> pd.Series:
        if not len(v):
            return pd.Series([], dtype=float)
        return pd.Series(1 / (1 + np.exp(-np.stack(v.to_numpy()) @ weights)))

    return probability(x)


@F.pandas_udf(DoubleType())
def log_sum_exp(v: pd.Series) -> float:
    """Grouped aggregate; its native twin is ``operators.log_sum_exp``."""
    top = v.max()
    return float(top + np.log(np.exp(v - top).sum()))


def numeric_gradient(df: DataFrame, model, theta: list[float], step: float = 1e-5) -> DataFrame:
    """(k, g): the gradient sums by central differences of the row terms, for models without a formula."""
    centre = np.asarray(theta, float)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(len(centre))
        for batch in batches:
            x = np.column_stack([batch.column(f"x{k}").to_numpy(zero_copy_only=False) for k in range(len(centre))])
            y = batch.column("y").to_numpy(zero_copy_only=False)
            for k in range(len(centre)):
                e = np.zeros(len(centre))
                e[k] = step
                total[k] += ((model.block(x @ (centre + e), y)[0] - model.block(x @ (centre - e), y)[0]) / (2 * step)).sum()
        yield pa.RecordBatch.from_arrays([pa.array(range(len(centre)), pa.int32()), pa.array(total)], names=["k", "g"])

    return df.select("y", *(f"x{k}" for k in range(len(centre)))).mapInArrow(run, "k int, g double").groupBy("k").agg(F.sum("g").alias("g"))
