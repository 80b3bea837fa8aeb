"""Scalar functions as column expressions (JVM-side, inlined by Catalyst), with numpy twins where a kernel needs them."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

#: 2^52, the range of 13 hexadecimal digits.
HEX_RANGE = 4503599627370496.0

#: Rational approximation of the normal quantile, numerators and denominators by highest power last.
PPF_CENTRAL = (
    (3.3871328727963666080e0, 1.3314166789178437745e2, 1.9715909503065514427e3, 1.3731693765509461125e4, 4.5921953931549871457e4, 6.7265770927008700853e4, 3.3430575583588128105e4, 2.5090809287301226727e3),
    (1.0, 4.2313330701600911252e1, 6.8718700749205790830e2, 5.3941960214247511077e3, 2.1213794301586595867e4, 3.9307895800092710610e4, 2.8729085735721942674e4, 5.2264952788528545610e3),
)
PPF_MIDDLE = (
    (1.42343711074968357734e0, 4.63033784615654529590e0, 5.76949722146069140550e0, 3.64784832476320460504e0, 1.27045825245236838258e0, 2.41780725177450611770e-1, 2.27238449892691845833e-2, 7.74545014278341407640e-4),
    (1.0, 2.05319162663775882187e0, 1.67638483018380384940e0, 6.89767334985100004550e-1, 1.48103976427480074590e-1, 1.51986665636164571966e-2, 5.47593808499534494600e-4, 1.05075007164441684324e-9),
)
PPF_TAIL = (
    (6.65790464350110377720e0, 5.46378491116411436990e0, 1.78482653991729133580e0, 2.96560571828504891230e-1, 2.65321895265761230930e-2, 1.24266094738807843860e-3, 2.71155556874348757815e-5, 2.01033439929228813265e-7),
    (1.0, 5.99832206555887937690e-1, 1.36929880922735805310e-1, 1.48753612908506148525e-2, 7.86869131145613259100e-4, 1.84631831751005468180e-5, 1.42151175831644588870e-7, 2.04426310338993978564e-15),
)
#: Rational approximation of the normal distribution function, by highest power first.
CDF_TOP = (3.52624965998911e-2, 0.700383064443688, 6.37396220353165, 33.912866078383, 112.079291497871, 221.213596169931, 220.206867912376)
CDF_BOTTOM = (8.83883476483184e-2, 1.75566716318264, 16.064177579207, 86.7807322029461, 296.564248779674, 637.333633378831, 793.826512519948, 440.413735824752)


def hash_uniform(*parts: Column | str) -> Column:
    """A uniform number in [0, 1) from the md5 of the parts joined by ``|``; strings are literal salts."""
    key = F.concat_ws("|", *(F.lit(p) if isinstance(p, str) else p.cast("string") for p in parts))
    return F.conv(F.substring(F.md5(key.cast("binary")), 1, 13), 16, 10).cast("bigint") / F.lit(HEX_RANGE)


def hash_uniform_sql(*parts: str) -> str:
    """The same in DuckDB; ``parts`` are SQL expressions."""
    return f"(('0x' || substr(md5(concat_ws('|', {', '.join(parts)})), 1, 13))::BIGINT / {HEX_RANGE})"


def sigmoid(z: Column) -> Column:
    """1 / (1 + exp(-z)) without overflow."""
    e = F.exp(-F.abs(z))
    return F.when(z >= 0, 1 / (1 + e)).otherwise(e / (1 + e))


def softplus(z: Column) -> Column:
    return F.greatest(z, F.lit(0.0)) + F.log1p(F.exp(-F.abs(z)))


def norm_pdf(x: Column, mean: Column | float = 0.0, sd: Column | float = 1.0) -> Column:
    u = (x - mean) / sd
    return F.exp(-0.5 * u * u) / (F.lit(math.sqrt(2 * math.pi)) * sd)


def horner(x, coefficients):
    """A polynomial by its coefficients, highest power first, of columns or arrays."""
    out = coefficients[0]
    for c in coefficients[1:]:
        out = out * x + c
    return out


def norm_cdf(x: Column) -> Column:
    """The normal distribution function, to about 1e-14."""
    a = F.least(F.abs(x), F.lit(37.0))
    e = F.exp(-a * a / 2)
    body = e * horner(a, CDF_TOP) / horner(a, CDF_BOTTOM)
    tail = e / (a + 1 / (a + 2 / (a + 3 / (a + 4 / (a + 0.65))))) / math.sqrt(2 * math.pi)
    upper = F.when(a < 7.07106781186547, body).otherwise(tail)
    return F.when(x > 0, 1 - upper).otherwise(upper)


def norm_ppf(u: Column) -> Column:
    """The normal quantile of a column in (0, 1)."""
    q = u - 0.5
    r = 0.180625 - q * q
    central = q * horner(r, PPF_CENTRAL[0][::-1]) / horner(r, PPF_CENTRAL[1][::-1])
    t = F.sqrt(-F.log(F.when(q < 0, u).otherwise(1 - u)))
    middle = horner(t - 1.6, PPF_MIDDLE[0][::-1]) / horner(t - 1.6, PPF_MIDDLE[1][::-1])
    far = horner(t - 5, PPF_TAIL[0][::-1]) / horner(t - 5, PPF_TAIL[1][::-1])
    outer = F.when(t <= 5, middle).otherwise(far)
    return F.when(F.abs(q) <= 0.425, central).otherwise(F.when(q < 0, -outer).otherwise(outer))


def ratio_np(x: np.ndarray, pair, factor: np.ndarray | float = 1.0) -> np.ndarray:
    """A factor times the quotient of two polynomials given by lowest power first, worked in place."""
    top, bottom = np.full_like(x, pair[0][-1]), np.full_like(x, pair[1][-1])
    for out, coefficients in ((top, pair[0]), (bottom, pair[1])):
        for c in coefficients[-2::-1]:
            out *= x
            out += c
    top *= factor
    top /= bottom
    return top


def norm_ppf_np(u: np.ndarray) -> np.ndarray:
    u = np.asarray(u, float)
    q = u - 0.5
    out = ratio_np(0.180625 - q * q, PPF_CENTRAL, q)
    far = np.flatnonzero(np.abs(q) > 0.425)
    if len(far):
        v = u.ravel()[far]
        t = np.sqrt(-np.log(np.minimum(v, 1 - v)))
        tail = ratio_np(t - 1.6, PPF_MIDDLE)
        if t.max() > 5:
            tail = np.where(t <= 5, tail, ratio_np(t - 5, PPF_TAIL))
        out.put(far, np.copysign(tail, q.ravel()[far]))
    return out


def norm_cdf_np(x: np.ndarray) -> np.ndarray:
    a = np.minimum(np.abs(x), 37.0)
    e = np.exp(-a * a / 2)
    body = e * horner(a, CDF_TOP) / horner(a, CDF_BOTTOM)
    tail = e / (a + 1 / (a + 2 / (a + 3 / (a + 4 / (a + 0.65))))) / math.sqrt(2 * math.pi)
    upper = np.where(a < 7.07106781186547, body, tail)
    return np.where(np.asarray(x) > 0, 1 - upper, upper)


def sigmoid_np(z: np.ndarray) -> np.ndarray:
    e = np.exp(-np.abs(z))
    return np.where(z >= 0, 1, e) / (1 + e)


def softplus_np(z: np.ndarray) -> np.ndarray:
    return np.maximum(z, 0) + np.log1p(np.exp(-np.abs(z)))


def dot(x: Column, theta: list[float]) -> Column:
    """Inner product of an array column with literal weights."""
    return F.aggregate(F.zip_with(x, F.array(*(F.lit(float(t)) for t in theta)), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)


def axpy(a: float, x: Column, y: Column) -> Column:
    return F.zip_with(x, y, lambda u, v: F.lit(float(a)) * u + v)


def outer(x: Column, y: Column) -> Column:
    """Row-major outer product of two array columns."""
    return F.flatten(F.transform(x, lambda u: F.transform(y, lambda v: u * v)))


def named_coefficients(names: list[str], values: Column) -> Column:
    return F.map_from_arrays(F.array(*(F.lit(n) for n in names)), values)


def register(spark: SparkSession) -> None:
    """Install the SQL functions and table functions; SQL bodies are inlined into the plan."""
    from gradvb.functions.tables import register_tables

    for statement in (
        "CREATE OR REPLACE TEMPORARY FUNCTION sigmoid(z DOUBLE) RETURNS DOUBLE RETURN CASE WHEN z >= 0 THEN 1 / (1 + exp(-z)) ELSE exp(z) / (1 + exp(z)) END",
        "CREATE OR REPLACE TEMPORARY FUNCTION softplus(z DOUBLE) RETURNS DOUBLE RETURN greatest(z, 0D) + log1p(exp(-abs(z)))",
        f"CREATE OR REPLACE TEMPORARY FUNCTION hash_uniform(salt STRING, k STRING) RETURNS DOUBLE RETURN cast(conv(substr(md5(concat_ws('|', salt, k)), 1, 13), 16, 10) AS BIGINT) / {HEX_RANGE}D",
        "CREATE OR REPLACE TEMPORARY FUNCTION norm_pdf(x DOUBLE) RETURNS DOUBLE RETURN exp(-x * x / 2) / sqrt(2 * pi())",
    ):
        spark.sql(statement)
    register_tables(spark)
