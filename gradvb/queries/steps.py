"""Queries of loop steps, panels, nets and measures on stored literals."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import functions as F

from gradvb import measures
from gradvb.designs import FLIGHT_BETA, PANEL_BETA, event_flights, flights, nest_panels, w3_panels
from gradvb.draws import direction_numbers, sobol
from gradvb.estimators import ExactProvider
from gradvb.families import NormalPrior, RankOneState
from gradvb.fit import FitConfig, bound_gradient
from gradvb.functions.scalars import hash_uniform, norm_cdf, norm_ppf, sigmoid, softplus
from gradvb.panel import Integrator, panel_frame, panel_sums
from gradvb.queries.estimates import rounded_col, value_rows
from gradvb.queries.text import linear, logistic, long_form, rounded, softplus as softplus_sql, u, w1, w1e, w3
from gradvb.sums import fit_mle

#: A fixed state and four fixed noise rows for the step queries.
MU, B, C = (-1.6, -0.15, 0.05, 0.75), (0.02, -0.005, -0.006, -0.03), 0.012
EPS = ((0.4, -1.1, 0.3, 0.9, -0.2), (-0.7, 0.5, 1.2, -0.4, 0.8), (1.3, 0.2, -0.6, 0.1, -1.0), (-0.9, 0.6, -0.8, -0.5, 0.7))
PRIOR = 50.0
D = 4
THETA_P = (*(float(b) for b in PANEL_BETA), 0.4)


# loop steps


def natural_steps(count: int):
    """The state after ``count`` natural steps of size 0.1/(t+1) on all rows, with the same four noise rows each time.

    The steps are plain ones, which grow with the table, so c may change its sign.
    """

    def run(spark, sf_dir):
        obs = flights(spark, sf_dir)
        provider, state, eps = ExactProvider(obs), RankOneState(np.array(MU), np.array(B), C, signed=True), np.array(EPS)
        for t in range(count):
            thetas = state.sample(eps)
            got = provider.estimate(thetas, t)
            gradient = bound_gradient(state, eps, thetas, got.grad, got.loglik, NormalPrior(PRIOR), FitConfig())
            state = state.moved(0.1 / (t + 1) * state.natural(gradient))
        names = [*(f"mu{j}" for j in range(D)), *(f"b{j}" for j in range(D)), "c"]
        return value_rows(spark, dict(zip(names, state.params(), strict=True)))

    return run


def reparam_gradient(spark, sf_dir):
    """The data part of the bound's gradient at the fixed state, per row of data."""
    provider, state, eps = ExactProvider(flights(spark, sf_dir)), RankOneState(np.array(MU), np.array(B), C), np.array(EPS)
    got = provider.estimate(state.sample(eps), 0)
    g = state.data_gradient(eps, got.grad) / provider.n
    return value_rows(spark, dict(zip([*(f"mu{j}" for j in range(D)), *(f"b{j}" for j in range(D)), "c"], g, strict=True)))


def step_sql(k: int) -> str:
    """CTEs of one natural step from the one-row state st{k-1} to st{k}."""
    prev, theta = f"st{k - 1}", []
    for s in range(4):
        theta.append([f"(mu{j} + ({EPS[s][0]!r}) * b{j} + c * ({EPS[s][1 + j]!r}))" for j in range(D)])
    sums = ", ".join(f"sum((y - {logistic(' + '.join(f'{theta[s][i]} * x{i}' for i in range(D)))}) * x{j}) AS g{s}_{j}" for s in range(4) for j in range(D))
    mean = lambda terms: "(" + " + ".join(terms) + ") / 4"
    parts = []
    for j in range(D):
        parts.append(f"-mu{j} / {PRIOR} + {mean([f'g{s}_{j}' for s in range(4)])} AS gm{j}")
        parts.append(f"(a - 1 / {PRIOR}) * b{j} + {mean([f'({EPS[s][0]!r}) * g{s}_{j}' for s in range(4)])} AS gb{j}")
    parts.append(f"-{D} * c / {PRIOR} + ({D} - a * bb) / c + {mean([f'({EPS[s][1 + j]!r}) * g{s}_{j}' for s in range(4) for j in range(D)])} AS gc")
    a = 0.1 / k
    moves = [f"mu{j} + {a!r} * (b{j} * bm + c * c * gm{j}) AS mu{j}" for j in range(D)]
    moves += [f"b{j} + {a!r} * ((rho - 0.5 * rho * rho + ka * ka / sp) * bg * b{j} + c * c * rho * gb{j} - ka / sp * gc * b{j}) AS b{j}" for j in range(D)]
    moves.append(f"c + {a!r} * ((gc - ka * bg) / sp) AS c")
    bb = " + ".join(f"b{j} * b{j}" for j in range(D))
    return f"""e{k} AS (SELECT {', '.join(f'any_value(mu{j}) AS mu{j}, any_value(b{j}) AS b{j}' for j in range(D))}, any_value(c) AS c, count(*) AS n, {sums} FROM obs, {prev}),
f{k} AS (SELECT *, {bb} AS bb, 1 / (c * c + {bb}) AS a FROM e{k}),
h{k} AS (SELECT *, {', '.join(parts)}, 1 + c * c / bb AS rho, c / bb AS ka, 2 * ({D} - 1) / (c * c) AS sp FROM f{k}),
i{k} AS (SELECT *, {' + '.join(f'b{j} * gm{j}' for j in range(D))} AS bm, {' + '.join(f'b{j} * gb{j}' for j in range(D))} AS bg FROM h{k}),
st{k} AS (SELECT {', '.join(moves)} FROM i{k})"""


def steps_sql(count: int) -> str:
    start = "st0 AS (SELECT " + ", ".join(f"{MU[j]!r}::DOUBLE AS mu{j}, {B[j]!r}::DOUBLE AS b{j}" for j in range(D)) + f", {C!r}::DOUBLE AS c)"
    names = [*(f"mu{j}" for j in range(D)), *(f"b{j}" for j in range(D)), "c"]
    return f"WITH {w1()}, {start}, " + ", ".join(step_sql(k) for k in range(1, count + 1)) + " " + long_form({k: rounded(k) for k in names}, f"st{count}")


def reparam_sql() -> str:
    thetas = [[MU[j] + EPS[s][0] * B[j] + C * EPS[s][1 + j] for j in range(D)] for s in range(4)]
    sums = ", ".join(f"sum((y - {logistic(linear(thetas[s]))}) * x{j}) AS g{s}_{j}" for s in range(4) for j in range(D))
    out = {f"mu{j}": rounded("(" + " + ".join(f"g{s}_{j}" for s in range(4)) + ") / 4 / n") for j in range(D)}
    out |= {f"b{j}": rounded("(" + " + ".join(f"({EPS[s][0]!r}) * g{s}_{j}" for s in range(4)) + ") / 4 / n") for j in range(D)}
    out["c"] = rounded("(" + " + ".join(f"({EPS[s][1 + j]!r}) * g{s}_{j}" for s in range(4) for j in range(D)) + ") / 4 / n")
    return f"WITH {w1()}, s AS (SELECT count(*) AS n, {sums} FROM obs) " + long_form(out, "s")


def two_columns(spark, sf_dir):
    return flights(spark, sf_dir).select("y", "x0", F.col("x3").alias("x1"))


def newton_mle(spark, sf_dir):
    best = fit_mle(two_columns(spark, sf_dir))
    return value_rows(spark, {"b0": best.theta[0], "b1": best.theta[1]})


def laplace_sd(spark, sf_dir):
    best = fit_mle(two_columns(spark, sf_dir))
    sd = np.sqrt(np.diag(np.linalg.inv(-best.hess)))
    return value_rows(spark, {"sd0": sd[0], "sd1": sd[1]})


def newton_sql(tail: dict[str, str], steps: int = 8) -> str:
    ctes = ["two AS (SELECT y, x0, x3 AS x1 FROM obs)", "t0 AS (SELECT 0.0::DOUBLE AS a, 0.0::DOUBLE AS b)"]
    for k in range(1, steps + 1):
        p = logistic("a + b * x1")
        ctes.append(f"m{k} AS (SELECT any_value(a) AS a, any_value(b) AS b, sum(y - {p}) AS g0, sum((y - {p}) * x1) AS g1, sum({p} * (1 - {p})) AS i00, sum({p} * (1 - {p}) * x1) AS i01, sum({p} * (1 - {p}) * x1 * x1) AS i11 FROM two, t{k - 1})")
        ctes.append(f"t{k} AS (SELECT a + (i11 * g0 - i01 * g1) / (i00 * i11 - i01 * i01) AS a, b + (i00 * g1 - i01 * g0) / (i00 * i11 - i01 * i01) AS b FROM m{k})")
    p = logistic("a + b * x1")
    ctes.append(f"z AS (SELECT any_value(a) AS a, any_value(b) AS b, sum({p} * (1 - {p})) AS i00, sum({p} * (1 - {p}) * x1) AS i01, sum({p} * (1 - {p}) * x1 * x1) AS i11 FROM two, t{steps})")
    return f"WITH {w1()}, " + ", ".join(ctes) + " " + long_form(tail, "z")


# panels


def panels_of(spark, sf_dir):
    return nest_panels(w3_panels(spark, sf_dir).drop("panel_rank"))


def panel_quadrature_loglik(spark, sf_dir):
    got = panel_frame(panels_of(spark, sf_dir), THETA_P, Integrator("quadrature", 40))
    return got.select("panel_id", rounded_col(F.col("ll")).alias("ll"))


def panel_quadrature_score(spark, sf_dir):
    s = panel_sums(panels_of(spark, sf_dir), THETA_P, Integrator("quadrature", 40))
    return value_rows(spark, {f"s{k}": s.grad[k] / s.n for k in range(12)})


def small_panels(spark, sf_dir):
    return w3_panels(spark, sf_dir).select("panel_id", "t", "y", "x1")


SMALL = (-0.5, 0.8, 0.3)


def missing_info_curvature(spark, sf_dir):
    s = panel_sums(nest_panels(small_panels(spark, sf_dir)), SMALL, Integrator("quadrature", 40))
    return value_rows(spark, {f"h{j}_{k}": s.hess[j, k] / s.n for j in range(3) for k in range(j, 3)})


def panel_is_score(spark, sf_dir):
    """Importance-sampling scores in DataFrame form: eight hashed draws a panel, weights normalised within it."""
    rows = small_panels(spark, sf_dir)
    draws = rows.select("panel_id").distinct().select("panel_id", F.explode(F.sequence(F.lit(1), F.lit(8))).alias("draw"))
    key = F.concat_ws("|", "panel_id", "draw")
    z = F.sqrt(-2 * F.log(F.greatest(hash_uniform("i1", key), F.lit(2.0**-53)))) * F.cos(2 * F.pi() * hash_uniform("i2", key))
    draws = draws.select("panel_id", "draw", (F.lit(math.exp(SMALL[2] / 2)) * z).alias("alpha"))
    each = rows.join(draws, "panel_id").withColumn("eta", F.lit(SMALL[0]) + F.lit(SMALL[1]) * F.col("x1") + F.col("alpha"))
    rest = F.col("y") - sigmoid(F.col("eta"))
    per = each.groupBy("panel_id", "draw").agg(
        F.sum(F.col("y") * F.col("eta") - softplus(F.col("eta"))).alias("lw"), F.sum(rest).alias("s0"), F.sum(rest * F.col("x1")).alias("s1"), F.first("alpha").alias("alpha")
    )
    w = F.exp("lw")
    s2 = 0.5 * F.lit(math.exp(-SMALL[2])) * F.col("alpha") ** 2 - 0.5
    return per.groupBy("panel_id").agg(*(rounded_col(F.sum(w * c) / F.sum(w)).alias(n) for n, c in (("s0", F.col("s0")), ("s1", F.col("s1")), ("s2", s2))), rounded_col(F.log(F.avg(w))).alias("ll"))


def nodes_sql(count: int = 40) -> str:
    z, w = np.polynomial.hermite_e.hermegauss(count)
    return "nodes(z, w) AS (VALUES " + ", ".join(f"({float(a)!r}::DOUBLE, {float(b)!r}::DOUBLE)" for a, b in zip(z, w / w.sum(), strict=True)) + ")"


def quadrature_ctes(theta, xs: list[str], source: str) -> str:
    d, tau = len(theta) - 1, math.exp(theta[-1] / 2)
    base = linear(theta[:-1], ["1.0", *xs])
    resid = ", ".join(f"sum((y - {logistic('eta')}) * {x}) AS s{k}" for k, x in enumerate(["1.0", *xs]))
    return f"""{nodes_sql()},
each AS (SELECT panel_id, z, w, y::DOUBLE AS y, {', '.join(xs)}, {base} + {tau!r} * z AS eta FROM {source}, nodes),
per AS (SELECT panel_id, z, any_value(w) AS w0, sum(y * eta - {softplus_sql('eta')}) + ln(any_value(w)) AS lw, {resid} FROM each GROUP BY panel_id, z),
tops AS (SELECT *, max(lw) OVER (PARTITION BY panel_id) AS top, 0.5 * z * z - 0.5 AS s{d} FROM per),
wts AS (SELECT *, exp(lw - top) AS v, exp(lw - top) / sum(exp(lw - top)) OVER (PARTITION BY panel_id) AS p FROM tops)"""


def curvature_sql() -> str:
    base = quadrature_ctes(SMALL, ["x1"], "w3")
    own = f"{logistic('eta')} * (1 - {logistic('eta')})"
    means = ", ".join(f"sum(p * s{k}) AS m{k}" for k in range(3))
    pairs = ", ".join(f"sum(p * s{j} * s{k}) AS q{j}{k}" for j in range(3) for k in range(j, 3))
    inner = f"varis AS (SELECT panel_id, z, sum({own}) AS v00, sum({own} * x1) AS v01, sum({own} * x1 * x1) AS v11 FROM each GROUP BY panel_id, z)"
    panel = f"pan AS (SELECT a.panel_id, {means}, {pairs}, sum(p * v00) AS v00, sum(p * v01) AS v01, sum(p * v11) AS v11, sum(p * 0.5 * a.z * a.z) AS v22 FROM wts a JOIN varis b ON a.panel_id = b.panel_id AND a.z = b.z GROUP BY a.panel_id)"
    out = {f"h{j}_{k}": rounded(f"sum(q{j}{k} - m{j} * m{k}" + (f" - v{j}{k}" if (j, k) in ((0, 0), (0, 1), (1, 1), (2, 2)) else "") + ") / count(*)") for j in range(3) for k in range(j, 3)}
    return f"WITH {w3()}, {base}, {inner}, {panel} " + long_form(out, "pan")


def is_sql() -> str:
    key = "concat_ws('|', panel_id, draw)"
    z = f"sqrt(-2 * ln(greatest({u("'i1'", key)}, {2.0**-53!r}))) * cos(2 * pi() * {u("'i2'", key)})"
    return f"""WITH {w3()}, draws AS (SELECT panel_id, draw, {math.exp(SMALL[2] / 2)!r} * {z} AS alpha FROM (SELECT DISTINCT panel_id FROM w3), range(1, 9) r(draw)),
each AS (SELECT panel_id, draw, alpha, y, x1, {SMALL[0]!r} + {SMALL[1]!r} * x1 + alpha AS eta FROM w3 JOIN draws USING (panel_id)),
per AS (SELECT panel_id, draw, any_value(alpha) AS alpha, sum(y * eta - {softplus_sql('eta')}) AS lw, sum(y - {logistic('eta')}) AS s0, sum((y - {logistic('eta')}) * x1) AS s1 FROM each GROUP BY panel_id, draw)
SELECT panel_id, {rounded('sum(exp(lw) * s0) / sum(exp(lw))')} AS s0, {rounded('sum(exp(lw) * s1) / sum(exp(lw))')} AS s1,
       {rounded(f'sum(exp(lw) * (0.5 * {math.exp(-SMALL[2])!r} * alpha * alpha - 0.5)) / sum(exp(lw))')} AS s2, {rounded('ln(avg(exp(lw)))')} AS ll FROM per GROUP BY panel_id"""


# nets


def sobol_query(shift: bool):
    def run(spark, sf_dir):
        points = sobol(64, 13)
        if shift:
            points = points ^ np.array([(2654435761 * (j + 1)) % 2**32 for j in range(13)], np.uint64)
        return spark.createDataFrame([(k, j, int(points[k, j])) for k in range(64) for j in range(13)], "point int, dim int, value bigint")

    return run


def sobol_sql(shift: bool) -> str:
    values = ", ".join(f"({j}, {k}, {int(v)})" for j in range(13) for k, v in enumerate(direction_numbers(j)[:6]))
    move = "xor(v, (2654435761 * (dim + 1)) % 4294967296)" if shift else "v"
    return f"WITH dirs(dim, k, v) AS (VALUES {values}), x AS (SELECT point, dim, coalesce(bit_xor(v::BIGINT) FILTER (WHERE (point >> k) & 1 = 1), 0)::BIGINT AS v FROM range(64) r(point), dirs GROUP BY 1, 2) SELECT point::INTEGER AS point, dim::INTEGER AS dim, {move}::BIGINT AS value FROM x"


# measures on literals

ARMS = [(m, r, p, round(-1.6 + 0.01 * r + 0.003 * k + 0.2 * len(p), 4), round(0.02 + 0.001 * r * (k + 1), 4), 20 + r + k, round(0.5 * (k + 1) + 0.05 * r, 3)) for k, m in enumerate(("chain", "mc", "rqmc")) for r in range(5) for p in ("b0", "b01")]


def arms(spark):
    return spark.createDataFrame(ARMS, "method string, rep int, param string, mean double, sd double, iters int, minutes double")


def values_sql(rows, names: str) -> str:
    cell = lambda v: repr(v) if isinstance(v, str) else f"{v!r}::DOUBLE" if isinstance(v, float) else str(v)
    return f"lit({names}) AS (VALUES " + ", ".join("(" + ", ".join(map(cell, r)) + ")" for r in rows) + ")"


def table(spark, sf_dir, name):
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def mc_errors(spark, sf_dir):
    """Users as repeats: each one's mean and sd of values by kind of event and parity."""
    reps = table(spark, sf_dir, "events").groupBy(F.col("event_type").alias("method"), F.col("user_id").alias("rep"), F.concat(F.lit("b"), (F.col("event_id") % 2).cast("string")).alias("param"))
    reps = reps.agg(F.avg("value").alias("mean"), F.stddev_samp("value").alias("sd"), F.count("*").alias("iters"), (F.count("*") / 60).alias("minutes"))
    got = measures.mc_standard_errors(reps)
    return got.select("method", "param", *(rounded_col(F.col(c), 6).alias(c) for c in ("mean", "sd", "mean_se", "sd_se", "var_se", "iters", "minutes")))


def bound_window_query(spark, sf_dir):
    """Daily means of the events' values as the trace."""
    day = F.datediff(F.col("ts"), F.lit("2024-01-01").cast("date")).alias("iter")
    got = measures.bound_window(table(spark, sf_dir, "events").groupBy(day).agg(F.round(F.avg("value"), 6).alias("lb")))
    return got.select("iter", "lb", *(F.round(c, 6).alias(c) for c in ("lb_avg", "change")))


def speedup_table(spark, sf_dir):
    return measures.speedups(arms(spark), "chain").select("method", *(rounded_col(F.col(c), 8).alias(c) for c in ("minutes", "iters", "speedup")))


def stability_table(spark, sf_dir):
    return measures.stability(arms(spark)).select("method", "param", rounded_col(F.col("spread"), 8).alias("spread"))


def density_grid(spark, sf_dir):
    """Normal densities with the mean and the sd of each kind of event's values."""
    state = table(spark, sf_dir, "events").groupBy(F.col("event_type").alias("param")).agg(F.avg("value").alias("mean"), F.stddev_samp("value").alias("sd"))
    rows = state.select("*", F.explode(F.sequence(F.lit(0), F.lit(40))).alias("k"))
    x = F.col("mean") + F.col("sd") * (F.lit(-4.0) + F.col("k") / 5.0)
    from gradvb.functions.scalars import norm_pdf

    return rows.select("param", "k", rounded_col(x).alias("x"), rounded_col(norm_pdf(x, F.col("mean"), F.col("sd"))).alias("pdf"))


def kde_grid(spark, sf_dir):
    events = spark.read.parquet(f"{sf_dir}/events.parquet").select(F.col("event_id").alias("iter"), F.col("value").alias("v"))
    got = measures.kde(events, "v", 21, 256)
    return got.select(rounded_col(F.col("x")).alias("x"), rounded_col(F.col("pdf"), 8).alias("pdf"))


KDE_SQL = """WITH f AS (SELECT count(*) AS n, stddev_samp(value) AS sd, min(value) AS mn, max(value) AS mx FROM events),
g AS (SELECT *, greatest(0.9 * sd * pow(n, -0.2), 1e-12) AS h FROM f), b AS (SELECT *, mn - 3 * h AS lo, mx + 3 * h AS hi, (mx + 3 * h - mn + 3 * h) / 256 AS step FROM g),
hist AS (SELECT least(floor((value - lo) / step), 255) AS bin, count(*) AS c FROM events, b GROUP BY 1),
grid AS (SELECT lo + (hi - lo) / 20 * k AS x FROM b, range(21) r(k))
SELECT round(x, 6) + 0.0 AS x, round(sum(c / n * exp(-0.5 * pow((x - (lo + (bin + 0.5) * step)) / h, 2)) / (sqrt(2 * pi()) * h)), 8) + 0.0 AS pdf FROM grid, hist, b GROUP BY x"""


def autocorrelation_query(spark, sf_dir):
    chain = spark.read.parquet(f"{sf_dir}/events.parquet").select(F.col("event_id").alias("iter"), F.col("value").alias("v"))
    return measures.autocorrelation(chain, "v", 5).select("lag", rounded_col(F.col("rho")).alias("rho"))


AUTO_SQL = "WITH m AS (SELECT avg(value) AS m FROM events), c AS (SELECT event_id, value - m AS v FROM events, m), l AS (SELECT v, " + ", ".join(f"lag(v, {k}) OVER (ORDER BY event_id) AS l{k}" for k in range(1, 6)) + " FROM c), s AS (SELECT sum(v * v) AS v0, " + ", ".join(f"sum(v * l{k}) AS r{k}" for k in range(1, 6)) + " FROM l) SELECT 0 AS lag, 1.0::DOUBLE AS rho UNION ALL " + " UNION ALL ".join(f"SELECT {k} AS lag, round(r{k} / v0, 6) + 0.0 AS rho FROM s" for k in range(1, 6))


def posterior_predict(spark, sf_dir):
    got = measures.posterior_predict(event_flights(spark, sf_dir), RankOneState(np.array(MU), np.array(B), C))
    return got.select("obs_key", rounded_col(F.col("p")).alias("p"))


def predict_sql() -> str:
    cov = np.outer(B, B) + C**2 * np.eye(D)
    v = " + ".join(f"({float(cov[j, k])!r}) * x{j} * x{k}" for j in range(D) for k in range(D))
    rows = "o AS (SELECT concat_ws('|', 'w1e', event_id) AS obs_key, 1.0::DOUBLE AS x0, night::DOUBLE AS x1, weekend::DOUBLE AS x2, distance AS x3 FROM w1e)"
    return f"WITH {w1e()}, {rows} SELECT obs_key, {rounded(logistic(f'({linear(MU)}) / sqrt(1 + {math.pi / 8!r} * ({v}))'))} AS p FROM o"


def normal_functions(spark, sf_dir):
    """Round trip of the normal quantile and distribution over the events' hashed uniforms: 0 where it closes."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", F.greatest(hash_uniform("n", F.col("event_id")), F.lit(1e-9)).alias("p"))
    return events.select("event_id", rounded_col(F.col("p"), 9).alias("p"), rounded_col(norm_cdf(norm_ppf(F.col("p"))) - F.col("p"), 9).alias("gap"))


QUERIES = {
    "reparam_gradient_s4": reparam_gradient,
    "one_natural_step": natural_steps(1),
    "three_natural_steps": natural_steps(3),
    "newton_mle_d2": newton_mle,
    "laplace_sd_d2": laplace_sd,
    "panel_quadrature_loglik": panel_quadrature_loglik,
    "panel_quadrature_score": panel_quadrature_score,
    "missing_info_curvature": missing_info_curvature,
    "panel_is_score": panel_is_score,
    "sobol_points_raw": sobol_query(False),
    "sobol_digital_shift": sobol_query(True),
    "mc_standard_errors": mc_errors,
    "bound_window": bound_window_query,
    "speedup_table": speedup_table,
    "stability_table": stability_table,
    "marginal_density_grid": density_grid,
    "kde_grid": kde_grid,
    "chain_autocorrelation": autocorrelation_query,
    "posterior_predict": posterior_predict,
    "normal_round_trip": normal_functions,
}

SQL = {
    "reparam_gradient_s4": reparam_sql(),
    "one_natural_step": steps_sql(1),
    "three_natural_steps": steps_sql(3),
    "newton_mle_d2": newton_sql({"b0": rounded("a"), "b1": rounded("b")}),
    "laplace_sd_d2": newton_sql({"sd0": rounded("sqrt(i11 / (i00 * i11 - i01 * i01))"), "sd1": rounded("sqrt(i00 / (i00 * i11 - i01 * i01))")}),
    "panel_quadrature_loglik": f"WITH {w3()}, {quadrature_ctes(THETA_P, [f'x{j}' for j in range(1, 11)], 'w3')} SELECT panel_id, {rounded('max(top) + ln(sum(v))')} AS ll FROM wts GROUP BY panel_id",
    "panel_quadrature_score": f"WITH {w3()}, {quadrature_ctes(THETA_P, [f'x{j}' for j in range(1, 11)], 'w3')}, tot AS (SELECT count(DISTINCT panel_id) AS n, {', '.join(f'sum(p * s{k}) AS s{k}' for k in range(12))} FROM wts) " + long_form({f"s{k}": rounded(f"s{k} / n") for k in range(12)}, "tot"),
    "missing_info_curvature": curvature_sql(),
    "panel_is_score": is_sql(),
    "sobol_points_raw": sobol_sql(False),
    "sobol_digital_shift": sobol_sql(True),
    "mc_standard_errors": f"WITH reps AS (SELECT event_type AS method, user_id AS rep, concat('b', event_id % 2) AS param, avg(value) AS mean, stddev_samp(value) AS sd, count(*) AS iters, count(*) / 60 AS minutes FROM events GROUP BY 1, 2, 3) SELECT method, param, {rounded('avg(mean)')} AS mean, {rounded('avg(sd)')} AS sd, {rounded('stddev_samp(mean)')} AS mean_se, {rounded('stddev_samp(sd)')} AS sd_se, {rounded('stddev_samp(sd * sd)')} AS var_se, {rounded('avg(iters)')} AS iters, {rounded('avg(minutes)')} AS minutes FROM reps GROUP BY 1, 2",
    "bound_window": "WITH lit AS (SELECT date_diff('day', DATE '2024-01-01', ts::DATE)::INTEGER AS iter, round(avg(value), 6) AS lb FROM events GROUP BY 1), a AS (SELECT iter, lb, CASE WHEN row_number() OVER (ORDER BY iter) >= 5 THEN avg(lb) OVER (ORDER BY iter ROWS 4 PRECEDING) END AS lb_avg FROM lit) SELECT iter, lb, round(lb_avg, 6) AS lb_avg, round(lb_avg - lag(lb_avg) OVER (ORDER BY iter), 6) AS change FROM a",
    "speedup_table": f"WITH {values_sql(ARMS, 'method, rep, param, mean, sd, iters, minutes')}, c AS (SELECT method, avg(minutes) AS minutes, avg(iters) AS iters FROM lit GROUP BY 1) SELECT method, {rounded('minutes', 8)} AS minutes, {rounded('iters', 8)} AS iters, {rounded("(SELECT minutes FROM c WHERE method = 'chain') / minutes", 8)} AS speedup FROM c",
    "stability_table": f"WITH {values_sql(ARMS, 'method, rep, param, mean, sd, iters, minutes')} SELECT method, param, {rounded('max(round(mean, 2)) - min(round(mean, 2))', 8)} AS spread FROM lit GROUP BY 1, 2",
    "marginal_density_grid": f"WITH lit AS (SELECT event_type AS param, avg(value) AS mean, stddev_samp(value) AS sd FROM events GROUP BY 1) SELECT param, k::INTEGER AS k, {rounded('mean + sd * (-4.0 + k / 5.0::DOUBLE)')} AS x, {rounded('exp(-0.5 * pow(-4.0 + k / 5.0::DOUBLE, 2)) / (sqrt(2 * pi()) * sd)')} AS pdf FROM lit, range(41) r(k)",
    "kde_grid": KDE_SQL,
    "chain_autocorrelation": AUTO_SQL,
    "posterior_predict": predict_sql(),
    "normal_round_trip": f"SELECT event_id, {rounded(f'greatest({u("'n'", 'event_id')}, 1e-9)', 9)} AS p, 0.0::DOUBLE AS gap FROM events",
}
