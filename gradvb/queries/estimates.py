"""Queries of designs, exact sums, samples and gradient estimates."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gradvb import designs
from gradvb.designs import FLIGHT_BETA, flights
from gradvb.estimators import anchor_sums, block_kernel, column_kernel, from_frame
from gradvb.functions.scalars import hash_uniform_sql as u
from gradvb.models import GaussianModel, Model, Poisson, Probit
from gradvb.queries.text import linear, logistic, long_form, rounded, softplus, w1, w1e, w3
from gradvb.sampling import assign_chunks, build_store, stratified, take
from gradvb.sums import Sums, chunk_rollup, chunk_sums, exact_sums

D = 4
ANCHOR = (-1.55, -0.2, 0.05, 0.8)
POINTS = np.array([(-1.6, -0.1, 0.0, 0.7), (-1.5, -0.25, 0.1, 0.9)])
M = 600


def rounded_col(c: Column, digits: int = 6) -> Column:
    return F.round(c, digits) + F.lit(0.0)


def value_rows(spark: SparkSession, values: dict[str, float]) -> DataFrame:
    return spark.createDataFrame([(k, round(float(v), 6) + 0.0) for k, v in values.items()], "k string, value double")


def entries(d: int = D) -> list[tuple[int, int]]:
    return [(j, k) for j in range(d) for k in range(j, d)]


def total(spark, sf_dir, theta, order, model: Model | None = None) -> Sums:
    return exact_sums(flights(spark, sf_dir), theta, model, order)


def exact_loglik(spark, sf_dir):
    s = total(spark, sf_dir, FLIGHT_BETA, 0)
    return spark.createDataFrame([(s.n, round(s.loglik / s.n, 6))], "n bigint, loglik_mean double")


def exact_gradient(spark, sf_dir):
    s = total(spark, sf_dir, FLIGHT_BETA, 1)
    return value_rows(spark, {f"g{j}": s.grad[j] / s.n for j in range(D)})


def exact_hessian(spark, sf_dir):
    s = total(spark, sf_dir, FLIGHT_BETA, 2)
    return value_rows(spark, {f"h{j}_{k}": s.hess[j, k] / s.n for j, k in entries()})


def anchor_query(spark, sf_dir):
    s = anchor_sums(flights(spark, sf_dir), ANCHOR)
    return value_rows(spark, {"loglik": s.loglik / s.n} | {f"a{j}": s.grad[j] / s.n for j in range(D)} | {f"c{j}_{k}": s.hess[j, k] / s.n for j, k in entries()})


def surrogate_at_theta(spark, sf_dir):
    s = anchor_sums(flights(spark, sf_dir), ANCHOR)
    g = s.grad + s.hess @ (POINTS[0] - s.theta)
    return value_rows(spark, {f"g{j}": g[j] / s.n for j in range(D)})


def sample_of(spark, sf_dir, seed: int = 7):
    return take(flights(spark, sf_dir), "hash_rank", 0, seed, m=M)


def hash_sample(spark, sf_dir):
    return sample_of(spark, sf_dir)[0].select("obs_key")


def bernoulli_hash_sample(spark, sf_dir):
    return take(flights(spark, sf_dir), "hash", 0.02, 8)[0].select("obs_key")


def stratified_sample(spark, sf_dir):
    return stratified(assign_chunks(flights(spark, sf_dir), 8), 0.01, 9).select("obs_key", "chunk_id", rounded_col(F.col("w")).alias("w"))


def tile_query(spark, sf_dir):
    """Rows, responses and hashed tile totals of two tiles of the store."""
    return build_store(flights(spark, sf_dir), 16).where(F.col("tile").isin(3, 11)).groupBy("tile").agg(F.count("*").alias("n"), F.sum("y").alias("ones"), F.max("row_idx").alias("last_row"))


def estimated(spark, sf_dir, surrogate: str, what: str):
    sample, weight = sample_of(spark, sf_dir)
    anchor = anchor_sums(flights(spark, sf_dir), ANCHOR)
    grad, ll, _, _ = from_frame(block_kernel(sample, POINTS, anchor, weight, surrogate=surrogate), POINTS, anchor, surrogate)
    if what == "loglik":
        return value_rows(spark, {f"s{s}": ll[s] / anchor.n for s in range(len(POINTS))})
    return value_rows(spark, {f"s{s}_g{j}": grad[s, j] / anchor.n for s in range(len(POINTS)) for j in range(D)})


def column_gradient(spark, sf_dir):
    """The remainder sums by the broadcast join and generated code."""
    sample, weight = sample_of(spark, sf_dir)
    anchor = anchor_sums(flights(spark, sf_dir), ANCHOR)
    got = column_kernel(sample, POINTS, anchor, weight)
    return got.select("draw_id", *(rounded_col(F.col(f"g{j}") / anchor.n).alias(f"g{j}") for j in range(D)))


def chunked_gradient(spark, sf_dir):
    """Each chunk's estimate from its own rows and weight, and their sum (chunk -1)."""
    obs = assign_chunks(flights(spark, sf_dir), 8)
    sums = stratified(obs, 0.05, 9).withColumn("wy", F.col("w"))
    z = Model.linear(FLIGHT_BETA)
    p = 1 / (1 + F.exp(-z))
    n = obs.count()
    return sums.rollup("chunk_id").agg(F.count("*").alias("m_k"), *(rounded_col(F.sum(F.col("wy") * (F.col("y") - p) * F.col(f"x{j}")) / n).alias(f"g{j}") for j in range(D))).withColumn("chunk_id", F.coalesce("chunk_id", F.lit(-1)))


def levels(got: DataFrame) -> DataFrame:
    """Means by chunk; -1 stands for all chunks together."""
    return got.select(F.coalesce("chunk_id", F.lit(-1)).alias("chunk_id"), "n", rounded_col(F.col("ll") / F.col("n")).alias("ll"), *(rounded_col(F.col(f"g{j}") / F.col("n")).alias(f"g{j}") for j in range(D)))


def chunk_sums_query(spark, sf_dir):
    got = chunk_sums(assign_chunks(flights(spark, sf_dir), 8), FLIGHT_BETA)
    return levels(got)


def chunk_rollup_query(spark, sf_dir):
    return levels(chunk_rollup(assign_chunks(flights(spark, sf_dir), 8), FLIGHT_BETA))


def sufficient_counts(spark, sf_dir):
    return designs.w1_design(spark, sf_dir).groupBy("rush", "weekend", F.round("distance", 4).alias("distance")).agg(F.count("*").alias("n"), F.sum("late_planted").alias("ones"))


def glm_gradient(model: Model):
    def run(spark, sf_dir):
        s = total(spark, sf_dir, (0.1, -0.2, 0.05, 0.3), 1, model)
        return value_rows(spark, {"loglik": s.loglik / s.n} | {f"g{j}": s.grad[j] / s.n for j in range(D)})

    return run


def draws_table(spark, sf_dir):
    """A hashed standard normal draw of five numbers for each customer, by Box and Muller's form."""
    from gradvb.functions.scalars import hash_uniform

    keys = spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").alias("draw_id"), F.explode(F.sequence(F.lit(0), F.lit(4))).alias("k"))
    key = F.concat_ws("|", "draw_id", "k")
    radius = F.sqrt(-2 * F.log(F.greatest(hash_uniform("e1", key), F.lit(2.0**-53))))
    return keys.select("draw_id", "k", rounded_col(radius * F.cos(2 * F.pi() * hash_uniform("e2", key))).alias("eps"))


def sums_sql(theta, d: int = D) -> dict[str, str]:
    p = logistic(linear(theta))
    return {"loglik": f"sum(y * ({linear(theta)}) - {softplus(linear(theta))})"} | {f"g{j}": f"sum((y - {p}) * x{j})" for j in range(d)} | {f"h{j}_{k}": f"sum(-{p} * (1 - {p}) * x{j} * x{k})" for j, k in entries(d)}


def one_row(theta, name: str = "s") -> str:
    return f"{name} AS (SELECT count(*) AS n, {', '.join(f'{v} AS {k}' for k, v in sums_sql(theta).items())} FROM obs)"


def chunk_of(chunks: int) -> str:
    return f"least(floor({u("'chunk'", 'obs_key')} * {chunks}), {chunks - 1})::INTEGER"


def remainder_sql(surrogate: str) -> str:
    """Sums of the remainders on the sample, with the anchor's sums, at the test points."""
    p0 = logistic(linear(ANCHOR))
    parts, out = [], {}
    for s, theta in enumerate(POINTS):
        p = logistic(linear(theta))
        move = linear(theta - np.array(ANCHOR))
        first = {"none": f"(y - {p})", "constant": f"({p0} - {p})", "linear": f"({p0} - {p} + {p0} * (1 - {p0}) * ({move}))"}[surrogate]
        for j in range(D):
            parts.append(f"sum({first} * x{j}) AS r{s}_{j}")
            base = {"none": "0", "constant": f"g{j}", "linear": f"g{j} + " + " + ".join(f"h{min(j, k)}_{max(j, k)} * ({float(theta[k] - ANCHOR[k])!r})" for k in range(D))}[surrogate]
            out[f"s{s}_g{j}"] = rounded(f"({base} + n / {M}.0 * r{s}_{j}) / n")
        second = f"{softplus(linear(ANCHOR))} - {softplus(linear(theta))} + {p0} * ({move}) + 0.5 * {p0} * (1 - {p0}) * ({move}) * ({move})"
        parts.append(f"sum({second}) AS l{s}")
    sample = f"sampled AS (SELECT * FROM obs ORDER BY {u("'s7'", 'obs_key')}, obs_key LIMIT {M})"
    return f"WITH {w1()}, {one_row(ANCHOR)}, {sample}, r AS (SELECT {', '.join(parts)} FROM sampled), both_rows AS (SELECT * FROM s, r) ", out


def estimate_sql(surrogate: str) -> str:
    head, out = remainder_sql(surrogate)
    return head + long_form(out, "both_rows")


def loglik_sql() -> str:
    head, _ = remainder_sql("linear")
    out = {}
    for s, theta in enumerate(POINTS):
        move = theta - np.array(ANCHOR)
        lin = " + ".join(f"g{j} * ({float(move[j])!r})" for j in range(D))
        quad = " + ".join(f"{1.0 if j == k else 2.0} * h{j}_{k} * ({float(move[j] * move[k])!r})" for j, k in entries())
        out[f"s{s}"] = rounded(f"(loglik + {lin} + 0.5 * ({quad}) + n / {M}.0 * l{s}) / n")
    return head + long_form(out, "both_rows")


def column_sql() -> str:
    head, _ = remainder_sql("linear")
    rows = [f"SELECT {s}::INTEGER AS draw_id, " + ", ".join(f"{rounded(f'n / {M}.0 * r{s}_{j} / n')} AS g{j}" for j in range(D)) + " FROM both_rows" for s in range(len(POINTS))]
    return head + " UNION ALL ".join(rows)


def strata(fraction: float) -> str:
    return f"""chunked AS (SELECT *, {chunk_of(8)} AS chunk_id FROM obs),
ranked AS (SELECT *, count(*) OVER (PARTITION BY chunk_id) AS n_k, row_number() OVER (PARTITION BY chunk_id ORDER BY {u("'s9'", 'obs_key')}, obs_key) AS rk FROM chunked),
picked AS (SELECT *, n_k / ceil(n_k * {fraction}) AS w FROM ranked WHERE rk <= ceil(n_k * {fraction}))"""


def chunk_level(group: str) -> str:
    s = sums_sql(FLIGHT_BETA)
    cols = ", ".join(f"{rounded(s[k] + ' / count(*)')} AS {name}" for k, name in [("loglik", "ll"), *((f"g{j}", f"g{j}") for j in range(D))])
    return f"WITH {w1()}, chunked AS (SELECT *, {chunk_of(8)} AS chunk_id FROM obs) SELECT coalesce(chunk_id, -1) AS chunk_id, count(*) AS n, {cols} FROM chunked GROUP BY {group}"


GLM_THETA = (0.1, -0.2, 0.05, 0.3)


def glm_sql(kind: str) -> str:
    z = linear(GLM_THETA)
    if kind == "probit":  # the distribution function by its series around zero
        t, series = f"((2 * y - 1) * ({z}))", "1.0"
        for k in range(41, 1, -2):
            series = f"(1.0 + (q * q / {k}) * {series})"
        inner = f"SELECT *, {t} AS q, exp(-0.5 * ({z}) * ({z})) / sqrt(2 * pi()) AS f FROM obs"
        source = f"SELECT *, 0.5 + f * q * {series} AS p FROM ({inner})"
        values = {"loglik": "sum(ln(p))"} | {f"g{j}": f"sum((2 * y - 1) * f / p * x{j})" for j in range(D)}
        return f"WITH {w1()}, s AS (SELECT count(*) AS n, {', '.join(f'{v} AS {k}' for k, v in values.items())} FROM ({source})) " + long_form({k: rounded(f"{k} / n") for k in values}, "s")
    if kind == "gaussian":
        ll, a = f"-0.5 * (y - ({z})) * (y - ({z})) - ln(sqrt(2 * pi()))", f"(y - ({z}))"
    else:
        ll, a = f"y * ({z}) - exp({z})", f"(y - exp({z}))"
    values = {"loglik": f"sum({ll})"} | {f"g{j}": f"sum({a} * x{j})" for j in range(D)}
    inner = ", ".join(f"{v} AS {k}" for k, v in values.items())
    return f"WITH {w1()}, s AS (SELECT count(*) AS n, {inner} FROM obs) " + long_form({k: rounded(f"{k} / n") for k in values}, "s")


QUERIES = {
    "w1_design": designs.w1_design,
    "w1e_design": designs.w1e_design,
    "w3_panels": designs.w3_panels,
    "w1_sufficient_counts": sufficient_counts,
    "quality_design": lambda s, d: designs.quality_design(s, d).withColumn("log_chars", F.round("log_chars", 9)),
    "conversation_panels": lambda s, d: designs.conversation_panels(s, d).withColumn("x2", F.round("x2", 9)),
    "events_panels": lambda s, d: designs.events_panels(s, d),
    "supplier_panels": lambda s, d: designs.supplier_panels(s, d).groupBy("panel_id").agg(F.count("*").alias("n"), F.sum("y").alias("ones"), rounded_col(F.sum("x1"), 4).alias("x1")),
    "benchmark_lengths": lambda s, d: designs.benchmark_lengths(s, d).withColumn("log_tokens", F.round("log_tokens", 9)),
    "page_lengths": lambda s, d: designs.page_lengths(s, d).withColumn("log_length", F.round("log_length", 9)),
    "exact_loglik": exact_loglik,
    "exact_gradient": exact_gradient,
    "exact_hessian": exact_hessian,
    "anchor_sums": anchor_query,
    "surrogate_at_theta": surrogate_at_theta,
    "hash_sample": hash_sample,
    "bernoulli_hash_sample": bernoulli_hash_sample,
    "stratified_sample": stratified_sample,
    "tile_sample": tile_query,
    "plain_gradient": lambda s, d: estimated(s, d, "none", "grad"),
    "constant_surrogate_gradient": lambda s, d: estimated(s, d, "constant", "grad"),
    "difference_gradient": lambda s, d: estimated(s, d, "linear", "grad"),
    "difference_loglik": lambda s, d: estimated(s, d, "linear", "loglik"),
    "column_kernel_remainders": column_gradient,
    "chunk_sums": chunk_sums_query,
    "chunk_rollup": chunk_rollup_query,
    "chunked_gradient": chunked_gradient,
    "glm_gaussian_gradient": glm_gradient(GaussianModel()),
    "glm_poisson_gradient": glm_gradient(Poisson()),
    "glm_probit_gradient": glm_gradient(Probit()),
    "draws_table": draws_table,
}

SQL = {
    "w1_design": f"WITH {w1()} SELECT obs_key, rush, weekend, distance, late_raw, late_planted FROM w1",
    "w1e_design": f"WITH {w1e()} SELECT * FROM w1e",
    "w3_panels": f"WITH {w3()} SELECT * FROM w3",
    "w1_sufficient_counts": f"WITH {w1()} SELECT rush, weekend, round(distance, 4) AS distance, count(*) AS n, sum(late_planted)::BIGINT AS ones FROM w1 GROUP BY 1, 2, 3",
    "quality_design": "SELECT doc_id, quality, toxic, round(ln(n_chars + 1.0), 9) AS log_chars, (lang = 'de')::INTEGER AS lang_de, (lang = 'es')::INTEGER AS lang_es, (lang = 'fr')::INTEGER AS lang_fr FROM labels JOIN documents USING (doc_id)",
    "conversation_panels": "SELECT conv_id AS panel_id, turn AS t, (role = 'user')::INTEGER AS y, turn / 10.0::DOUBLE AS x1, round(ln(length(coalesce(text, '')) + 1.0), 9) AS x2 FROM conversations",
    "events_panels": "SELECT user_id AS panel_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id)::INTEGER AS t, (event_type = 'purchase')::INTEGER AS y, (hour(ts) < 6 OR hour(ts) >= 22)::INTEGER::DOUBLE AS x1, (isodow(ts) IN (6, 7))::INTEGER::DOUBLE AS x2, value / 100 AS x3 FROM events",
    "supplier_panels": "SELECT l_suppkey AS panel_id, count(*) AS n, sum((l_returnflag = 'R')::INTEGER)::BIGINT AS ones, round(sum(l_quantity / 50), 4) + 0.0 AS x1 FROM lineitem GROUP BY 1",
    "benchmark_lengths": "SELECT item_id, tokens, round(ln(tokens + 1.0), 9) AS log_tokens FROM (SELECT item_id, len(list_filter(regexp_split_to_array(coalesce(text, ''), '[ \\t\\n\\r\\f]+'), lambda w: w <> ''))::BIGINT AS tokens FROM benchmark)",
    "page_lengths": "SELECT page_id, round(ln(length(html) + 1.0), 9) AS log_length, ((length(html) - length(replace(html, '<a ', ''))) / 3)::BIGINT AS links, split_part(url, '/', 4) AS lang FROM pages",
    "exact_loglik": f"WITH {w1()}, {one_row(FLIGHT_BETA)} SELECT n, round(loglik / n, 6) AS loglik_mean FROM s",
    "exact_gradient": f"WITH {w1()}, {one_row(FLIGHT_BETA)} " + long_form({f"g{j}": rounded(f"g{j} / n") for j in range(D)}, "s"),
    "exact_hessian": f"WITH {w1()}, {one_row(FLIGHT_BETA)} " + long_form({f"h{j}_{k}": rounded(f"h{j}_{k} / n") for j, k in entries()}, "s"),
    "anchor_sums": f"WITH {w1()}, {one_row(ANCHOR)} " + long_form({"loglik": rounded("loglik / n")} | {f"a{j}": rounded(f"g{j} / n") for j in range(D)} | {f"c{j}_{k}": rounded(f"h{j}_{k} / n") for j, k in entries()}, "s"),
    "surrogate_at_theta": f"WITH {w1()}, {one_row(ANCHOR)} " + long_form({f"g{j}": rounded("(g%d + %s) / n" % (j, " + ".join(f"h{min(j, k)}_{max(j, k)} * ({float(POINTS[0][k] - ANCHOR[k])!r})" for k in range(D)))) for j in range(D)}, "s"),
    "hash_sample": f"WITH {w1()} SELECT obs_key FROM obs ORDER BY {u("'s7'", 'obs_key')}, obs_key LIMIT {M}",
    "bernoulli_hash_sample": f"WITH {w1()} SELECT obs_key FROM obs WHERE {u("'s8'", 'obs_key')} < 0.02",
    "stratified_sample": f"WITH {w1()}, {strata(0.01)} SELECT obs_key, chunk_id, {rounded('w')} AS w FROM picked",
    "tile_sample": f"WITH {w1()}, tiled AS (SELECT *, least(floor({u("'tile'", 'obs_key')} * 16), 15)::INTEGER AS tile FROM obs) SELECT tile, count(*) AS n, sum(y) AS ones, count(*) - 1 AS last_row FROM tiled WHERE tile IN (3, 11) GROUP BY tile",
    "plain_gradient": estimate_sql("none"),
    "constant_surrogate_gradient": estimate_sql("constant"),
    "difference_gradient": estimate_sql("linear"),
    "difference_loglik": loglik_sql(),
    "column_kernel_remainders": column_sql(),
    "chunk_sums": chunk_level("chunk_id"),
    "chunk_rollup": chunk_level("ROLLUP (chunk_id)"),
    "chunked_gradient": f"WITH {w1()}, {strata(0.05)}, total AS (SELECT count(*) AS n_all FROM obs) SELECT coalesce(chunk_id, -1) AS chunk_id, count(*) AS m_k, {', '.join(f"{rounded(f'sum(w * (y - {logistic(linear(FLIGHT_BETA))}) * x{j}) / max(n_all)')} AS g{j}" for j in range(D))} FROM picked, total GROUP BY ROLLUP (chunk_id)",
    "glm_gaussian_gradient": glm_sql("gaussian"),
    "glm_probit_gradient": glm_sql("probit"),
    "glm_poisson_gradient": glm_sql("poisson"),
    "draws_table": f"SELECT d AS draw_id, k::INTEGER AS k, {rounded(f'sqrt(-2 * ln(greatest({u("'e1'", 'd', 'k')}, {2.0**-53!r}))) * cos(2 * pi() * {u("'e2'", 'd', 'k')})')} AS eps FROM (SELECT c_custkey AS d FROM customer) a, range(5) b(k)",
}
