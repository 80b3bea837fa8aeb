"""Design tables: the response and the covariates of each workload, from raw tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from gradvb.functions.scalars import hash_uniform, sigmoid
from gradvb.sources.tables import load_table

#: Coefficients of the planted responses.
FLIGHT_BETA = (-1.613, -0.155, 0.089, 0.764)
FULL_FLIGHT_BETA = (-1.608, -0.154, 0.084, 0.770)
PANEL_BETA = (-1.5, 1.5, 0.5, 0.25, 0.3, 0.8, 0.45, 0.85, 0.75, 0.67, 1.5)
PANEL_TAU2 = 1.5


def design(df: DataFrame, response: Column, covariates: dict[str, Column], keep: tuple[str, ...] = ()) -> DataFrame:
    """(keep, y, x0..): x0 is the intercept; rows with a null (or NaN) response or covariate are dropped.

    Each column has a condition of its own, so those that cannot fail are known beforehand and a hashed response is not worked twice.
    """
    columns = [F.lit(1.0).alias("x0"), *(c.cast("double").alias(f"x{k}") for k, c in enumerate(covariates.values(), 1))]
    rows = df.select(*keep, response.cast("double").alias("y"), *columns)
    for name in ("y", *(f"x{k}" for k in range(len(covariates) + 1))):
        rows = rows.where(F.col(name).isNotNull() & ~F.isnan(name))
    return rows


def indicator(condition: Column) -> Column:
    return F.when(condition, 1).otherwise(0)


def one_hot(name: str, levels: list[str]) -> dict[str, Column]:
    return {f"{name}_{v}": indicator(F.col(name) == v) for v in levels}


def planted(key: Column, beta, xs: list[Column]) -> Column:
    """A response drawn from the logistic model by a hash of the row's key."""
    z = F.lit(float(beta[0]))
    for b, x in zip(beta[1:], xs, strict=True):
        z = z + F.lit(float(b)) * x
    return indicator(hash_uniform(key) < sigmoid(z))


def w1_design(spark: SparkSession, sf_dir: str, beta=FLIGHT_BETA) -> DataFrame:
    """Line items with their orders: rush orders, weekend orders and quantity stand for night, weekend and distance."""
    items = load_table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_extendedprice", "l_quantity", "l_shipdate")
    orders = load_table(spark, sf_dir, "orders").select("o_orderkey", "o_orderdate", "o_orderpriority")
    cents = F.round(F.col("l_extendedprice") * 100).cast("bigint")
    key = F.concat_ws("|", F.lit("w1"), "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", cents)
    rows = items.join(orders, items["l_orderkey"] == orders["o_orderkey"])
    rows = rows.select(
        key.alias("obs_key"),
        indicator(F.col("o_orderpriority").isin("1-URGENT", "2-HIGH")).alias("rush"),
        indicator(F.dayofweek("o_orderdate").isin(1, 7)).alias("weekend"),
        (F.col("l_quantity") / 50).alias("distance"),
        indicator(F.datediff("l_shipdate", "o_orderdate") > 15).alias("late_raw"),
    )
    return rows.withColumn("late_planted", planted(F.col("obs_key"), beta, [F.col("rush"), F.col("weekend"), F.col("distance")]))


def w1e_design(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events at true clock times: night, weekend and value."""
    rows = load_table(spark, sf_dir, "events").select(
        "event_id",
        indicator((F.hour("ts") < 6) | (F.hour("ts") >= 22)).alias("night"),
        indicator(F.dayofweek("ts").isin(1, 7)).alias("weekend"),
        (F.col("value") / 100).alias("distance"),
        indicator(F.col("event_type") == "purchase").alias("purchase_raw"),
    )
    key = F.concat_ws("|", F.lit("w1e"), "event_id")
    return rows.withColumn("y_planted", planted(key, FLIGHT_BETA, [F.col("night"), F.col("weekend"), F.col("distance")]))


def ranks(keys: DataFrame, key: str, name: str, parts: int = 64) -> DataFrame:
    """Adds the rank (from 1) of distinct numbers ``key``: rows are numbered within ranges, and ranges shifted by the sizes of those before.

    Ends of ranges come from approximate quantiles and move the cost alone; the driver sees a number for each range.
    """
    ends = sorted(set(keys.approxQuantile(key, [k / parts for k in range(1, parts)], 0.25 / parts)))
    part = F.size(F.filter(F.array(*map(F.lit, ends)), lambda e: e < F.col(key))) if ends else F.lit(0)
    placed = keys.withColumn("part", part)
    sizes = {r["part"]: r["count"] for r in placed.groupBy("part").count().collect()}
    shifts = F.array(*(F.lit(sum(n for q, n in sizes.items() if q < p)) for p in range(len(ends) + 1)))
    within = F.row_number().over(W.partitionBy("part").orderBy(key))
    return placed.withColumn(name, (within + F.get(shifts, F.col("part"))).cast("int")).drop("part")


def w3_panels(spark: SparkSession, sf_dir: str, panels: int | None = None) -> DataFrame:
    """Customers with five orders or more: five rows each, ten hashed covariates and a hashed random intercept.

    ``panels`` keeps the first panels by customer; by default all are kept.
    """
    orders = load_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    by_customer = W.partitionBy("o_custkey")
    rows = orders.withColumn("t", F.row_number().over(by_customer.orderBy("o_orderdate", "o_orderkey"))).withColumn("n", F.count("*").over(by_customer)).where("n >= 5 and t <= 5")
    eligible = rows.where("t = 1").select("o_custkey")
    first = eligible if panels is None else eligible.orderBy("o_custkey").limit(panels)
    rows = rows.join(ranks(first, "o_custkey", "panel_rank"), "o_custkey")
    radius = F.sqrt(F.lit(PANEL_TAU2)) * F.sqrt(-2 * F.log(F.greatest(hash_uniform("a1", F.col("o_custkey")), F.lit(2.0**-53))))
    alpha = radius * F.cos(F.lit(2.0) * F.pi() * hash_uniform("a2", F.col("o_custkey")))
    xs = [hash_uniform(f"x{j}", F.col("o_orderkey")).alias(f"x{j}") for j in range(1, 11)]
    rows = rows.select(F.col("o_custkey").alias("panel_id"), "panel_rank", "t", "o_orderkey", alpha.alias("alpha"), *xs)
    z = F.lit(PANEL_BETA[0]) + F.col("alpha")
    for j in range(1, 11):
        z = z + F.lit(PANEL_BETA[j]) * F.col(f"x{j}")
    y = indicator(hash_uniform("w3", F.col("o_orderkey")) < sigmoid(z))
    return rows.select("panel_id", "panel_rank", "t", y.alias("y"), *(f"x{j}" for j in range(1, 11)))


def events_panels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Purchases by user: unbalanced panels."""
    return load_table(spark, sf_dir, "events").select(
        F.col("user_id").alias("panel_id"), F.row_number().over(W.partitionBy("user_id").orderBy("ts", "event_id")).alias("t"),
        indicator(F.col("event_type") == "purchase").alias("y"), indicator((F.hour("ts") < 6) | (F.hour("ts") >= 22)).cast("double").alias("x1"),
        indicator(F.dayofweek("ts").isin(1, 7)).cast("double").alias("x2"), (F.col("value") / 100).alias("x3"),
    )


def supplier_panels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line items by supplier: few large panels."""
    return load_table(spark, sf_dir, "lineitem").select(
        F.col("l_suppkey").alias("panel_id"), F.row_number().over(W.partitionBy("l_suppkey").orderBy("l_orderkey", "l_linenumber", "l_extendedprice")).alias("t"),
        indicator(F.col("l_returnflag") == "R").alias("y"), (F.col("l_quantity") / 50).alias("x1"), F.col("l_discount").alias("x2"),
    )


def conversation_panels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Turns by conversation: who speaks, against the turn and the length."""
    return load_table(spark, sf_dir, "conversations").select(
        F.col("conv_id").alias("panel_id"), F.col("turn").alias("t"), indicator(F.col("role") == "user").alias("y"),
        (F.col("turn") / 10.0).alias("x1"), F.log(F.length(F.coalesce("text", F.lit(""))) + 1.0).alias("x2"),
    )


def quality_design(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = load_table(spark, sf_dir, "documents"), load_table(spark, sf_dir, "labels")
    rows = labels.join(docs.select("doc_id", "lang", "n_chars"), "doc_id")
    return rows.select("doc_id", "quality", "toxic", F.log(F.col("n_chars") + 1.0).alias("log_chars"), *(c.alias(k) for k, c in one_hot("lang", ["de", "es", "fr"]).items()))


def embedding_design(spark: SparkSession, sf_dir: str, label: int = 0) -> DataFrame:
    """One class against the rest on 64 components and an intercept: 65 parameters."""
    rows = load_table(spark, sf_dir, "embeddings")
    return design(rows, indicator(F.col("label") == label), {f"e{k}": F.get("embedding", F.lit(k)) for k in range(64)}, keep=("vec_id",))


def page_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = load_table(spark, sf_dir, "pages")
    links = (F.length("html") - F.length(F.replace("html", F.lit("<a "), F.lit("")))) / 3
    return pages.select("page_id", F.log(F.length("html") + 1.0).alias("log_length"), links.cast("bigint").alias("links"), F.element_at(F.split("url", "/"), 4).alias("lang"))


def flights(spark: SparkSession, sf_dir: str, response: str = "late_planted", beta=FLIGHT_BETA) -> DataFrame:
    """The first workload as (obs_key, y, x0..x3)."""
    return design(w1_design(spark, sf_dir, beta), F.col(response), {c: F.col(c) for c in ("rush", "weekend", "distance")}, keep=("obs_key",))


def event_flights(spark: SparkSession, sf_dir: str, response: str = "y_planted") -> DataFrame:
    rows = w1e_design(spark, sf_dir).withColumn("obs_key", F.concat_ws("|", F.lit("w1e"), "event_id"))
    return design(rows, F.col(response), {c: F.col(c) for c in ("night", "weekend", "distance")}, keep=("obs_key",))


def scale_out(obs: DataFrame, times: int) -> DataFrame:
    """Every row ``times`` times under new keys, to stress a plan; ``times`` is a literal range, not data."""
    copies = F.explode(F.sequence(F.lit(0), F.lit(times - 1)))
    return obs.withColumn("copy", copies).withColumn("obs_key", F.concat_ws("|", "obs_key", "copy")).drop("copy")


def nest_panels(rows: DataFrame) -> DataFrame:
    """(panel_id, n_rows, y, x): responses and row-major covariates with the intercept first, sorted by t; built once by a shuffle."""
    xs = sorted((c for c in rows.columns if c[0] == "x" and c[1:].isdigit()), key=lambda c: int(c[1:]))
    row = F.struct("t", F.col("y").cast("double").alias("y"), F.array(F.lit(1.0), *(F.col(c).cast("double") for c in xs)).alias("x"))
    nested = rows.groupBy("panel_id").agg(F.sort_array(F.collect_list(row)).alias("rows"))
    return nested.select("panel_id", F.size("rows").alias("n_rows"), F.col("rows.y").alias("y"), F.flatten("rows.x").alias("x"))


def benchmark_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Token counts of the benchmark's items, split at white space, and their logs; null texts have none."""
    words = F.filter(F.split(F.coalesce("text", F.lit("")), r"[ \t\n\r\f]+"), lambda w: w != "")
    items = load_table(spark, sf_dir, "benchmark").select("item_id", F.size(words).cast("long").alias("tokens"))
    return items.select("item_id", "tokens", F.log(F.col("tokens") + 1.0).alias("log_tokens"))
