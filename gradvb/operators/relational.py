"""Relational operators as thin, typed wrappers over the DataFrame API; each keeps its work inside Catalyst."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

# projections, filters


def where(df: DataFrame, condition: Column | str) -> DataFrame:
    return df.filter(condition)


def drop_incomplete(df: DataFrame, cols: list[str]) -> DataFrame:
    return df.dropna(subset=cols)


def rescale(df: DataFrame, col: str, by: float) -> DataFrame:
    return df.withColumn(col, F.col(col) / by)


def pack(df: DataFrame, cols: list[str], name: str = "x") -> DataFrame:
    return df.withColumn(name, F.array(*cols))


def unpack(df: DataFrame, name: str, size: int, prefix: str = "x") -> DataFrame:
    return df.select("*", *(F.get(name, F.lit(k)).alias(f"{prefix}{k}") for k in range(size)))


def fill(df: DataFrame, defaults: dict) -> DataFrame:
    return df.fillna(defaults)


def cast_schema(df: DataFrame, types: dict[str, str]) -> DataFrame:
    """Casts that give null where a value has no such form."""
    return df.select(*(F.col(c).try_cast(types[c]).alias(c) if c in types else F.col(c) for c in df.columns))


# joins


def hinted_join(a: DataFrame, b: DataFrame, on, how: str = "inner", hint: str | None = None) -> DataFrame:
    """``merge``, ``shuffle_hash`` or no hint (adaptive execution decides)."""
    return a.join(b.hint(hint) if hint else b, on, how)


def sort_merge_join(a: DataFrame, b: DataFrame, on) -> DataFrame:
    return hinted_join(a, b, on, hint="merge")


def shuffle_hash_join(a: DataFrame, b: DataFrame, on) -> DataFrame:
    return hinted_join(a, b, on, hint="shuffle_hash")


def broadcast_join(a: DataFrame, b: DataFrame, on, how: str = "inner", most_rows: int = 1_000_000) -> DataFrame:
    """Broadcast ``b`` only if it has at most ``most_rows`` rows; else let the planner shuffle."""
    small = b.limit(most_rows + 1).count() <= most_rows
    return a.join(F.broadcast(b) if small else b, on, how)


def cross_draws(sample: DataFrame, draws: DataFrame, most_rows: int = 4096) -> DataFrame:
    """Every row with each of a stated, small number of draws."""
    if draws.limit(most_rows + 1).count() > most_rows:
        raise ValueError(f"more than {most_rows} draws")
    return sample.crossJoin(F.broadcast(draws))


def range_join(points: DataFrame, spans: DataFrame, value: str, lo: str, hi: str, width: float) -> DataFrame:
    """Points with the spans [lo, hi) that hold them: bins of ``width`` meet by equality, then the bounds decide."""
    cut = spans.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    return points.withColumn("_bin", F.floor(F.col(value) / width)).join(cut, "_bin").where((F.col(value) >= F.col(lo)) & (F.col(value) < F.col(hi))).drop("_bin")


def interval_join(left: DataFrame, right: DataFrame, left_ts: str, right_ts: str, seconds: int) -> DataFrame:
    """Pairs whose right time lies within ``seconds`` after the left one; hourly or longer bins meet by equality."""
    bin_s = max(seconds, 3600)
    at = lambda c: F.unix_timestamp(F.col(c).cast("timestamp"))
    a = left.withColumn("_s", at(left_ts))
    a = a.withColumn("_bin", F.explode(F.array(F.floor(F.col("_s") / bin_s), F.floor(F.col("_s") / bin_s) + 1)))
    b = right.withColumn("_r", at(right_ts)).withColumn("_bin", F.floor(F.col("_r") / bin_s))
    return a.join(b, "_bin").where((F.col("_r") >= F.col("_s")) & (F.col("_r") <= F.col("_s") + seconds)).drop("_bin", "_s", "_r")


def asof_join(left: DataFrame, right: DataFrame, by: str, ts: str, value: str) -> DataFrame:
    """Each left row with the latest right value of its key at or before its time: a union and one window, no pairs."""
    both = left.select(by, ts, *(c for c in left.columns if c not in (by, ts)), F.lit(None).cast(right.schema[value].dataType).alias(value), F.lit(1).alias("_left"))
    other = right.select(by, ts, *(F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns if c not in (by, ts)), value, F.lit(0).alias("_left"))
    order = W.partitionBy(by).orderBy(ts, "_left").rowsBetween(W.unboundedPreceding, 0)
    return both.unionByName(other).withColumn(value, F.last(value, ignorenulls=True).over(order)).where("_left = 1").drop("_left")


def semi_join(a: DataFrame, b: DataFrame, on) -> DataFrame:
    return a.join(b, on, "left_semi")


def anti_join(a: DataFrame, b: DataFrame, on) -> DataFrame:
    return a.join(b, on, "left_anti")


def self_join(df: DataFrame, condition: Callable[[str, str], str], most_rows: int = 4096) -> DataFrame:
    """Pairs (a.*, b.*) of a stated, small table by a condition on both."""
    if df.limit(most_rows + 1).count() > most_rows:
        raise ValueError(f"more than {most_rows} rows")
    a, b = df.select(*(F.col(c).alias(f"a_{c}") for c in df.columns)), df.select(*(F.col(c).alias(f"b_{c}") for c in df.columns))
    return a.join(F.broadcast(b), F.expr(condition("a_", "b_")))


# aggregates


def sum_columns(df: DataFrame, exprs: dict[str, Column], by: list[str] | None = None) -> DataFrame:
    return df.groupBy(*(by or [])).agg(*(F.sum(e).alias(k) for k, e in exprs.items()))


def sorted_lists(df: DataFrame, by: str, order: str, cols: list[str], name: str = "rows") -> DataFrame:
    return df.groupBy(by).agg(F.sort_array(F.collect_list(F.struct(order, *cols))).alias(name))


def moments(df: DataFrame, col: str, by: list[str] | None = None) -> DataFrame:
    return df.groupBy(*(by or [])).agg(F.avg(col).alias("mean"), F.var_samp(col).alias("var"), F.stddev_samp(col).alias("sd"), F.skewness(col).alias("skew"), F.kurtosis(col).alias("kurt"))


def covariances(df: DataFrame, cols: list[str]) -> DataFrame:
    """(a, b, cov, corr) of all pairs by one aggregate."""
    pairs = [(a, b) for i, a in enumerate(cols) for b in cols[i:]]
    row = df.agg(*(F.covar_samp(a, b).alias(f"c{k}") for k, (a, b) in enumerate(pairs)), *(F.corr(a, b).alias(f"r{k}") for k, (a, b) in enumerate(pairs)))
    return row.select(F.explode(F.array(*(F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), F.col(f"c{k}").alias("cov"), F.col(f"r{k}").alias("corr")) for k, (a, b) in enumerate(pairs)))).alias("s")).select("s.*")


def credible_limits(df: DataFrame, col: str, probs: list[float], exact: bool = True, accuracy: int = 10_000) -> DataFrame:
    f = F.percentile(col, F.array(*map(F.lit, probs))) if exact else F.percentile_approx(col, probs, accuracy)
    return df.agg(f.alias("q")).select(F.posexplode("q").alias("k", "value")).select(F.get(F.array(*map(F.lit, probs)), F.col("k")).alias("prob"), "value")


def rollup_sums(df: DataFrame, dims: list[str], exprs: dict[str, Column]) -> DataFrame:
    return df.rollup(*dims).agg(*(F.sum(e).alias(k) for k, e in exprs.items()), F.grouping_id().alias("level"))


def cube_sums(df: DataFrame, dims: list[str], exprs: dict[str, Column]) -> DataFrame:
    return df.cube(*dims).agg(*(F.sum(e).alias(k) for k, e in exprs.items()), F.grouping_id().alias("level"))


def grouping_sets(df: DataFrame, sets: list[list[str]], dims: list[str], exprs: dict[str, Column]) -> DataFrame:
    return df.groupingSets([[F.col(c) for c in s] for s in sets], *dims).agg(*(F.sum(e).alias(k) for k, e in exprs.items()))


def pivot_arms(df: DataFrame, row: str, arm: str, value: str, arms: list[str]) -> DataFrame:
    return df.groupBy(row).pivot(arm, arms).agg(F.first(value))


def unpivot_arms(df: DataFrame, row: str, arms: list[str]) -> DataFrame:
    return df.unpivot([row], arms, "arm", "value")


def filtered_sum(value: Column, condition: Column) -> Column:
    return F.sum(F.when(condition, value))


def log_sum_exp(df: DataFrame, col: str, by: list[str]) -> DataFrame:
    """Stable log of summed exponentials: the maximum first, as a window-free two-step aggregate."""
    top = df.groupBy(*by).agg(F.max(col).alias("_top"))
    return df.join(top, by).groupBy(*by).agg((F.max("_top") + F.log(F.sum(F.exp(F.col(col) - F.col("_top"))))).alias("lse"))


def group_map(df: DataFrame, by: list[str], fn, schema: str) -> DataFrame:
    return df.groupBy(*by).applyInArrow(fn, schema)


def block_map(df: DataFrame, fn, schema: str) -> DataFrame:
    return df.mapInArrow(fn, schema)


def sketch_quantile(df: DataFrame, col: str, prob: float, by: list[str] | None = None) -> DataFrame:
    """Quantiles from mergeable sketches, for chains too long to sort."""
    sketch = df.groupBy(*(by or [])).agg(F.kll_sketch_agg_double(col).alias("s"))
    return sketch.select(*(by or []), F.kll_sketch_get_quantile_double("s", F.lit(prob)).alias("value"))


def sketch_counts(df: DataFrame, col: str, keys: list, error: float = 1e-4, confidence: float = 0.99, seed: int = 1) -> DataFrame:
    """(key, n): counts of chosen values from one count-min sketch of the column, whose size does not grow with the data.

    Counts are never too low, and with ``confidence`` too high by ``error`` times the rows at most.
    """
    spark = df.sparkSession
    made = df.agg(F.count_min_sketch(F.col(col), F.lit(error), F.lit(confidence), F.lit(seed)).alias("s")).first().s
    sketch = spark._jvm.org.apache.spark.util.sketch.CountMinSketch.readFrom(bytearray(made)) if made else None
    rows = [(k, int(sketch.estimateCount(k)) if sketch else 0) for k in keys]
    return spark.createDataFrame(rows, f"key {df.select(col).schema[0].dataType.simpleString()}, n long")


# windows


def panel_index(df: DataFrame, by: str, order: list[str], name: str = "t") -> DataFrame:
    return df.withColumn(name, F.row_number().over(W.partitionBy(by).orderBy(*order)))


def ranks(df: DataFrame, by: str, order: str) -> DataFrame:
    w = W.partitionBy(by).orderBy(order)
    return df.select("*", F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("dense_rank"), F.percent_rank().over(w).alias("percent_rank"), F.cume_dist().over(w).alias("cume_dist"))


def moving_average(df: DataFrame, by: str, order: str, col: str, k: int = 5) -> DataFrame:
    return df.withColumn("moving", F.avg(col).over(W.partitionBy(by).orderBy(order).rowsBetween(-(k - 1), 0)))


def change(df: DataFrame, by: str, order: str, col: str) -> DataFrame:
    w = W.partitionBy(by).orderBy(order)
    return df.select("*", (F.col(col) - F.lag(col).over(w)).alias("change"), F.lead(col).over(w).alias("ahead"))


def running_sum(df: DataFrame, by: str, order: list[str], col: str) -> DataFrame:
    return df.withColumn("running", F.sum(col).over(W.partitionBy(by).orderBy(*order).rowsBetween(W.unboundedPreceding, 0)))


def time_range_window(df: DataFrame, by: str, ts: str, col: str, seconds: int) -> DataFrame:
    w = W.partitionBy(by).orderBy(F.unix_timestamp(F.col(ts).cast("timestamp"))).rangeBetween(-seconds, 0)
    return df.withColumn("recent", F.sum(col).over(w))


def first_last(df: DataFrame, by: str, order: list[str], col: str) -> DataFrame:
    w = W.partitionBy(by).orderBy(*order).rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return df.select("*", F.first(col).over(w).alias("first"), F.last(col).over(w).alias("last"), F.nth_value(col, 2).over(w).alias("second"))


def running_moments(df: DataFrame, by: str, order: list[str], col: str) -> DataFrame:
    w = W.partitionBy(by).orderBy(*order).rowsBetween(W.unboundedPreceding, 0)
    return df.select("*", F.avg(col).over(w).alias("run_mean"), F.stddev_samp(col).over(w).alias("run_sd"))


# sorts, limits, sets


def global_sort(df: DataFrame, keys: list[str], nulls_last: bool = True) -> DataFrame:
    return df.orderBy(*(F.col(k).asc_nulls_last() if nulls_last else F.col(k).asc_nulls_first() for k in keys))


def top_k(df: DataFrame, keys: list[Column], k: int) -> DataFrame:
    return df.orderBy(*keys).limit(k)


def top_k_per_group(df: DataFrame, by: str, keys: list[Column], k: int) -> DataFrame:
    return df.withColumn("_r", F.row_number().over(W.partitionBy(by).orderBy(*keys))).where(F.col("_r") <= k).drop("_r")


def page(df: DataFrame, keys: list[str], offset: int, limit: int) -> DataFrame:
    return df.orderBy(*keys).offset(offset).limit(limit)


def union_by_name(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.unionByName(b, allowMissingColumns=True)
