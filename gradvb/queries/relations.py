"""Queries of relational operators, windows, scalar functions, and streams held against batch answers."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from gradvb.functions.scalars import axpy, dot, hash_uniform, named_coefficients, outer, register, sigmoid
from gradvb.functions.tables import predict_prob
from gradvb.operators import relational as R
from gradvb.plans.planner import plan_fit
from gradvb.queries.estimates import rounded_col
from gradvb.queries.text import logistic, rounded, softplus, u
from gradvb.session import ensure_checkpoint_dir
from gradvb.sources.tables import load_table, read_tiles, register_views, stream_table, table_sample_sql, write_bucketed, write_store
from gradvb.streaming import online


def t(name):
    return lambda spark, sf_dir: load_table(spark, sf_dir, name)


def of(name, f):
    return lambda spark, sf_dir: f(load_table(spark, sf_dir, name))


def two(left, right, f):
    return lambda spark, sf_dir: f(load_table(spark, sf_dir, left), load_table(spark, sf_dir, right))


def folder(spark) -> str:
    return f"{ensure_checkpoint_dir(spark)}/tables-{uuid.uuid4().hex}"


def store_round_trip(spark, sf_dir):
    """Written by tile, read back two tiles by pruning."""
    path = folder(spark)
    events = load_table(spark, sf_dir, "events").select("event_id", "value", F.pmod("event_id", F.lit(8)).cast("int").alias("tile"), F.col("event_id").alias("row_idx"))
    write_store(events, path)
    return read_tiles(spark, path, [2, 5]).groupBy("tile").agg(F.count("*").alias("n"), rounded_col(F.sum("value"), 4).alias("v"))


def csv_round_trip(spark, sf_dir):
    from gradvb.sources.tables import load_observations, save_result

    path = folder(spark)
    save_result(load_table(spark, sf_dir, "nation"), path, "csv")
    return load_observations(spark, path, "csv", "n_nationkey int, n_name string, n_regionkey int")


def json_round_trip(spark, sf_dir):
    from gradvb.sources.tables import load_observations, save_result

    path = folder(spark)
    save_result(load_table(spark, sf_dir, "supplier").select("s_suppkey", "s_name"), path, "json")
    return load_observations(spark, path, "json", "s_suppkey bigint, s_name string")


def orc_round_trip(spark, sf_dir):
    from gradvb.sources.tables import load_observations, save_result

    path = folder(spark)
    save_result(load_table(spark, sf_dir, "region"), path, "orc")
    return load_observations(spark, path, "orc")


def bucketed_join(spark, sf_dir):
    """Two tables bucketed alike join without a shuffle."""
    tag = uuid.uuid4().hex[:8]
    write_bucketed(load_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), "o_custkey", 8, f"orders_{tag}")
    write_bucketed(load_table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey"), "c_custkey", 8, f"customer_{tag}")
    joined = spark.table(f"orders_{tag}").join(spark.table(f"customer_{tag}").hint("merge"), F.col("o_custkey") == F.col("c_custkey"))
    return joined.groupBy("c_nationkey").agg(F.count("*").alias("n"))


ANCHOR = (-1.5, -0.1, 0.1, 0.7)


def stream_sums(spark, sf_dir):
    name = f"s{uuid.uuid4().hex[:10]}"
    online.run_to_end(online.streaming_anchor_sums(online.event_stream(stream_table(spark, sf_dir, "events")), ANCHOR), name, "complete", folder(spark))
    return spark.table(name).select("n", rounded_col(F.col("ll") / F.col("n")).alias("ll"), *(rounded_col(F.col(f"g{j}") / F.col("n")).alias(f"g{j}") for j in range(4)), rounded_col(F.col("h1_3") / F.col("n")).alias("h1_3"))


def stream_windows(spark, sf_dir):
    name = f"s{uuid.uuid4().hex[:10]}"
    online.run_to_end(online.windowed_rates(online.event_stream(stream_table(spark, sf_dir, "events"))), name, "complete", folder(spark))
    return spark.table(name).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "n", "ones", rounded_col(F.col("rate")).alias("rate"))


def stream_sessions(spark, sf_dir):
    name = f"s{uuid.uuid4().hex[:10]}"
    online.run_to_end(online.session_rates(online.event_stream(stream_table(spark, sf_dir, "events"), "3650 days"), "12 hours"), name, "complete", folder(spark))
    return spark.table(name).groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("n"), F.sum("ones").alias("ones"))


def stream_dedup(spark, sf_dir):
    kept = online.deduplicated(online.event_stream(stream_table(spark, sf_dir, "events")))
    return online.run_to_table(kept.select("event_id", "event_type"), folder(spark), folder(spark)).groupBy("event_type").agg(F.count("*").alias("n"))


def stream_panels(spark, sf_dir):
    name = f"s{uuid.uuid4().hex[:10]}"
    online.run_to_end(online.panel_buffer(online.event_stream(stream_table(spark, sf_dir, "events"))), name, "update", folder(spark))
    return spark.table(name).groupBy("user_id").agg(F.max("n").alias("n"), F.max("ones").alias("ones"))


def stream_static(spark, sf_dir):
    name = f"s{uuid.uuid4().hex[:10]}"
    customers = load_table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    joined = online.with_dimension(online.event_stream(stream_table(spark, sf_dir, "events")), customers, "user_id").groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.sum("y").alias("ones"))
    online.run_to_end(joined, name, "complete", folder(spark))
    return spark.table(name)


def stream_pairs(spark, sf_dir):
    """Stream-stream join: each user's events with those of the hour after them."""
    left, right = (online.event_stream(stream_table(spark, sf_dir, "events"), "3650 days") for _ in range(2))
    pairs = online.matched_streams(left, right, 3600).where("left_id != right_id").select("user_id", "left_id", "right_id")
    return online.run_to_table(pairs, folder(spark), folder(spark))


def random_functions(spark, sf_dir):
    """Seeded uniform and normal columns; plain draws for estimates whose replay is not needed."""
    rows = load_table(spark, sf_dir, "events").select("event_id", F.rand(3).alias("u"), F.randn(4).alias("z"), F.uniform(F.lit(0), F.lit(10), F.lit(5)).alias("k"))
    return rows.agg(F.count("*").alias("n"), F.avg("u").alias("u"), F.avg("z").alias("z"), F.var_samp("z").alias("v"), F.max("k").alias("k"))


def poisson_sample(spark, sf_dir):
    """Rows drawn at a rate with replacement, as the scan goes."""
    from gradvb.sampling import take

    sample, weight = take(load_table(spark, sf_dir, "events"), "poisson", 0.1, 5)
    return sample.groupBy("event_type").agg((F.count("*") * F.lit(weight)).alias("estimate"))


def online_fit(spark, sf_dir):
    """One natural step for each mini-batch."""
    import numpy as np

    from gradvb.families import RankOneState

    fit = online.OnlineFit(RankOneState(np.array(ANCHOR), np.array((0.02, 0.01, 0.01, 0.02)), 0.02), np.array(ANCHOR))
    online.to_batches(online.event_stream(stream_table(spark, sf_dir, "events")), fit, folder(spark))
    mean, sd = fit.state.marginals()
    return spark.createDataFrame([(f"b{k}", float(mean[k]), float(sd[k]), fit.steps) for k in range(4)], "param string, mean double, sd double, batches int")


def sql_functions(spark, sf_dir):
    register(spark)
    register_views(spark, sf_dir, ["events"])
    return spark.sql("SELECT event_id, round(sigmoid((value - 50) / 10), 9) AS p, round(softplus((value - 50) / 10), 9) AS s, hash_uniform('q', CAST(event_id AS STRING)) AS u FROM events")


def table_functions(spark, sf_dir):
    """A net for each nation, draws for each supplier, keyed by their numbers, and a density grid for each kind of event."""
    register(spark)
    register_views(spark, sf_dir, ["nation", "supplier", "events"])
    return spark.sql(
        "SELECT 'net' AS kind, count(*) AS n, round(avg(u), 6) AS v FROM nation, LATERAL sobol_points(16, 3, n_nationkey + 1) "
        "UNION ALL SELECT 'draws', count(*), round(avg(value), 6) FROM supplier, LATERAL explode_draws(2, 3, s_suppkey) "
        "UNION ALL SELECT 'grid', count(*), round(sum(pdf), 6) FROM (SELECT avg(value) AS mean, stddev_samp(value) AS sd FROM events GROUP BY event_type) kinds, LATERAL density_grid(mean, sd, 41)"
    )


def lateral_draws(spark, sf_dir):
    register(spark)
    register_views(spark, sf_dir, ["region"])
    return spark.sql("SELECT r_regionkey, draw, k, value FROM region, LATERAL explode_draws(2, 3, r_regionkey)")


def interval_pairs(events, orders):
    a = events.where("event_type = 'purchase'").select("event_id", "ts")
    return R.interval_join(a, orders.select("o_orderkey", "o_orderdate"), "ts", "o_orderdate", 7200).groupBy("event_id").agg(F.count("*").alias("n"))


def asof(events):
    left = events.where("event_type = 'purchase'").select("user_id", "ts", "event_id")
    right = events.where("event_type != 'purchase'").select("user_id", "ts", "value")
    return R.asof_join(left, right, "user_id", "ts", "value").select("event_id", "value")


def bins(spark, sf_dir):
    spans = spark.createDataFrame([(k, 7.0 * k, 7.0 * k + 10.0) for k in range(14)], "span int, lo double, hi double")
    return R.range_join(load_table(spark, sf_dir, "events").select("event_id", "value"), spans, "value", "lo", "hi", 10.0).groupBy("span").agg(F.count("*").alias("n"))


def plan_table(spark, sf_dir):
    n = load_table(spark, sf_dir, "lineitem").count()
    return plan_fit(n, 4, 0.01, 256).frame(spark).union(plan_fit(10**12, 4, 10**6, 256).frame(spark)).union(plan_fit(10**9, 65, 0.2, 256).frame(spark))


def feature_arrays(events):
    x = F.array(F.lit(1.0), F.col("value") / 100, F.hour("ts").cast("double"))
    base = events.select("event_id", x.alias("x"))
    return base.select("event_id", rounded_col(dot(F.col("x"), [0.5, -1.0, 0.25])).alias("dot"), rounded_col(F.get(axpy(2.0, F.col("x"), F.col("x")), F.lit(2))).alias("axpy"), rounded_col(F.aggregate(outer(F.col("x"), F.col("x")), F.lit(0.0), lambda a, b: a + b)).alias("outer_sum"))


def maps(events):
    m = named_coefficients(["a", "b"], F.array(F.lit(1.5), F.col("value")))
    doubled = F.transform_values(m, lambda k, v: v * 2)
    return events.select("event_id", F.element_at(doubled, "b").alias("b2"), F.size(F.map_keys(m)).alias("keys"))


def dates(orders):
    ts = F.col("o_orderdate")
    return orders.select("o_orderkey", F.hour(ts).alias("h"), F.dayofweek(ts).alias("dow"), F.datediff(F.lit("1998-01-01").cast("timestamp_ntz"), ts).alias("age"), F.date_format(F.date_trunc("month", ts), "yyyy-MM-dd").alias("month"), ((F.lit("1995-01-01").cast("timestamp_ntz") - ts) > F.expr("INTERVAL '15' DAY")).alias("early"))


def strings(docs):
    text = F.coalesce("text", F.lit(""))
    return docs.select("doc_id", F.length(text).alias("chars"), F.size(F.split(text, " ")).alias("pieces"), F.lower(F.substring(text, 1, 5)).alias("head"), F.length(F.regexp_replace(text, "[0-9]", "")).alias("no_digits"))


def bits(events):
    k = F.col("event_id")
    return events.select("event_id", k.bitwiseXOR(F.lit(21845)).alias("x"), F.shiftright(k, 2).alias("r"), F.shiftleft(k, 3).alias("l"), F.bit_count(k).alias("ones"), F.bit_get(k, F.lit(1)).cast("int").alias("b1"))


def conditionals(labels):
    return labels.select("doc_id", F.coalesce(F.nullif(F.col("toxic"), F.lit(0)), F.lit(-1)).alias("c"), F.when(F.col("quality") == 1, "good").otherwise("bad").alias("q"))


def decimals(items):
    price = F.col("l_extendedprice").cast("decimal(20,2)")
    return items.groupBy("l_returnflag").agg(F.sum(price).cast("double").alias("total"), F.try_divide(F.sum(price), F.lit(0)).cast("double").alias("nothing"))


def lse(events):
    return R.log_sum_exp(events, "value", ["user_id"]).select("user_id", rounded_col(F.col("lse")).alias("lse"))


def chunk_means(events):
    def fit(table):
        import pyarrow as pa
        import pyarrow.compute as pc

        return pa.table({"user_id": table.column("user_id")[:1], "n": pa.array([table.num_rows]), "mean": pa.array([pc.mean(table.column("value")).as_py()])})

    return R.group_map(events.select("user_id", "value"), ["user_id"], fit, "user_id long, n long, mean double").select("user_id", "n", rounded_col(F.col("mean"), 9).alias("mean"))


E = "events"
QUERIES = {
    "op_scan": t("nation"),
    "op_filter": of(E, lambda d: R.where(d, (F.col("value").between(20, 40)) & F.col("event_type").isin("click", "view", "purchase") & F.col("props").like("%1%")).select("event_id")),
    "op_indicator": of("orders", lambda d: d.select("o_orderkey", F.when(F.col("o_totalprice") > 100000, 1).otherwise(0).alias("big"))),
    "op_drop_incomplete": of("documents", lambda d: R.drop_incomplete(d.select("doc_id", F.when(F.col("n_chars") % 3 != 0, F.col("n_chars")).alias("n")), ["n"])),
    "op_pack_unpack": of(E, lambda d: R.unpack(R.pack(d.select("event_id", "value", (F.col("value") * 2).alias("w")), ["value", "w"]), "x", 2).select("event_id", "x0", "x1")),
    "op_rescale_fill": of(E, lambda d: R.rescale(R.fill(d.select("event_id", F.when(F.col("user_id") % 2 == 0, F.col("value")).alias("value")), {"value": 0.0}), "value", 4.0)),
    "op_cast": of(E, lambda d: R.cast_schema(d.select("event_id", F.col("event_type"), F.col("user_id").cast("string").alias("uid")), {"uid": "bigint", "event_type": "double"})),
    "op_sort_merge_join": two("orders", "customer", lambda a, b: R.sort_merge_join(a, b, F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))),
    "op_shuffle_hash_join": two("orders", "customer", lambda a, b: R.shuffle_hash_join(a, b, F.col("o_custkey") == F.col("c_custkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n"))),
    "op_broadcast_join": two("nation", "region", lambda a, b: R.broadcast_join(a, b, F.col("n_regionkey") == F.col("r_regionkey")).select("n_name", "r_name")),
    "op_cross_draws": two("nation", "region", lambda a, b: R.cross_draws(a.select("n_nationkey"), b.select("r_regionkey"))),
    "op_nested_loop_join": two("supplier", "nation", lambda a, b: a.join(F.broadcast(b), (F.col("s_nationkey") > F.col("n_nationkey")) & (F.col("n_regionkey") == 1)).groupBy("s_suppkey").agg(F.count("*").alias("n"))),
    "op_range_join": bins,
    "op_interval_join": two(E, "orders", interval_pairs),
    "op_asof_join": of(E, asof),
    "op_semi_join": two("customer", "orders", lambda a, b: R.semi_join(a, b.select(F.col("o_custkey").alias("c_custkey")), "c_custkey").select("c_custkey")),
    "op_anti_join": two("documents", "labels", lambda a, b: R.anti_join(a, b, "doc_id").select("doc_id")),
    "op_left_join": two("documents", "labels", lambda a, b: a.join(b, "doc_id", "left").groupBy("lang").agg(F.count("*").alias("n"), F.count("toxic").alias("labelled"))),
    "op_right_join": two("orders", "customer", lambda a, b: a.join(b, F.col("o_custkey") == F.col("c_custkey"), "right").groupBy("c_mktsegment").agg(F.count("o_orderkey").alias("n"), F.count("*").alias("rows"))),
    "op_full_join": two("supplier", "nation", lambda a, b: a.join(b, F.col("s_nationkey") == F.col("n_nationkey"), "full").groupBy("n_name").agg(F.count("s_suppkey").alias("n"))),
    "op_self_join": of("nation", lambda d: R.self_join(d.select("n_nationkey", "n_regionkey"), lambda a, b: f"{a}n_regionkey = {b}n_regionkey AND {a}n_nationkey < {b}n_nationkey").select("a_n_nationkey", "b_n_nationkey")),
    "op_bucketed_join": bucketed_join,
    "op_sums": of("lineitem", lambda d: R.sum_columns(d, {"q": F.col("l_quantity"), "r": F.col("l_extendedprice") * (1 - F.col("l_discount"))}, ["l_returnflag"]).select("l_returnflag", rounded_col(F.col("q"), 2).alias("q"), rounded_col(F.col("r"), 2).alias("r"))),
    "op_sorted_lists": of("conversations", lambda d: R.sorted_lists(d, "conv_id", "turn", ["role"]).select("conv_id", F.array_join(F.col("rows.role"), ",").alias("roles"))),
    "op_counts": of(E, lambda d: d.groupBy("event_type").agg(F.count("*").alias("n"), F.count_if(F.col("value") > 50).alias("high"), F.count_distinct("user_id").alias("users"))),
    "op_moments": of(E, lambda d: R.moments(d, "value", ["event_type"]).select("event_type", *(rounded_col(F.col(c), 5).alias(c) for c in ("mean", "var", "sd")))),
    "op_covariances": of("lineitem", lambda d: R.covariances(d, ["l_quantity", "l_discount", "l_tax"]).select("a", "b", rounded_col(F.col("cov"), 7).alias("cov"), rounded_col(F.col("corr"), 7).alias("corr"))),
    "op_credible_limits": of(E, lambda d: R.credible_limits(d, "value", [0.025, 0.5, 0.975]).select("prob", rounded_col(F.col("value"), 6).alias("value"))),
    "op_rollup": of("lineitem", lambda d: R.rollup_sums(d, ["l_returnflag", "l_linestatus"], {"q": F.col("l_quantity")}).select(F.coalesce("l_returnflag", F.lit("*")).alias("a"), F.coalesce("l_linestatus", F.lit("*")).alias("b"), "q", F.col("level").cast("int").alias("level"))),
    "op_cube": of("lineitem", lambda d: R.cube_sums(d, ["l_returnflag", "l_linestatus"], {"q": F.col("l_quantity")}).select(F.coalesce("l_returnflag", F.lit("*")).alias("a"), F.coalesce("l_linestatus", F.lit("*")).alias("b"), "q", F.col("level").cast("int").alias("level"))),
    "op_grouping_sets": of("orders", lambda d: R.grouping_sets(d, [["o_orderstatus"], ["o_orderpriority"]], ["o_orderstatus", "o_orderpriority"], {"n": F.lit(1)}).select(F.coalesce("o_orderstatus", F.lit("*")).alias("a"), F.coalesce("o_orderpriority", F.lit("*")).alias("b"), "n")),
    "op_pivot": of(E, lambda d: R.pivot_arms(d.groupBy(F.hour("ts").alias("h"), "event_type").agg(F.count("*").alias("n")), "h", "event_type", "n", ["click", "purchase", "view"])),
    "op_unpivot": of("region", lambda d: R.unpivot_arms(d.select("r_regionkey", (F.col("r_regionkey") * 2).alias("p"), (F.col("r_regionkey") + 1).alias("q")), "r_regionkey", ["p", "q"])),
    "op_filtered_sum": of(E, lambda d: d.groupBy("user_id").agg(rounded_col(R.filtered_sum(F.col("value"), F.col("event_type") == "purchase"), 6).alias("v"))),
    "op_distinct_sum": of("orders", lambda d: d.groupBy("o_orderstatus").agg(F.sum_distinct("o_custkey").alias("s"))),
    "op_log_sum_exp": of(E, lse),
    "op_extremes": of(E, lambda d: d.groupBy("user_id").agg(F.min("value").alias("lo"), F.max("value").alias("hi"), F.min_by("value", "event_id").alias("earliest"), F.max_by("value", "event_id").alias("latest"), F.bool_and(F.col("value") >= 0).alias("ok"))),
    "op_group_map": of(E, chunk_means),
    "op_approx_distinct": of("orders", lambda d: d.agg(F.approx_count_distinct("o_custkey", 0.02).alias("n"))),
    "op_sketch_counts": of(E, lambda d: R.sketch_counts(d, "event_type", ["view", "click", "purchase", "none such"])),
    "op_sketch_quantile": of(E, lambda d: R.sketch_quantile(d, "value", 0.5)),
    "op_panel_index": of("orders", lambda d: R.panel_index(d.select("o_custkey", "o_orderkey"), "o_custkey", ["o_orderkey"])),
    "op_ranks": of("part", lambda d: R.ranks(d.select("p_partkey", "p_brand", "p_size"), "p_brand", "p_size").select("p_partkey", "rank", "dense_rank", rounded_col(F.col("percent_rank")).alias("percent_rank"), rounded_col(F.col("cume_dist")).alias("cume_dist"))),
    "op_moving_average": of(E, lambda d: R.moving_average(d, "user_id", "event_id", "value").select("event_id", rounded_col(F.col("moving")).alias("moving"))),
    "op_change": of(E, lambda d: R.change(d, "user_id", "event_id", "value").select("event_id", rounded_col(F.col("change")).alias("change"), "ahead")),
    "op_running_sum": of(E, lambda d: R.running_sum(d, "user_id", ["event_id"], "value").select("event_id", rounded_col(F.col("running")).alias("running"))),
    "op_time_range": of(E, lambda d: R.time_range_window(d, "user_id", "ts", "value", 86400).select("event_id", rounded_col(F.col("recent")).alias("recent"))),
    "op_first_last": of(E, lambda d: R.first_last(d, "user_id", ["event_id"], "value").select("event_id", "first", "last", "second")),
    "op_running_moments": of(E, lambda d: R.running_moments(d, "user_id", ["event_id"], "value").select("event_id", rounded_col(F.col("run_mean"), 9).alias("run_mean"), rounded_col(F.col("run_sd"), 5).alias("run_sd"))),
    "op_tiles_ntile": of("orders", lambda d: d.select("o_orderkey", F.ntile(8).over(R.W.partitionBy("o_orderstatus").orderBy("o_orderkey")).alias("tile"))),
    "op_top_k": of("orders", lambda d: R.top_k(d, [F.desc("o_totalprice"), F.asc("o_orderkey")], 25).select("o_orderkey")),
    "op_top_k_per_group": of("orders", lambda d: R.top_k_per_group(d, "o_custkey", [F.desc("o_totalprice"), F.asc("o_orderkey")], 3).select("o_custkey", "o_orderkey")),
    "op_page": of("orders", lambda d: R.page(d, ["o_orderkey"], 40, 20).select("o_orderkey")),
    "op_sort_nulls": of("labels", lambda d: R.global_sort(d.select("doc_id", F.nullif(F.col("toxic"), F.lit(0)).cast("double").alias("t")), ["t", "doc_id"])),
    "op_union": two("customer", "supplier", lambda a, b: R.union_by_name(a.select(F.col("c_nationkey").alias("n")), b.select(F.col("s_nationkey").alias("n"))).groupBy("n").agg(F.count("*").alias("c"))),
    "op_union_distinct": two("customer", "supplier", lambda a, b: a.select(F.col("c_nationkey").alias("n")).union(b.select("s_nationkey")).distinct()),
    "op_intersect": of(E, lambda d: d.where("value < 50").select("user_id").intersect(d.where("event_type = 'purchase'").select("user_id"))),
    "op_intersect_all": of(E, lambda d: d.where("value < 50").select("user_id").intersectAll(d.where("event_type = 'purchase'").select("user_id")).groupBy("user_id").agg(F.count("*").alias("n"))),
    "op_except": two("customer", "orders", lambda a, b: a.select(F.col("c_custkey").alias("k")).subtract(b.select("o_custkey"))),
    "op_except_all": of(E, lambda d: d.select("user_id").exceptAll(d.where("value < 50").select("user_id")).groupBy("user_id").agg(F.count("*").alias("n"))),
    "op_store_round_trip": store_round_trip,
    "op_csv_round_trip": csv_round_trip,
    "op_json_round_trip": json_round_trip,
    "op_orc_round_trip": orc_round_trip,
    "op_table_sample": lambda spark, sf_dir: (register_views(spark, sf_dir, ["events"]), table_sample_sql(spark, "events", 5, 7).select("event_id"))[1],
    "fn_math": of(E, lambda d: d.select("event_id", *(rounded_col(c, 6).alias(n) for n, c in (("a", F.log1p("value")), ("b", F.sqrt("value")), ("c", F.expm1(F.col("value") / 100)), ("d", F.pow(F.col("value"), 1.5)), ("e", F.cos("value")), ("f", F.greatest(F.col("value"), F.lit(30.0))), ("g", F.signum(F.col("value") - 50)))))),
    "fn_logistic": of(E, lambda d: d.select("event_id", rounded_col(sigmoid((F.col("value") - 50) / 7), 9).alias("p"))),
    "fn_bits": of(E, bits),
    "fn_hash_uniform": of(E, lambda d: d.select("event_id", hash_uniform("h", F.col("event_id")).alias("u"))),
    "fn_dates": of("orders", dates),
    "fn_strings": of("documents", strings),
    "fn_arrays": of(E, feature_arrays),
    "fn_maps": of(E, maps),
    "fn_json": of(E, lambda d: d.select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"), F.from_json("props", "k int")["k"].alias("k2"))),
    "fn_conditionals": of("labels", conditionals),
    "fn_decimals": of("lineitem", decimals),
    "fn_sql": sql_functions,
    "fn_predict_prob": of(E, lambda d: d.select("event_id", rounded_col(predict_prob(F.array(F.lit(1.0), F.col("value") / 100), [-1.0, 2.0])).alias("p"))),
    "fn_table_functions": table_functions,
    "fn_lateral_draws": lateral_draws,
    "plan_choices": plan_table,
    "stream_anchor_sums": stream_sums,
    "stream_windows": stream_windows,
    "stream_sessions": stream_sessions,
    "stream_dedup": stream_dedup,
    "stream_panels": stream_panels,
    "stream_static_join": stream_static,
    "stream_interval_join": stream_pairs,
    "stream_online_fit": online_fit,
    "fn_random": random_functions,
    "op_poisson_sample": poisson_sample,
}

WIN = "PARTITION BY user_id ORDER BY event_id"
Z = "(-1.5 - 0.1 * x1 + 0.1 * x2 + 0.7 * x3)"
EV = "ev AS (SELECT *, (event_type = 'purchase')::INTEGER::DOUBLE AS y, 1.0::DOUBLE AS x0, (hour(ts) < 6 OR hour(ts) >= 22)::INTEGER::DOUBLE AS x1, (isodow(ts) IN (6, 7))::INTEGER::DOUBLE AS x2, value / 100 AS x3 FROM events)"
SQL = {
    "op_scan": "SELECT * FROM nation",
    "op_sketch_counts": "SELECT key, (SELECT count(*) FROM events WHERE event_type = key) AS n FROM (VALUES ('view'), ('click'), ('purchase'), ('none such')) v(key)",
    "op_filter": "SELECT event_id FROM events WHERE value BETWEEN 20 AND 40 AND event_type IN ('click', 'view', 'purchase') AND props LIKE '%1%'",
    "op_indicator": "SELECT o_orderkey, (o_totalprice > 100000)::INTEGER AS big FROM orders",
    "op_drop_incomplete": "SELECT doc_id, n_chars AS n FROM documents WHERE n_chars % 3 <> 0",
    "op_pack_unpack": "SELECT event_id, value AS x0, value * 2 AS x1 FROM events",
    "op_rescale_fill": "SELECT event_id, CASE WHEN user_id % 2 = 0 THEN value ELSE 0 END / 4 AS value FROM events",
    "op_cast": "SELECT event_id, TRY_CAST(event_type AS DOUBLE) AS event_type, user_id AS uid FROM events",
    "op_sort_merge_join": "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1",
    "op_shuffle_hash_join": "SELECT o_orderstatus, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1",
    "op_broadcast_join": "SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey",
    "op_cross_draws": "SELECT n_nationkey, r_regionkey FROM nation, region",
    "op_nested_loop_join": "SELECT s_suppkey, count(*) AS n FROM supplier JOIN nation ON s_nationkey > n_nationkey AND n_regionkey = 1 GROUP BY 1",
    "op_range_join": "SELECT k::INTEGER AS span, count(*) AS n FROM events, range(14) r(k) WHERE value >= 7.0 * k AND value < 7.0 * k + 10.0 GROUP BY 1",
    "op_interval_join": "SELECT event_id, count(*) AS n FROM events JOIN orders ON o_orderdate >= ts AND o_orderdate <= ts + INTERVAL 7200 SECOND WHERE event_type = 'purchase' GROUP BY 1",
    "op_asof_join": "WITH l AS (SELECT * FROM events WHERE event_type = 'purchase'), r AS (SELECT user_id, ts, value FROM events WHERE event_type <> 'purchase') SELECT event_id, r.value FROM l ASOF LEFT JOIN r ON l.user_id = r.user_id AND l.ts >= r.ts",
    "op_semi_join": "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)",
    "op_anti_join": "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)",
    "op_left_join": "SELECT lang, count(*) AS n, count(toxic) AS labelled FROM documents LEFT JOIN labels USING (doc_id) GROUP BY 1",
    "op_right_join": "SELECT c_mktsegment, count(o_orderkey) AS n, count(*) AS rows FROM orders RIGHT JOIN customer ON o_custkey = c_custkey GROUP BY 1",
    "op_full_join": "SELECT n_name, count(s_suppkey) AS n FROM supplier FULL JOIN nation ON s_nationkey = n_nationkey GROUP BY 1",
    "op_self_join": "SELECT a.n_nationkey AS a_n_nationkey, b.n_nationkey AS b_n_nationkey FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey",
    "op_bucketed_join": "SELECT c_nationkey, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1",
    "op_sums": "SELECT l_returnflag, round(sum(l_quantity), 2) + 0.0 AS q, round(sum(l_extendedprice * (1 - l_discount)), 2) + 0.0 AS r FROM lineitem GROUP BY 1",
    "op_sorted_lists": "SELECT conv_id, string_agg(role, ',' ORDER BY turn, role) AS roles FROM conversations GROUP BY 1",
    "op_counts": "SELECT event_type, count(*) AS n, count(*) FILTER (WHERE value > 50) AS high, count(DISTINCT user_id) AS users FROM events GROUP BY 1",
    "op_moments": "SELECT event_type, round(avg(value), 5) + 0.0 AS mean, round(var_samp(value), 5) + 0.0 AS var, round(stddev_samp(value), 5) + 0.0 AS sd FROM events GROUP BY 1",
    "op_covariances": " UNION ALL ".join(f"SELECT '{a}' AS a, '{b}' AS b, round(covar_samp({a}, {b}), 7) + 0.0 AS cov, round(corr({a}, {b}), 7) + 0.0 AS corr FROM lineitem" for a, b in (("l_quantity", "l_quantity"), ("l_quantity", "l_discount"), ("l_quantity", "l_tax"), ("l_discount", "l_discount"), ("l_discount", "l_tax"), ("l_tax", "l_tax"))),
    "op_credible_limits": " UNION ALL ".join(f"SELECT {p}::DOUBLE AS prob, round(quantile_cont(value, {p}), 6) + 0.0 AS value FROM events" for p in (0.025, 0.5, 0.975)),
    "op_rollup": "SELECT coalesce(l_returnflag, '*') AS a, coalesce(l_linestatus, '*') AS b, sum(l_quantity) AS q, grouping(l_returnflag, l_linestatus)::INTEGER AS level FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)",
    "op_cube": "SELECT coalesce(l_returnflag, '*') AS a, coalesce(l_linestatus, '*') AS b, sum(l_quantity) AS q, grouping(l_returnflag, l_linestatus)::INTEGER AS level FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)",
    "op_grouping_sets": "SELECT coalesce(o_orderstatus, '*') AS a, coalesce(o_orderpriority, '*') AS b, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))",
    "op_pivot": "SELECT hour(ts)::INTEGER AS h, " + ", ".join(f"nullif(count(*) FILTER (WHERE event_type = '{e}'), 0) AS {e}" for e in ("click", "purchase", "view")) + " FROM events GROUP BY 1",
    "op_unpivot": "SELECT r_regionkey, 'p' AS arm, r_regionkey * 2 AS value FROM region UNION ALL SELECT r_regionkey, 'q', r_regionkey + 1 FROM region",
    "op_filtered_sum": "SELECT user_id, round(sum(value) FILTER (WHERE event_type = 'purchase'), 6) + 0.0 AS v FROM events GROUP BY 1",
    "op_distinct_sum": "SELECT o_orderstatus, sum(DISTINCT o_custkey)::BIGINT AS s FROM orders GROUP BY 1",
    "op_log_sum_exp": "WITH m AS (SELECT user_id, max(value) AS m FROM events GROUP BY 1) SELECT user_id, round(any_value(m) + ln(sum(exp(value - m))), 6) + 0.0 AS lse FROM events JOIN m USING (user_id) GROUP BY 1",
    "op_extremes": "SELECT user_id, min(value) AS lo, max(value) AS hi, arg_min(value, event_id) AS earliest, arg_max(value, event_id) AS latest, bool_and(value >= 0) AS ok FROM events GROUP BY 1",
    "op_group_map": "SELECT user_id, count(*) AS n, round(avg(value), 9) + 0.0 AS mean FROM events GROUP BY 1",
    "op_panel_index": "SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderkey)::INTEGER AS t FROM orders",
    "op_ranks": "SELECT p_partkey, (rank() OVER w)::INTEGER AS rank, (dense_rank() OVER w)::INTEGER AS dense_rank, round(percent_rank() OVER w, 6) + 0.0 AS percent_rank, round(cume_dist() OVER w, 6) + 0.0 AS cume_dist FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size)",
    "op_moving_average": f"SELECT event_id, round(avg(value) OVER ({WIN} ROWS 4 PRECEDING), 6) + 0.0 AS moving FROM events",
    "op_change": f"SELECT event_id, round(value - lag(value) OVER ({WIN}), 6) + 0.0 AS change, lead(value) OVER ({WIN}) AS ahead FROM events",
    "op_running_sum": f"SELECT event_id, round(sum(value) OVER ({WIN} ROWS UNBOUNDED PRECEDING), 6) + 0.0 AS running FROM events",
    "op_time_range": "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY floor(epoch(ts))::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW), 6) + 0.0 AS recent FROM events",
    "op_first_last": f"SELECT event_id, first_value(value) OVER w AS first, last_value(value) OVER w AS last, nth_value(value, 2) OVER w AS second FROM events WINDOW w AS ({WIN} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)",
    "op_running_moments": f"SELECT event_id, round(avg(value) OVER w, 9) + 0.0 AS run_mean, round(stddev_samp(value) OVER w, 5) + 0.0 AS run_sd FROM events WINDOW w AS ({WIN} ROWS UNBOUNDED PRECEDING)",
    "op_tiles_ntile": "SELECT o_orderkey, (ntile(8) OVER (PARTITION BY o_orderstatus ORDER BY o_orderkey))::INTEGER AS tile FROM orders",
    "op_top_k": "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25",
    "op_top_k_per_group": "SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 3",
    "op_page": "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 20 OFFSET 40",
    "op_sort_nulls": "SELECT doc_id, nullif(toxic, 0)::DOUBLE AS t FROM labels",
    "op_union": "SELECT n, count(*) AS c FROM (SELECT c_nationkey AS n FROM customer UNION ALL SELECT s_nationkey FROM supplier) GROUP BY 1",
    "op_union_distinct": "SELECT c_nationkey AS n FROM customer UNION SELECT s_nationkey FROM supplier",
    "op_intersect": "SELECT user_id FROM events WHERE value < 50 INTERSECT SELECT user_id FROM events WHERE event_type = 'purchase'",
    "op_intersect_all": "SELECT user_id, count(*) AS n FROM (SELECT user_id FROM events WHERE value < 50 INTERSECT ALL SELECT user_id FROM events WHERE event_type = 'purchase') GROUP BY 1",
    "op_except": "SELECT c_custkey AS k FROM customer EXCEPT SELECT o_custkey FROM orders",
    "op_except_all": "SELECT user_id, count(*) AS n FROM (SELECT user_id FROM events EXCEPT ALL SELECT user_id FROM events WHERE value < 50) GROUP BY 1",
    "op_store_round_trip": "SELECT (event_id % 8)::INTEGER AS tile, count(*) AS n, round(sum(value), 4) + 0.0 AS v FROM events WHERE event_id % 8 IN (2, 5) GROUP BY 1",
    "op_csv_round_trip": "SELECT * FROM nation",
    "op_json_round_trip": "SELECT s_suppkey, s_name FROM supplier",
    "op_orc_round_trip": "SELECT * FROM region",
    "fn_math": "SELECT event_id, " + ", ".join(f"{rounded(x)} AS {n}" for n, x in (("a", "ln(1 + value)"), ("b", "sqrt(value)"), ("c", "exp(value / 100) - 1"), ("d", "pow(value, 1.5)"), ("e", "cos(value)"), ("f", "greatest(value, 30.0)"), ("g", "sign(value - 50)"))) + " FROM events",
    "fn_logistic": f"SELECT event_id, {rounded(logistic('(value - 50) / 7'), 9)} AS p FROM events",
    "fn_bits": "SELECT event_id, xor(event_id, 21845) AS x, event_id >> 2 AS r, event_id << 3 AS l, bit_count(event_id)::INTEGER AS ones, ((event_id >> 1) & 1)::INTEGER AS b1 FROM events",
    "fn_hash_uniform": f"SELECT event_id, {u("'h'", 'event_id')} AS u FROM events",
    "fn_dates": "SELECT o_orderkey, hour(o_orderdate)::INTEGER AS h, (dayofweek(o_orderdate) + 1)::INTEGER AS dow, date_diff('day', o_orderdate::DATE, DATE '1998-01-01')::INTEGER AS age, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, TIMESTAMP '1995-01-01' - o_orderdate > INTERVAL 15 DAY AS early FROM orders",
    "fn_strings": "SELECT doc_id, length(coalesce(text, ''))::INTEGER AS chars, len(string_split(coalesce(text, ''), ' '))::INTEGER AS pieces, lower(substr(coalesce(text, ''), 1, 5)) AS head, length(regexp_replace(coalesce(text, ''), '[0-9]', '', 'g'))::INTEGER AS no_digits FROM documents",
    "fn_arrays": "WITH b AS (SELECT event_id, [1.0::DOUBLE, value / 100, hour(ts)::DOUBLE] AS x FROM events) SELECT event_id, round(x[1] * 0.5 - x[2] + 0.25 * x[3], 6) + 0.0 AS dot, round(3 * x[3], 6) + 0.0 AS axpy, round(pow(x[1] + x[2] + x[3], 2), 6) + 0.0 AS outer_sum FROM b",
    "fn_maps": "SELECT event_id, value * 2 AS b2, 2 AS keys FROM events",
    "fn_json": "SELECT event_id, json_extract_string(props, '$.k')::INTEGER AS k, json_extract_string(props, '$.k')::INTEGER AS k2 FROM events",
    "fn_conditionals": "SELECT doc_id, coalesce(nullif(toxic, 0), -1) AS c, CASE WHEN quality = 1 THEN 'good' ELSE 'bad' END AS q FROM labels",
    "fn_decimals": "SELECT l_returnflag, sum(l_extendedprice::DECIMAL(20, 2))::DOUBLE AS total, NULL::DOUBLE AS nothing FROM lineitem GROUP BY 1",
    "fn_sql": f"SELECT event_id, round({logistic('(value - 50) / 10')}, 9) AS p, round({softplus('(value - 50) / 10')}, 9) AS s, {u("'q'", 'event_id')} AS u FROM events",
    "fn_predict_prob": f"SELECT event_id, {rounded(logistic('-1.0 + 2.0 * value / 100'))} AS p FROM events",
    "stream_anchor_sums": f"WITH {EV} SELECT count(*) AS n, {rounded(f'sum(y * {Z} - {softplus(Z)}) / count(*)')} AS ll, {', '.join(f'{rounded(f'sum((y - {logistic(Z)}) * x{j}) / count(*)')} AS g{j}' for j in range(4))}, {rounded(f'sum(-{logistic(Z)} * (1 - {logistic(Z)}) * x1 * x3) / count(*)')} AS h1_3 FROM ev",
    "stream_windows": f"WITH {EV} SELECT strftime(ts, '%Y-%m-%d') AS day, count(*) AS n, sum(y) AS ones, {rounded('sum(y) / count(*)')} AS rate FROM ev GROUP BY 1",
    "stream_sessions": f"WITH {EV}, g AS (SELECT *, CASE WHEN ts > lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 12 HOUR OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL THEN 1 ELSE 0 END AS s FROM ev) SELECT user_id, sum(s)::BIGINT AS sessions, count(*) AS n, sum(y) AS ones FROM g GROUP BY 1",
    "stream_dedup": "SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY 1",
    "stream_interval_join": "SELECT a.user_id, a.event_id AS left_id, b.event_id AS right_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 3600 SECOND AND a.event_id <> b.event_id",
    "stream_panels": f"WITH {EV} SELECT user_id, count(*) AS n, sum(y) AS ones FROM ev GROUP BY 1",
    "stream_static_join": f"WITH {EV} SELECT c_mktsegment, count(*) AS n, sum(y) AS ones FROM ev LEFT JOIN customer ON user_id = c_custkey GROUP BY 1",
}
