"""Operators, sources, streams and the entry module."""

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from gradvb import measures
from gradvb.designs import flights
from gradvb.families import RankOneState
from gradvb.fit import FitConfig, prepare
from gradvb.functions.scalars import norm_cdf, norm_ppf, register
from gradvb.functions.tables import log_sum_exp, numeric_gradient
from gradvb.models import Logit
from gradvb.operators import relational as R
from gradvb.plans.planner import plan_fit
from gradvb.queries import MODULES
from gradvb.sources.tables import draws_frame, explain_text, read_tiles, write_store

SF = "/root/testdata/sf0.001"


def test_entry_and_contract(spark):
    got = entry.entry(spark).toPandas()
    assert list(got.columns) == ["param", "mean", "sd", "anchor", "truth"] and len(got) == 4
    assert (np.abs(got["mean"] - got["truth"]) < 5 * got["sd"]).all()
    names = entry.queries()
    assert set(entry.oracle_sql()) <= set(names)
    assert sum(len(m.QUERIES) for m in MODULES) <= len(names)


def test_range_join_equals_the_plain_condition(spark):
    points = spark.createDataFrame([(k, k * 0.37) for k in range(200)], "i int, v double")
    spans = spark.createDataFrame([(k, k * 3.0, k * 3.0 + 7.5) for k in range(20)], "j int, lo double, hi double")
    got = {(r.i, r.j) for r in R.range_join(points, spans, "v", "lo", "hi", 2.0).collect()}
    assert got == {(i, j) for i in range(200) for j in range(20) if j * 3.0 <= i * 0.37 < j * 3.0 + 7.5}


def test_tile_reads_are_pruned(spark, tmp_path):
    df = spark.range(100).select("id", (F.col("id") % 5).cast("int").alias("tile"), F.col("id").alias("row_idx"))
    write_store(df, str(tmp_path / "store"))
    got = read_tiles(spark, str(tmp_path / "store"), [1, 4])
    assert got.count() == 40 and "PartitionFilters: [" in explain_text(got) and "tile" in explain_text(got).split("PartitionFilters")[1][:80]


def test_broadcasts_are_checked(spark):
    big = spark.range(50)
    with pytest.raises(ValueError):
        R.cross_draws(big, big, 10)
    assert "BroadcastHashJoin" not in explain_text(R.broadcast_join(spark.range(10).toDF("id"), big, "id", most_rows=10).hint("merge")).split("Sort")[0][:40]


def test_log_sum_exp_twins(spark):
    df = spark.createDataFrame([(k % 3, float(k) * 40) for k in range(30)], "g int, v double")
    a = {r.g: r.lse for r in R.log_sum_exp(df, "v", ["g"]).collect()}
    b = {r.g: r.lse for r in df.groupBy("g").agg(log_sum_exp("v").alias("lse")).collect()}
    assert all(np.isclose(a[k], b[k]) for k in a)


def test_numeric_gradient(spark):
    df = spark.createDataFrame([(float(k % 2), 1.0, k / 10) for k in range(20)], "y double, x0 double, x1 double")
    got = {r.k: r.g for r in numeric_gradient(df, Logit(), [0.2, -0.4]).collect()}
    x = np.array([[1.0, k / 10] for k in range(20)])
    y = np.array([float(k % 2) for k in range(20)])
    assert np.allclose([got[0], got[1]], x.T @ Logit().block(x @ [0.2, -0.4], y)[1], atol=1e-5)


def test_normal_columns(spark):
    df = spark.createDataFrame([(float(u),) for u in (1e-9, 0.01, 0.3, 0.5, 0.99)], "u double")
    for r in df.select("u", norm_cdf(norm_ppf(F.col("u"))).alias("v")).collect():
        assert abs(r.u - r.v) < 1e-12


def test_sql_surface(spark):
    register(spark)
    assert abs(spark.sql("SELECT sigmoid(0D) + softplus(0D) AS v").first().v - 0.5 - np.log(2)) < 1e-12
    assert spark.sql("SELECT count(*) AS n FROM sobol_points(8, 2, 0)").first().n == 16


def test_density_tables(spark):
    state = RankOneState(np.array([0.0, 1.0]), np.array([0.3, 0.1]), 0.2)
    grid = measures.marginal_density(spark, state, 201)
    for p, x, pdf in [(g.param, g.x, g.pdf) for g in grid.groupBy("param").agg(F.collect_list("x").alias("x"), F.collect_list("pdf").alias("pdf")).collect()]:
        order = np.argsort(x)
        assert abs(np.trapezoid(np.array(pdf)[order], np.array(x)[order]) - 1) < 1e-3, p
    same = measures.density_distance(grid, grid).collect()
    assert all(r.l1 == 0 and r.hellinger < 1e-2 for r in same)
    assert draws_frame(spark, [[0.0, 1.0]]).count() == 1


def test_traces_are_appended(spark, tmp_path):
    from gradvb.sources.tables import append_trace

    for t in range(3):
        append_trace(spark, str(tmp_path / "trace"), [{"iter": t, "lb": -1.0 / (t + 1)}], "iter int, lb double")
    assert [tuple(r) for r in spark.read.parquet(str(tmp_path / "trace")).orderBy("iter").collect()] == [(0, -1.0), (1, -0.5), (2, -1 / 3)]


def test_sketched_counts_are_never_too_low(spark):
    from gradvb.operators.relational import sketch_counts

    df = spark.range(10_000).selectExpr("pmod(id * id, 97) AS k")
    exact = {r.k: r["count"] for r in df.groupBy("k").count().collect()}
    got = {r.key: r.n for r in sketch_counts(df, "k", list(range(97)), 0.01).collect()}
    assert all(exact.get(k, 0) <= n <= exact.get(k, 0) + 0.05 * 10_000 for k, n in got.items())


def test_plan_choices(spark):
    small, large = plan_fit(600_000, 4, 0.01, 256), plan_fit(10**12, 4, 10**6, 256)
    assert small.engine == "driver" and large.engine == "spark" and large.tiles == 500_000
    ready = prepare(flights(spark, SF))
    assert ready.scheme(FitConfig()) == "replacement" and ready.scheme(FitConfig(scheme="chunks")) == "chunks"
    ready.counts = {k: 10**9 for k in range(500)}
    assert ready.scheme(FitConfig(m=10**5)) == "slice" and ready.scheme(FitConfig(m=0.2)) == "tile"
    assert plan_fit(10**9, 65, 0.2, 256).scheme == "tile" and plan_fit(10**9, 65, 0.2, 256).exact_kernel == "block"


@pytest.mark.parametrize("name", ["stream_anchor_sums", "stream_windows", "stream_dedup"])
def test_streams_run(spark, name):
    assert entry.queries()[name](spark, SF).count() > 0


def test_matched_streams_leave_through_files_and_keep_state_on_disk(spark, tmp_path):
    from gradvb.streaming import online

    rows = [(1, 0), (1, 0), (1, 3600), (1, 3601), (1, 7199), (1, 7200), (2, 3599), (2, 10_799), (2, -1), (2, 3598)]
    spark.createDataFrame([(k, u, 360_000_000 + t) for k, (u, t) in enumerate(rows)], "event_id long, user_id long, s long").selectExpr("event_id", "user_id", "timestamp_seconds(s) AS time").coalesce(1).write.parquet(str(tmp_path / "in"))
    left, right = (spark.readStream.schema("event_id long, user_id long, time timestamp").parquet(str(tmp_path / "in")).withWatermark("time", "1 day") for _ in range(2))
    got = online.run_to_table(online.matched_streams(left, right, 3600), str(tmp_path / "out"), str(tmp_path / "state"))
    assert got.columns == ["user_id", "left_time", "left_id", "right_time", "right_id"]
    want = sorted((a, b) for a, (u, s) in enumerate(rows) for b, (v, t) in enumerate(rows) if u == v and s <= t <= s + 3600)
    assert sorted((r.left_id, r.right_id) for r in got.collect()) == want
    assert list((tmp_path / "state" / "state").rglob("*.zip")) and spark.conf.get("spark.sql.streaming.stateStore.providerClass").endswith("HDFSBackedStateStoreProvider")


@pytest.mark.parametrize("name", ["bound_window", "draws_table", "marginal_density_grid", "mc_standard_errors"])
def test_measures_and_draws_read_given_tables(spark, name):
    import duckdb

    got, sql = entry.queries()[name](spark, SF), entry.oracle_sql()[name]
    assert got.inputFiles()
    with duckdb.connect() as c:
        for table in ("customer", "events"):
            c.execute(f"CREATE VIEW {table} AS SELECT * FROM '{SF}/{table}.parquet'")
        want = c.execute(f"SELECT {', '.join(got.columns)} FROM ({sql})").fetchall()
    mine = [tuple(r) for r in got.collect()]
    assert len(mine) == len(want) > 0
    for a, b in zip(sorted(mine, key=str), sorted(want, key=str), strict=True):
        assert a == pytest.approx(b, abs=2e-6)


def test_table_functions_go_over_given_tables(spark):
    got = {r.kind: r for r in entry.queries()["fn_table_functions"](spark, SF).collect()}
    rows = {t: spark.read.parquet(f"{SF}/{t}.parquet") for t in ("nation", "supplier", "events")}
    assert got["net"].n == 16 * 3 * rows["nation"].count() and got["draws"].n == 2 * 3 * rows["supplier"].count()
    assert got["grid"].n == 41 * rows["events"].select("event_type").distinct().count() and abs(got["net"].v - 0.5) < 0.02


@pytest.mark.parametrize("name", ["chunk_constancy", "integrator_check", "net_quality", "model_choice"])
def test_experiments_run(spark, name):
    got = entry.queries()[name](spark, SF).toPandas()
    if name == "chunk_constancy":
        assert got["loglik_mean"].nunique() == 1
    if name == "integrator_check":
        by = got.set_index(["proposal", "draws"])["loglik_error"].abs()
        assert by[("prior", "rqmc")] < by[("prior", "mc")]
    if name == "model_choice":
        assert list(got["rank"]) == [1, 2, 3, 4]


def test_net_quality_goes_over_the_events(spark, tmp_path):
    """It made its points up and read no table; its mean now moves with the events, and even points leave less variance."""
    events = spark.read.parquet(f"{SF}/events.parquet")
    events.where("event_type = 'purchase'").write.parquet(str(tmp_path / "events.parquet"))
    whole, part = (entry.queries()["net_quality"](spark, d).toPandas().set_index(["draws", "s"]) for d in (SF, str(tmp_path)))
    for s in (64, 256):
        assert whole.loc[("rqmc", s), "variance"] < whole.loc[("mc", s), "variance"] and whole.loc[("rqmc", s), "discrepancy"] < whole.loc[("mc", s), "discrepancy"]
    assert (whole["variance"] != part["variance"]).all()
