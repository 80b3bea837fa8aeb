import numpy as np
import pytest
from pyspark.sql import functions as F

from gradvb import estimators
from gradvb.designs import flights
from gradvb.estimators import block_kernel, from_frame, remainders
from gradvb.models import Logit
from gradvb.sums import exact_sums


@pytest.fixture(scope="module")
def obs(spark):
    return flights(spark, "/root/testdata/sf0.001").cache()


def test_equal_rows_of_a_batch_are_worked_once(obs):
    """6000 rows are of at most 400 kinds; every one of them went through the kernel for every draw."""

    class Few(Logit):
        def block(self, z, y):
            if len(z) > 401:
                raise ValueError(f"{len(z)} rows")
            return super().block(z, y)

    thetas, anchor = np.random.default_rng(2).normal(size=(32, 4)), exact_sums(obs, np.zeros(4))
    frame = obs.withColumn("w", 1.0 + F.pmod(F.xxhash64("obs_key"), F.lit(3)))
    rows = frame.toPandas()
    x, y, w = rows[[f"x{k}" for k in range(4)]].to_numpy(), rows["y"].to_numpy(), rows["w"].to_numpy()
    plain = remainders(x, y, w, thetas, anchor, Logit(), "linear")
    got = {r.draw_id: (r.stats, r.n) for r in block_kernel(frame.coalesce(1), thetas, anchor, 1.0, Few(), "linear").collect()}
    for k in range(32):
        assert got[k][1] == len(y) and np.allclose(got[k][0], np.concatenate([plain[0][k], plain[1][k], [plain[2][k]]]), rtol=1e-9, atol=1e-8)


def test_rows_of_their_own_stay_as_they_are(spark):
    frame = spark.range(500).select(F.lit(1.0).alias("x0"), (F.col("id") / 500).alias("x1"), F.pmod("id", F.lit(2)).cast("double").alias("y"))
    thetas = np.random.default_rng(3).normal(size=(16, 2))
    grad, ll, _, n = from_frame(block_kernel(frame, thetas, None, None, None, "none"), thetas, None, "none")
    assert n == 500
    for k in range(16):
        exact = exact_sums(frame, thetas[k])
        assert np.allclose(grad[k], exact.grad) and np.isclose(ll[k], exact.loglik)


@pytest.mark.parametrize("scheme", ["replacement", "slice"])
def test_large_stores_of_few_kinds_are_held(spark, obs, monkeypatch, scheme):
    """A store beyond the driver's numbers was joined with an index list for each sample, however few its kinds."""
    from gradvb.estimators import HeldStore, SampleProvider
    from gradvb.sampling import lay_out, tile_counts

    store = lay_out(obs)
    counts, anchor, thetas = tile_counts(store), exact_sums(obs, np.full(4, 0.1)), np.random.default_rng(4).normal(size=(8, 4)) * 0.1
    fetched = SampleProvider(store, anchor, 0.05, scheme=scheme, counts=counts, hold=False, engine="driver").estimate(thetas, 3)
    monkeypatch.setattr(estimators, "DRIVER_NUMBERS", 1000)
    monkeypatch.setattr(estimators, "FETCH_ROWS", 300)  # less than a tile
    whole = HeldStore(store, counts)
    assert whole.fits() and not whole.small()
    provider = SampleProvider(store, anchor, 0.05, scheme=scheme, counts=counts, whole=whole)
    got = provider.estimate(thetas, 3)
    assert provider.holds and len(whole.kind) == sum(counts.values()) and len(whole.x) <= 400
    assert np.allclose(got.grad, fetched.grad) and np.allclose(got.loglik, fetched.loglik) and got.rows == fetched.rows
    monkeypatch.setattr(estimators, "HELD_KINDS", 10)
    assert not HeldStore(store, counts).fits()


def test_long_index_lists_draw_the_same_rows(spark, obs, monkeypatch):
    """Beyond a number of rows executors drew other rows than the driver would, so fits moved with the size alone."""
    from gradvb import sampling

    store = sampling.lay_out(obs)
    counts = sampling.tile_counts(store)
    monkeypatch.setattr(sampling, "TILE_ROWS", 70)
    keys = ["draw_id", "tile", "row_idx", "w"]
    rows = lambda: sorted(map(tuple, sampling.with_replacement(store, counts, 300, 5, 2, 3)[0].select(*keys).collect()))
    short = rows()
    monkeypatch.setattr(sampling, "BROADCAST_INDEX", 100)
    assert rows() == short and sum(r[3] for r in short) == 900


def test_ablations_take_the_same_samples_at_every_size(spark, monkeypatch):
    """Arms that leave the scheme open took slices from 20 million rows on."""
    from gradvb import fit
    from gradvb.queries import experiments

    used = []

    def first_arms(provider, *_):
        used.append((provider.scheme, provider.pairing))
        raise StopIteration

    monkeypatch.setattr(fit, "CACHED_ROWS", 1000)
    monkeypatch.setattr(experiments, "ascend", first_arms)
    with pytest.raises(StopIteration):
        experiments.QUERIES["ablations"](spark, "/root/testdata/sf0.001")
    assert used == [("replacement", "shared")]


def test_chain_on_many_cells_makes_no_pass_for_a_step(spark, monkeypatch):
    """With more than 100000 covariate cells every step was a job over the rows."""
    from gradvb import baselines, sums

    def refused(*_):
        raise AssertionError("a pass over the rows")

    frame = spark.range(120_000).select(F.lit(1.0).alias("x0"), (F.col("id") / 120_000).alias("x1"), F.pmod(F.xxhash64("id"), F.lit(2)).cast("double").alias("y"))
    exact = sums.fit_mle(frame)
    value = exact_sums(frame, [0.3, -0.2], order=0).loglik
    monkeypatch.setattr(sums, "exact_sums", refused)
    chain = baselines.rw_mcmc(frame, iters=20, burn=10)
    assert chain.draws.shape == (20, 2)
    cells = estimators.sufficient_cells(frame)
    assert len(cells.x) == 120_000 and cells.loglik(np.array([0.3, -0.2])) == pytest.approx(value)
    assert np.allclose(cells.fit_mle().theta, exact.theta, atol=1e-9)


def test_subsets_of_few_kinds_are_fitted_by_one_aggregate(obs, monkeypatch):
    """Each Newton step was a job."""
    from gradvb import sums

    best = sums.fit_anchor(obs, fraction=0.5)
    monkeypatch.setattr(sums, "SUBSET_KINDS", 10)
    rows = sums.fit_anchor(obs, fraction=0.5)
    assert best.n == rows.n and np.allclose(best.theta, rows.theta, atol=1e-9) and np.allclose(best.hess, rows.hess, rtol=1e-9)
    monkeypatch.setattr(sums, "SUBSET_KINDS", 1000)
    monkeypatch.setattr(sums, "exact_sums", lambda *_: 1 / 0)
    assert sums.fit_anchor(obs, fraction=0.5).n == best.n


def test_tiles_are_dealt_out_evenly(obs):
    """Sixteen hashed tiles left some of eight tasks with several and others with none."""
    from gradvb.sampling import build_store

    store = build_store(obs, 16)
    assert [r["count"] for r in store.select(F.spark_partition_id().alias("p"), "tile").distinct().groupBy("p").count().collect()] == [1] * 16


def test_incomplete_rows_of_a_design_go(spark):
    from gradvb.designs import design

    rows = spark.createDataFrame([(1.0, 1.0), (None, 1.0), (1.0, None), (float("nan"), 0.0), (0.0, float("nan"))], "a double, b double")
    assert [tuple(r) for r in design(rows, F.col("b"), {"a": F.col("a")}).collect()] == [(1.0, 1.0, 1.0)]
