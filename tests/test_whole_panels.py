"""Panel queries without SQL work on every eligible customer."""

import pytest

from gradvb.baselines import loglik_estimates
from gradvb.designs import nest_panels, w3_panels
from gradvb.panel import to_block
from gradvb.queries import experiments

SF = "/root/testdata/sf0.01"


def test_all_eligible_customers_are_kept(spark):
    orders = spark.read.parquet(f"{SF}/orders.parquet")
    eligible = orders.groupBy("o_custkey").count().where("count >= 5").count()
    assert eligible > 1000
    assert w3_panels(spark, SF).select("panel_id").distinct().count() == eligible
    assert w3_panels(spark, SF, 70).count() == 5 * 70


def test_chain_takes_all_panels_and_the_tuned_draws(spark, monkeypatch):
    """146 panels are eligible at sf0.001; the chain used to stop at 100 and at 64 draws whatever was tuned."""
    small, used = "/root/testdata/sf0.001", {}

    def chain(block, start, n_is, iters, burn):
        used.update(n=block.count(), n_is=n_is, at=start.n)
        rows = block.limit(40).collect()
        own = to_block([r.panel_id for r in rows], [r.y for r in rows], [r.x for r in rows])
        few = block.where(block["panel_id"].isin([r.panel_id for r in rows]))
        used["pair"] = [loglik_estimates(b, start.theta, 32, 5) for b in (own, few)]
        raise StopIteration

    monkeypatch.setattr(experiments.baselines, "tune_is_count", lambda block, theta, **_: (37, [(37, 1.0)]))
    monkeypatch.setattr(experiments.baselines, "pm_mcmc", chain)
    with pytest.raises(StopIteration):
        experiments.QUERIES["pseudo_marginal_chain"](spark, small)
    eligible = nest_panels(w3_panels(spark, small).drop("panel_rank")).count()
    assert used["n"] == used["at"] == eligible > 100 and used["n_is"] == 37
    assert used["pair"][0] == pytest.approx(used["pair"][1])


def test_chain_has_the_published_length(spark, monkeypatch):
    """300 proposals were run of 40000."""
    used = {}

    def chain(block, start, n_is, iters, burn):
        used.update(iters=iters, burn=burn)
        raise StopIteration

    monkeypatch.setattr(experiments.baselines, "tune_is_count", lambda block, theta, **_: (16, [(16, 1.0)]))
    monkeypatch.setattr(experiments.baselines, "pm_mcmc", chain)
    with pytest.raises(StopIteration):
        experiments.QUERIES["pseudo_marginal_chain"](spark, "/root/testdata/sf0.001")
    assert used == {"iters": 30_000, "burn": 10_000}
