"""Sweeps give what they name: accuracy, seconds and the fit to the similarity."""

import numpy as np
import pytest

from hyperembed.plans import embed as em, experiments as ex
from hyperembed.sources import graphs


@pytest.fixture(scope="module")
def planted(spark):
    return graphs.planted(spark, n=120, edges=200)


@pytest.mark.parametrize("alpha, steps", [(0.1, 10), (0.3, 7), (0.2, 1)])
def test_fit_over_all_pairs_is_that_of_the_matrices(planted, monkeypatch, alpha, steps):
    x = ex.extended(planted, 5)
    z = em.embed_dense(x, 8, alpha, steps)
    ids, sim = em.dense_similarity(x, alpha, steps)
    monkeypatch.setattr(em.rf, "BLOCK", 7)
    assert em.similarity_error(x, z.repartition(3), alpha, steps) == pytest.approx(ex._mae(ids, sim, z), rel=1e-9)


def test_fit_with_no_vectors_is_the_similaritys_own_mean(planted):
    x = ex.extended(planted, 5)
    ids, sim = em.dense_similarity(x)
    z = em.lr.to_frame(x.inc.sparkSession, ids, np.zeros((len(ids), 2)))
    assert em.similarity_error(x, z) == pytest.approx(sim.mean() / np.diag(sim).mean(), rel=1e-9)


def test_sweep_tells_the_fit_for_each_value(spark, planted):
    rows = ex.sweep(spark, planted, "K", (2, 5)).collect()
    metrics = {"seconds", "micro_f1", "macro_f1", "mae_node"}
    assert {(r["param"], r["metric"]) for r in rows} == {(p, m) for p in ("2", "5") for m in metrics}
    assert all(0 < r["value"] < 1 for r in rows if r["metric"] == "mae_node")
