"""Smoothing by panels against joins."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from hyperembed.operators import baselines as bl, lowrank as lr, panels
from hyperembed.operators.hypergraph import hypergraph_from
from hyperembed.plans import embed as em, experiments as ex
from hyperembed.sources import graphs


def test_panels_give_the_vectors_of_joins(spark, monkeypatch):
    rng = np.random.default_rng(4)
    rows = [(int(e), int(v) * 7 - 50, float(g)) for e, v, g in zip(rng.integers(0, 60, 400), rng.integers(0, 90, 400), rng.random(400) + 0.1)]
    rows += [(900, 5000, 1.0), (900, 5001, 2.0)]  # no vector reaches these
    h = hypergraph_from(spark.createDataFrame(rows, "e long, v long, g double"), "e", "v", gamma="g", w=F.col("size") * 0.5)
    given = [(v * 7 - 50, rng.standard_normal(5).tolist()) for v in range(80)] + [(-49, [1.0] * 5), (None, [1.0] * 5)]
    vecs = spark.createDataFrame(given, "id long, vec array<double>")
    read = lambda df: {r["id"]: r["vec"] for r in df.collect()}
    want = read(bl._smooth(h, vecs, 5, 2))
    monkeypatch.setattr(panels, "JOINED", 0)
    monkeypatch.setattr(panels, "FILE_ROWS", 100)
    monkeypatch.setattr(panels, "PANEL_BYTES", 2 * 8 * 90)
    joins = []
    monkeypatch.setattr(bl, "half_step", lambda *a, **k: joins.append(1))
    got = read(bl._smooth(h, vecs, 5, 2))
    assert not joins and got.keys() == want.keys() and 5000 not in got
    assert all(np.allclose(got[i], want[i], rtol=1e-12, atol=1e-12) for i in want)


def _close(got, want):
    """Up to the columns' signs and turns among equal values."""
    return np.abs(got @ got.T - want @ want.T).max() < 1e-8


@pytest.mark.parametrize("power", [0, 2])
@pytest.mark.parametrize("edges", [True, False])
def test_block_svd_by_panels_is_that_of_joins(spark, monkeypatch, power, edges):
    w = graphs.planted(spark, n=120, edges=200)
    x = ex.extended(w, 5)
    read = lambda df: np.array([r["vec"] for r in df.orderBy("id").collect()])
    want = lr.svd_block(x, 6, power=power)
    monkeypatch.setattr(panels, "JOINED", 0)
    monkeypatch.setattr(panels, "FILE_ROWS", 300)
    monkeypatch.setattr(panels, "PANEL_BYTES", 3 * 8 * 120)
    blocks, write = [], lr.cut
    monkeypatch.setattr(lr, "cut", lambda df, label="cut": blocks.append(label) or write(df, label))
    got = lr.svd_block(x, 6, power=power, edges=edges)
    assert "block" not in blocks
    assert np.abs(got.sigma - want.sigma).max() < 1e-10 and _close(read(got.v), read(want.v))
    if edges:
        assert _close(read(got.u), read(want.u))


def test_sketch_is_not_written(spark, monkeypatch):
    w = graphs.planted(spark, n=120, edges=200)
    x, labels, write = ex.extended(w, 5), [], em.cut
    monkeypatch.setattr(em, "cut", lambda df, label="cut": labels.append(label) or write(df, label))
    assert em.embed_sketch(x, ex.SMALL, ("node",)).vectors("node").count() == 120
    assert "sketch" not in labels
