"""Similarities kept in files give what the matrices on the driver give."""

import numpy as np
import pytest

from hyperembed.operators import baselines as bl, rowfiles as rf
from hyperembed.plans import embed as em, experiments as ex
from hyperembed.queries import QUERIES
from hyperembed.sources import graphs


@pytest.fixture(scope="module")
def planted(spark):
    w = graphs.planted(spark, n=120, edges=200)
    return w, ex.extended(w, 5)


def vectors(df):
    p = df.toPandas().sort_values("id")
    return p["id"].to_numpy(), np.array(p["vec"].tolist())


@pytest.mark.parametrize("side, negative", [("node", "drop"), ("edge", "drop"), ("node", "keep")])
def test_base_method_above_the_drivers_size(planted, monkeypatch, side, negative):
    x = planted[1]
    ids, want = vectors(em.embed_dense(x, 8, side=side, negative=negative))
    monkeypatch.setattr(rf, "DENSE", 10)
    got_ids, got = vectors(em.embed_dense(x, 8, side=side, negative=negative))
    assert (ids == got_ids).all()
    assert np.abs(want - got).max() < 1e-5


def test_dense_factorisation_above_the_drivers_size(planted, monkeypatch):
    h = planted[0].graph
    ids, want = vectors(bl.base_dense_mf(h, 8))
    monkeypatch.setattr(rf, "DENSE", 10)
    got_ids, got = vectors(bl.base_dense_mf(h, 8))
    assert (ids == got_ids).all()
    assert np.abs(want @ want.T - got @ got.T).max() < 1e-5


def test_two_view_with_similarity_rows_above_the_columns_limit(planted, monkeypatch):
    w, x = planted
    dense = graphs.dense_attributes(w)
    q = len(dense.first()["attrs"])
    ids, want = vectors(ex.two_view_extended(w, x, dense, q, 6))
    monkeypatch.setattr(ex, "COLUMNS", 10)
    got_ids, got = vectors(ex.two_view_extended(w, x, dense, q, 6))
    assert (ids == got_ids).all()
    assert np.abs(want @ want.T - got @ got.T).max() < 1e-5 * np.abs(want @ want.T).max()


@pytest.mark.parametrize("name, rows", [("sketch_unbiased", 3), ("sketch_bound", 2), ("base_dense_mf_planted", 125)])
def test_moved_queries_read_a_given_table(spark, monkeypatch, name, rows):
    seen = []
    monkeypatch.setattr(graphs, "read", lambda s, d, t, read=graphs.read: seen.append(t) or read(s, d, t))
    assert QUERIES[name](spark, "/root/testdata/sf0.001").count() <= rows
    assert seen


def test_smoothing_of_vectors_that_are_mostly_zero_broadcasts_none(spark, planted, monkeypatch):
    plans, write = [], bl.cut

    def watched(df, label="cut"):
        if label == "smooth":
            df.collect()
            plans.append(df._jdf.queryExecution().executedPlan().toString().split("Initial Plan")[0])
        return write(df, label)

    monkeypatch.setattr(bl, "cut", watched)
    h = planted[0].graph
    zero = h.inc.select("vid").distinct().selectExpr("vid AS id", "array(1D, 0D) AS vec")
    bl._smooth(bl.Hypergraph(write(h.inc), write(h.edges)), write(zero), 2, 1)
    assert plans and not any("BroadcastHashJoin" in p for p in plans)
