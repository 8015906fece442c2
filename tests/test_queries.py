"""Every query with a SQL twin gives the twin's rows on the smallest tables."""

import glob
import os

import duckdb
import pytest

from hyperembed.plans import embed as em, experiments as ex
from hyperembed.queries import ORACLES, QUERIES
from hyperembed.sources import graphs

SF = "/root/testdata/sf0.001"
#: Minutes of work in all; run by the driver's gate, and here with HYPEREMBED_ALL=1.
HEAVY = {"reported_shapes", "svd_residual", "exact_tail", "fold_in", "embed_checks", "sweep_tau_b"}


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for p in glob.glob(f"{SF}/*.parquet"):
        c.execute(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM read_parquet('{p}')")
    return c


def rows(columns, records):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted(repr(tuple(float(r[i]) if isinstance(r[i], (int, float)) and not isinstance(r[i], bool) else r[i] for i in order)) for r in records)


@pytest.mark.parametrize("name", sorted(ORACLES if os.environ.get("HYPEREMBED_ALL") else set(ORACLES) - HEAVY))
def test_against_sql(spark, duck, name):
    df = QUERIES[name](spark, SF)
    got = rows(df.columns, df.collect())
    result = duck.execute(ORACLES[name])
    columns = [d[0] for d in result.description]
    assert sorted(df.columns) == sorted(columns)
    assert got == rows(columns, result.fetchall())


@pytest.mark.parametrize("name, source", [("base_anchor", graphs.order_baskets), ("base_dense_mf_vectors", graphs.vec_buckets), ("base_linear_filter_days", graphs.user_days)])
def test_compared_methods_read_the_tables(spark, name, source):
    ids = [x[0] for x in QUERIES[name](spark, SF).select("id").collect()]
    assert sorted(ids) == sorted(x[0] for x in source(spark, SF).graph.inc.select("vid").distinct().collect())


def test_compared_methods_and_experiments_on_every_workload():
    names = [n for n in QUERIES if n.startswith(("base_", "exp_")) and n not in ("exp_scale", "exp_scale_settings", "exp_mae")]
    roots = {n for n in names if not n.endswith(("_days", "_vectors", "_planted"))}
    assert len(roots) == 15 + 13 and set(names) == {n + s for n in roots for s in ("", "_days", "_vectors", "_planted")}


def test_experiments_use_the_default_sketch_width():
    assert ex.SMALL.b == em.Settings().b == 128


@pytest.mark.parametrize("name", ["walk_filter", "walk_filter_shape", "sweep_alpha", "metric_gain", "metric_repeat", "metric_rank"])
def test_queries_read_a_given_table(spark, monkeypatch, name):
    seen = []
    monkeypatch.setattr(graphs, "read", lambda s, d, t, read=graphs.read: seen.append(t) or read(s, d, t))
    QUERIES[name](spark, SF)
    assert seen
