"""Walks by files against walks by joins."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from hyperembed.functions.vectors import mix, mix_numbers
from hyperembed.operators import baselines as bl, walkers
from hyperembed.operators.hypergraph import hypergraph_from


def test_hash_of_arrays_is_that_of_columns(spark):
    a = [0, 1, -1, 7, 2147483647, -(1 << 62), (1 << 62) + 12345]
    df = spark.createDataFrame([(x,) for x in a], "a long")
    for b, seed in ((0, 1), (93, 51), (5, 61)):
        assert [r[0] for r in df.select(mix(F.col("a"), b, seed)).collect()] == mix_numbers(np.array(a), b, seed).tolist()


@pytest.mark.parametrize("restart", [None, 0.3])
def test_walks_by_files_are_those_of_joins(spark, monkeypatch, restart):
    rng = np.random.default_rng(5)
    rows = [(int(e) - 9, int(v) * 11 - 60) for e, v in zip(rng.integers(0, 70, 300), rng.integers(0, 90, 300))] + [(500, 1 << 41), (500, 3)]
    h = hypergraph_from(spark.createDataFrame(rows, "e long, v long"), "e", "v")
    read = lambda c: sorted(tuple(r) for r in c.select("start", "walk", "step", "vid").collect())
    want = read(bl.walk_corpus(h, 3, 7, restart=restart))
    monkeypatch.setattr(walkers, "JOINED", 0)
    monkeypatch.setattr(walkers, "FILE_ROWS", 20)
    labels, write = [], bl.cut
    monkeypatch.setattr(bl, "cut", lambda df, label="cut": labels.append(label) or write(df, label))
    assert read(bl.walk_corpus(h, 3, 7, restart=restart)) == want
    assert "members" not in labels
