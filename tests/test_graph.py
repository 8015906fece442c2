import numpy as np
import pytest
from pyspark.sql import functions as F

from hyperembed.operators import baselines as bl, hypergraph as hg, knn, lowrank as lr, tasks as tk, walk as wk
from hyperembed.plans import embed as em
from hyperembed.queries.common import extended
from hyperembed.sources import graphs, hyperedge_text


@pytest.fixture(scope="module")
def toy(spark):
    return graphs.toy(spark)


@pytest.fixture(scope="module")
def toy_x(spark, toy):
    return extended(spark, toy, 2)


def pairs(df, *cols):
    return sorted(tuple(r[c] for c in cols) for r in df.collect())


def test_worked_example(toy):
    """Three hyperedges; node 3 lies in all of them, so on the dual they all meet in it."""
    assert pairs(hg.node_degrees(toy.graph), "vid", "d") == [(1, 1), (2, 1), (3, 3), (4, 1), (5, 2), (6, 1)]
    assert pairs(hg.line_graph(toy.graph), "e", "f", "shared") == [(1, 2, 1), (1, 3, 1), (2, 3, 2)]
    assert pairs(hg.clique_expand(toy.graph).where("weight > 1"), "i", "j", "weight") == [(3, 5, 2.0)]
    d = hg.dual(toy.graph)
    assert pairs(hg.edge_degrees(d), "eid", "delta") == [(1, 1), (2, 1), (3, 3), (4, 1), (5, 2), (6, 1)]
    assert pairs(hg.components(toy.graph), "vid", "component") == [(v, 1) for v in range(1, 7)]


def test_attribute_hyperedges_of_the_example(toy, toy_x):
    a = toy_x.inc.where(F.col("eid") >= hg.ATTR)
    sizes = pairs(a.groupBy("eid").count(), "eid", "count")
    assert len(sizes) == 6 and all(1 < n <= 3 for _, n in sizes)
    assert pairs(a.where(F.col("eid") == hg.ATTR + 3).withColumn("g", F.round("gamma", 6)), "vid", "g") == [(3, 1.0), (4, 0.707107), (5, 1.0)]
    vol = {r["kind"]: r["v"] for r in toy_x.weighted.join(toy_x.edges.select("eid", "kind"), "eid").groupBy("kind").agg(F.sum(F.col("w") * F.col("gamma")).alias("v")).collect()}
    assert abs(vol["A"] - vol["S"]) < 1e-9 and vol["S"] == 9


def test_construction_edge_cases(spark):
    rows = spark.createDataFrame([(1, 1, 2.0), (1, 1, 3.0), (1, 2, 1.0), (2, 7, 1.0), (3, None, 1.0), (None, 4, 1.0), (4, 1, -5.0), (4, 2, 1.0)], "e long, v long, g double")
    h = hg.hypergraph_from(rows, "e", "v", "g")
    assert pairs(h.inc, "eid", "vid", "gamma") == [(1, 1, 5.0), (1, 2, 1.0)]
    assert pairs(h.edges, "eid", "kind", "w") == [(1, "S", 1.0)]
    empty = hg.hypergraph_from(rows.limit(0), "e", "v")
    assert hg.stats(empty).count() == 1 and hg.components(empty).count() == 0
    with pytest.raises(ValueError):
        hg.clique_expand(h, most_pairs=0)


def test_negative_and_zero_cosines(spark):
    v = spark.createDataFrame([(1, [1.0, 0.0]), (2, [-1.0, 0.0]), (3, [0.0, 0.0]), (4, [1.0, 0.0])], "vid long, attrs array<double>")
    near = knn.knn_exact(v, 3, 2)
    assert pairs(near.where("vid = 1"), "nbr", "cos") == [(2, -1.0), (3, 0.0), (4, 1.0)]
    assert pairs(hg.attribute_hyperedges(near, v.select("vid")).where(F.col("eid") == hg.ATTR + 3), "vid", "gamma") == [(3, 1.0)]
    assert pairs(knn.knn_broadcast(v, 3), "vid", "nbr", "cos") == pairs(near, "vid", "nbr", "cos")


def test_knn_forms_on_ties(spark, toy):
    dense = graphs.dense_attributes(toy)
    exact = knn.knn_exact(dense, 2, 3)
    sparse = knn.knn_sparse(toy.attrs, 2)
    assert pairs(exact.where("cos > 0").select("vid", "nbr", F.round("cos", 9).alias("c")), "vid", "nbr", "c") == pairs(sparse.select("vid", "nbr", F.round("cos", 9).alias("c")), "vid", "nbr", "c")
    assert pairs(knn.knn_lsh(dense, 2), "vid", "nbr", "cos") == pairs(knn.knn_ivf(dense, 2), "vid", "nbr", "cos") == pairs(exact, "vid", "nbr", "cos")


def test_knn_of_nulls_short_vectors_and_repeated_rows(spark):
    rows = [(1, [1.0, 0.0]), (1, [1.0, 0.0]), (2, [-1.0, 0.0]), (3, [0.0, 0.0]), (4, [1.0]), (5, None), (None, [1.0, 2.0]), (6, [1.0, None]), (7, []), (8, [1.0, float("nan")])]
    v = spark.createDataFrame([(i, x, "more", 1) for i, x in rows], "vid long, attrs array<double>, cos string, nbr int")
    exact = pairs(knn.knn_exact(v, 3, 2), "vid", "nbr", "cos")
    assert [x[1:] for x in exact if x[0] == 1] == [(4, 1.0), (6, 1.0), (8, 1.0)] and {x[0] for x in exact} == {1, 2, 3, 4, 6, 7, 8}
    for f in (knn.knn_broadcast, knn.knn_lsh, knn.knn_ivf):
        assert pairs(f(v, 3), "vid", "nbr", "cos") == exact
        assert f(v.limit(0), 3).count() == 0


def test_knn_in_tiles_and_lists(spark, monkeypatch):
    """Cells beyond TILE rows and a vector that a third of all rows have: the same result as one block; recall from measured probes."""
    x = np.random.default_rng(3).standard_normal((400, 6))
    x[::3] = x[0]
    v = spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(x)], "vid long, attrs array<double>")
    exact = pairs(knn.knn_exact(v, 5, 1), "vid", "nbr", "cos")
    monkeypatch.setattr(knn, "TILE", 64)
    assert pairs(knn.knn_ivf(v, 5, lists=1), "vid", "nbr", "cos") == exact
    assert knn.recall(knn.knn_ivf(v, 5, lists=12), spark.createDataFrame(exact, knn.OUT)).first()[0] >= 0.9
    assert knn.recall(knn.knn_lsh(v, 5, bits=2), spark.createDataFrame(exact, knn.OUT)).first()[0] >= 0.9


def test_walk_special_cases(spark, toy_x):
    src = spark.createDataFrame([(3,)], "id long")
    whole = wk.walk(toy_x, src, alpha=1.0, steps=3)
    assert pairs(whole.where("p > 0"), "id", "p") == [(3, 1.0)]
    free = wk.walk(toy_x, src, alpha=0.0, steps=2)
    assert abs(free.agg(F.sum("p")).first()[0] - 1) < 1e-12
    many = wk.walk(toy_x, src, alpha=0.0, steps=40).join(wk.stationary(toy_x).withColumnRenamed("p", "q"), "id")
    assert many.agg(F.max(F.abs(F.col("p") - F.col("q")))).first()[0] < 1e-6


def test_dense_and_walk_similarity_agree(spark, toy, toy_x):
    ids, sim = em.dense_similarity(toy_x)
    got = wk.similarity(toy_x, toy.nodes.select(F.col("vid").alias("id")))
    for r in got.collect():
        assert abs(sim[list(ids).index(r["source"]), list(ids).index(r["id"])] - r["sim"]) < 1e-9
    eids, esim = em.dense_similarity(toy_x, side="edge")
    assert list(eids) == [1, 2, 3] and np.allclose(esim, esim.T)


def test_rank_below_k_is_padded(toy_x):
    z = np.array(em.embed_dense(toy_x, k=32).toPandas()["vec"].tolist())
    assert z.shape == (6, 32)
    m = em.embed_sketch(toy_x, em.Settings(k=32, rank=32, b=16))
    assert np.array(m.vectors("node").toPandas()["vec"].tolist()).shape == (6, 32) and m.svd.rank <= 6
    assert m.vectors("edge").count() == 3


def test_svd_known_pair(toy_x):
    s = lr.svd_block(toy_x, 3, oversample=3)
    d = {r["vid"]: r["d"] for r in hg.node_degrees(toy_x).collect()}
    v = {r["id"]: r["vec"][0] for r in s.v.collect()}
    ratio = [v[i] / np.sqrt(d[i]) for i in d]
    assert abs(s.sigma[0] - 1) < 1e-9 and np.ptp(ratio) < 1e-9


def test_measures(spark):
    s = spark.createDataFrame([(True, 0.9), (False, 0.1), (True, 0.5), (False, 0.5)], "y boolean, score double")
    assert tk.auc(s).first()[0] == 0.875
    assert tk.auc(s.withColumn("score", F.lit(1.0))).first()[0] == 0.5
    p = spark.createDataFrame([("a", "a"), ("a", "b"), ("b", "b"), ("c", "b")], "y string, predicted string")
    f = tk.f1_scores(p).first()
    assert f["micro_f1"] == tk.accuracy(p).first()[0] == 0.5 and abs(f["macro_f1"] - (2 / 3 + 0.5 + 0) / 3) < 1e-12


def test_learner_on_planted_classes(spark):
    w = graphs.planted(spark, n=160, edges=320, purity=95)
    z = em.embed_sketch(extended(spark, w, 5), em.Settings(k=16, rank=16, b=64), ("node",)).vectors("node")
    labels = w.labels.select(F.col("vid").alias("id"), "y")
    f = tk.f1_scores(tk.classify(z, labels, tk.split(labels.select("id"), 40), 16)).first()
    assert f["micro_f1"] > 0.7
    base = tk.f1_scores(tk.classify(bl.base_spectral(w.graph, 16), labels, tk.split(labels.select("id"), 40), 16)).first()
    assert base["micro_f1"] > 0.4


def test_text_source_round_trip(spark, tmp_path):
    hyperedge_text.register(spark)
    (tmp_path / "a.txt").write_text("1 2 3\n\n4 4 5")
    got = spark.read.format("hyperedges").option("path", str(tmp_path)).load()
    assert pairs(got, "eid", "vid") == [(0, 1), (0, 2), (0, 3), (2, 4), (2, 5)]


def test_plans_push_filters_and_broadcast_small_sides_only(spark, capsys):
    from hyperembed.queries import QUERIES

    QUERIES["scan_pruned"](spark, "/root/testdata/sf0.001").explain("formatted")
    out = capsys.readouterr().out
    assert "PushedFilters: [IsNotNull(o_orderpriority)" in out and "ReadSchema: struct<o_orderkey:bigint,o_totalprice:double,o_orderpriority:string>" in out
    QUERIES["node_degree"](spark, "/root/testdata/sf0.001").explain("formatted")
    assert "CartesianProduct" not in capsys.readouterr().out


def test_wide_gram_adds_up_on_executors(spark):
    from hyperembed.operators.blocks import gram, gram_rows

    x = np.random.default_rng(1).standard_normal((300, 385))
    vecs = lr.to_frame(spark, np.arange(300), x).repartition(9)
    assert gram_rows(vecs, 385).count() == 385
    assert np.abs(gram(vecs, 385) - x.T @ x).max() < 1e-9


def test_lanczos_finds_values_that_repeat(spark, toy_x):
    """Three components: the value 1 three times over; vectors are orthonormal and their residuals small."""
    from hyperembed.operators.blocks import gram

    rows = [(10 * c + e, 100 * c + v, 1.0) for c in range(3) for e, v in [(0, 0), (0, 1), (0, 2), (1, 2), (1, 3), (2, 3), (2, 0), (3, 1), (3, 4), (3, 0)]]
    h = hg.hypergraph_from(spark.createDataFrame(rows, "e long, v long, g double"), "e", "v", "g")
    full, got = lr.svd_full(h, 8), lr.svd_lanczos(h, 8)
    assert np.abs(got.sigma[:3] - 1).max() < 1e-9 and np.abs(full.sigma - got.sigma).max() < 1e-7
    for side in (got.u, got.v):
        assert np.abs(gram(side, 8) - np.eye(8)).max() < 1e-6


def test_clique_walk_makes_no_pairs_of_neighbours(spark, monkeypatch):
    rows = [(1, 1, 1.0), (1, 2, 2.0), (1, 3, 1.0), (2, 3, 1.0), (2, 4, 3.0), (3, 5, 1.0), (3, 6, 1.0), (4, 6, 1.0), (5, 7, 1.0)]
    h = hg.hypergraph_from(spark.createDataFrame(rows, "e long, v long, g double"), "e", "v", "g", F.lit(2.0), min_size=1)
    a = np.zeros((8, 8))
    for e, i, x in rows:
        for f, j, y in rows:
            if e == f and i != j:
                a[i, j] += 2 * x * y
    p = np.divide(a, a.sum(1, keepdims=True), out=np.zeros_like(a), where=a.sum(1, keepdims=True) > 0)
    walk = np.eye(8)
    for _ in range(4):
        walk = 0.1 * np.eye(8) + 0.9 * walk @ p
    average = (p + p @ p + p @ p @ p) / 3
    monkeypatch.setattr(hg, "clique_expand", None)
    source = h.inc.select(F.col("vid").alias("id")).distinct()
    for limit in (700_000, 0):
        monkeypatch.setattr(bl, "RATES", limit)
        for got, want in ((bl.pagerank_pairs(h, source, 0.1, 4), walk), (bl.clique_powers_average(h), average)):
            found = {(r["source"], r["id"]): r["p"] for r in got.collect()}
            assert {k for k, v in found.items() if v > 1e-12} == {(i, j) for i in range(1, 8) for j in range(1, 8) if want[i, j] > 1e-12}
            assert all(abs(v - want[k]) < 1e-12 for k, v in found.items())
