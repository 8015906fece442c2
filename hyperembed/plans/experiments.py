"""Experiment runs: tidy rows (experiment, graph, method, param, metric, split, value)."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame, SparkSession, functions as F

from ..operators import baselines as bl, hypergraph as hg, knn, lowrank as lr, tasks as tk
from ..session import cut
from ..sources import graphs
from . import embed as em

TIDY = "experiment string, graph string, method string, param string, metric string, split int, value double"


class Run:
    """Collects tidy rows; only single numbers reach the driver."""

    def __init__(self, spark: SparkSession, name: str):
        self.spark, self.name, self.rows = spark, name, []

    def put(self, graph, method, metric, value, param="", split=0):
        self.rows.append((self.name, graph, method, str(param), metric, split, float(value)))

    def frame(self) -> DataFrame:
        return self.spark.createDataFrame(self.rows, TIDY)


def extended(w: graphs.Workload, k: int = 10, beta: float = 1.0) -> hg.Hypergraph:
    if not k:
        return w.graph
    near = knn.knn_ivf(graphs.dense_attributes(w), k)
    h = hg.extend(w.graph, cut(near), w.nodes, beta)
    return hg.Hypergraph(cut(h.inc), cut(h.edges))


def node_scores(run: Run, name: str, method: str, z: DataFrame, w: graphs.Workload, width: int, splits: int = 3, param="", train: int = 20) -> None:
    """Micro- and Macro-F1 of a linear learner on node vectors, per split."""
    z, labels = cut(z.select("id", "vec")), w.labels.select(F.col("vid").alias("id"), "y")
    for s in range(splits):
        pred = tk.classify(z, labels, tk.split(labels.select("id"), train, s), width)
        f = tk.f1_scores(pred).first()
        run.put(name, method, "micro_f1", f["micro_f1"], param, s)
        run.put(name, method, "macro_f1", f["macro_f1"], param, s)


def edge_scores(run: Run, name: str, method: str, z: DataFrame, w: graphs.Workload, width: int, splits: int = 3, param="") -> None:
    z, labels = cut(z.select("id", "vec")), cut(tk.edge_majority_label(w.graph, w.labels).select(F.col("eid").alias("id"), "y"))
    for s in range(splits):
        f = tk.f1_scores(tk.classify(z, labels, tk.split(labels.select("id"), 20, s), width)).first()
        run.put(name, method, "micro_f1", f["micro_f1"], param, s)
        run.put(name, method, "macro_f1", f["macro_f1"], param, s)


SMALL = em.Settings(k=16, rank=16)


def node_classification(spark, w: graphs.Workload, settings=SMALL, compared=("linear filter", "affinity", "anchor", "spectral", "dense factorisation")) -> DataFrame:
    run = Run(spark, "exp_node_cls")
    x = extended(w)
    dense = cut(graphs.dense_attributes(w))
    q = dense.first() and len(dense.first()["attrs"])
    methods = {
        "final method": lambda: em.embed_sketch(x, settings, ("node",)).vectors("node"),
        "base method": lambda: em.embed_dense(x, settings.k),
        "linear filter": lambda: bl.base_linear_filter(w.graph, dense, q, settings.k),
        "affinity": lambda: bl.base_affinity(w.graph, dense, q, settings.k),
        "anchor": lambda: bl.base_anchor(w.graph, settings.k),
        "spectral": lambda: bl.base_spectral(w.graph, settings.k),
        "dense factorisation": lambda: bl.base_dense_mf(w.graph, settings.k),
    }
    for name, make in methods.items():
        if name in ("final method", "base method", *compared):
            node_scores(run, w.name, name, make(), w, settings.k)
    return run.frame()


def edge_classification(spark, w: graphs.Workload, settings=SMALL) -> DataFrame:
    """Native hyperedge vectors against means of node vectors."""
    run = Run(spark, "exp_edge_cls")
    x = extended(w)
    m = em.embed_sketch(x, settings)
    edge_scores(run, w.name, "final method", m.vectors("edge"), w, settings.k)
    edge_scores(run, w.name, "base method", em.embed_dense(x, settings.k, side="edge"), w, settings.k)
    pooled = hg.mean_pool(m.vectors("node"), w.graph, settings.k).withColumnRenamed("eid", "id")
    edge_scores(run, w.name, "mean of node vectors", pooled, w, settings.k)
    return run.frame()


def link_prediction(spark, w: graphs.Workload, settings=SMALL) -> DataFrame:
    """Embed the training hyperedges with all attributes; tell real from random hyperedges."""
    run = Run(spark, "exp_link")
    graph, examples = tk.link_examples(w.graph, w.nodes)
    examples = cut(examples)
    x = extended(graphs.Workload(w.name, hg.Hypergraph(cut(graph.inc), cut(graph.edges)), w.nodes, w.attrs, w.labels))
    for method, z in (("final method", em.embed_sketch(x, settings, ("node",)).vectors("node")), ("base method", em.embed_dense(x, settings.k))):
        for how in ("range", "concat"):
            s = tk.link_scores(examples, cut(z), settings.k, how).first()
            run.put(w.name, method, "accuracy", s["accuracy"], how)
            run.put(w.name, method, "auc", s["auc"], how)
    return run.frame()


def _mae(ids, sim, z_frame) -> float:
    p = z_frame.toPandas().sort_values("id")
    z = np.array(p["vec"].tolist(), float)[np.isin(p["id"].to_numpy(), ids)]
    dots = z @ z.T
    return float(np.abs(sim / np.diag(sim).mean() - dots / max(np.diag(dots).mean(), 1e-12)).mean())


def approximation_error(spark, w: graphs.Workload, settings=em.Settings(k=32, rank=32)) -> DataFrame:
    run = Run(spark, "exp_mae")
    x = extended(w)
    model = em.embed_sketch(x, settings)
    for side in ("node", "edge"):
        ids, sim = em.dense_similarity(x, side=side)
        run.put(w.name, "base method", f"mae_{side}", _mae(ids, sim, em.embed_dense(x, settings.k, side=side)))
        run.put(w.name, "final method", f"mae_{side}", _mae(ids, sim, model.vectors(side)))
    return run.frame()


def ablation(spark, w: graphs.Workload, k: int = 16) -> DataFrame:
    """The base method in full, with one hop only, and without attribute hyperedges."""
    run = Run(spark, "exp_ablation")
    x = extended(w)
    for method, h, steps in (("full", x, 10), ("one hop", x, 1), ("no attribute hyperedges", w.graph, 10)):
        node_scores(run, w.name, method, em.embed_dense(h, k, steps=steps), w, k)
        edge_scores(run, w.name, method, em.embed_dense(h, k, steps=steps, side="edge"), w, k)
    return run.frame()


def sweep(spark, w: graphs.Workload, what: str, values, settings=SMALL) -> DataFrame:
    """One parameter at a time: K, beta, r, alpha, tau or b; accuracy, seconds and the fit to the similarity."""
    run = Run(spark, f"exp_{what}")
    base = extended(w)
    for v in values:
        began = time.time()
        x = extended(w, k=v) if what == "K" else extended(w, beta=v) if what == "beta" else base
        s = settings if what in ("K", "beta") else em.Settings(**(settings.__dict__ | {{"r": "rank"}.get(what, what): v}))
        z = cut(em.embed_sketch(x, s, ("node",)).vectors("node"))
        run.put(w.name, "final method", "seconds", time.time() - began, v)
        node_scores(run, w.name, "final method", z, w, s.k, 1, v)
        run.put(w.name, "final method", "mae_node", em.similarity_error(x, z, s.alpha, s.steps), v)
    return run.frame()


def grid(spark, w: graphs.Workload, ks=(5, 10), betas=(0.5, 1.0), ranks=(8, 16), settings=SMALL) -> DataFrame:
    run = Run(spark, "exp_grid")
    for k in ks:
        for beta in betas:
            x = extended(w, k, beta)
            for r in ranks:
                z = em.embed_sketch(x, em.Settings(**(settings.__dict__ | {"rank": r})), ("node",)).vectors("node")
                node_scores(run, w.name, "final method", z, w, settings.k, 1, f"K={k},beta={beta},r={r}")
    return run.frame()


def scaling(spark, sizes=(500, 1000, 2000), settings=em.Settings(k=8, rank=8, b=32, power=1)) -> DataFrame:
    """Seconds of extension and embedding on random hypergraphs of three nodes each; the slope of log time on log size."""
    run = Run(spark, "exp_scale")
    logs = []
    for n in sizes:
        w = graphs.synthetic(spark, n, q=20)
        began = time.time()
        near = knn.knn_ivf(graphs.dense_attributes(w), 5)
        h = hg.extend(w.graph, cut(near), w.nodes)
        h = hg.Hypergraph(cut(h.inc), cut(h.edges))
        run.put("synthetic", "extension", "seconds", time.time() - began, n)
        em.embed_sketch(h, settings).vectors("node").agg(F.count("*")).first()
        run.put("synthetic", "final method", "seconds", time.time() - began, n)
        run.put("synthetic", "incidence rows", "rows", h.inc.count(), n)
        logs.append((np.log(n), np.log(time.time() - began)))
    x, y = np.array(logs).T
    run.put("synthetic", "final method", "log_slope", np.polyfit(x, y, 1)[0])
    return run.frame()


def running_time(spark, w: graphs.Workload, settings=SMALL) -> DataFrame:
    """Seconds of each method on one graph."""
    run = Run(spark, "exp_time")
    began = time.time()
    x = extended(w)
    run.put(w.name, "extension", "seconds", time.time() - began)
    for name, make in {
        "final method": lambda: em.embed_sketch(x, settings).vectors("node"),
        "base method": lambda: em.embed_dense(x, settings.k),
        "dense factorisation": lambda: bl.base_dense_mf(w.graph, settings.k),
        "scalable factorisation": lambda: bl.base_sparse_mf(w.graph, settings.k),
    }.items():
        began = time.time()
        make().agg(F.count("*")).first()
        run.put(w.name, name, "seconds", time.time() - began)
    return run.frame()


#: Rows of the similarity up to which they are columns of a table.
COLUMNS = 512


def two_view_extended(w: graphs.Workload, x: hg.Hypergraph, dense: DataFrame, q: int, k: int) -> DataFrame:
    """The two-view learner with rows of the node similarity appended to the attributes."""
    if x.inc.select("vid").distinct().count() > COLUMNS:
        return bl.base_two_view_rows(w.graph, dense, q, em.stored_similarity(x), k)
    ids, sim = em.dense_similarity(x)
    extra = lr.to_frame(w.graph.inc.sparkSession, ids, sim)
    plus = dense.join(extra.select(F.col("id").alias("vid"), F.col("vec").alias("s")), "vid").select("vid", F.concat("attrs", "s").alias("attrs"))
    return bl.base_two_view(w.graph, plus, q + len(ids), k)


def extended_baselines(spark, w: graphs.Workload, k: int = 16) -> DataFrame:
    """Compared methods with and without this package's similarity in them."""
    run = Run(spark, "exp_extended_baselines")
    x = extended(w)
    dense = cut(graphs.dense_attributes(w))
    q = len(dense.first()["attrs"])
    for method, make in {
        "walk skip-gram": lambda: bl.base_walk_skipgram(w.graph, k), "walk skip-gram, restart walk": lambda: bl.base_walk_skipgram(x, k, restart=0.1),
        "two view": lambda: bl.base_two_view(w.graph, dense, q, k), "two view, similarity rows": lambda: two_view_extended(w, x, dense, q, k),
        "final method": lambda: em.embed_sketch(x, SMALL, ("node",)).vectors("node"),
    }.items():
        node_scores(run, w.name, method, make(), w, k, 2)
    return run.frame()


def repeat_average(results: DataFrame) -> DataFrame:
    """Mean and spread over splits."""
    return results.groupBy("experiment", "graph", "method", "param", "metric").agg(F.avg("value").alias("mean"), F.coalesce(F.stddev("value"), F.lit(0.0)).alias("spread"), F.count("*").alias("runs"))


def gain(results: DataFrame, method: str, against: str) -> DataFrame:
    """Difference in points and ratio of two methods' means, per graph and metric."""
    m = repeat_average(results)
    a, b = (m.where(F.col("method") == x).select("graph", "metric", "param", F.col("mean").alias(n)) for x, n in ((method, "a"), (against, "b")))
    return a.join(b, ["graph", "metric", "param"]).select("graph", "metric", "param", (F.col("a") - F.col("b")).alias("difference"), (F.col("b") / F.col("a")).alias("ratio"))
