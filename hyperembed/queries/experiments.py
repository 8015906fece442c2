"""Experiment workloads and parameter sweeps: SURVEY 2.4 and 2.7."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from ..operators import hypergraph as hg, lowrank as lr, walk as wk
from ..plans import embed as em, experiments as ex
from ..session import cut
from ..sources import graphs
from .common import WORKLOADS, Registry, r, sql_vectors, sql_walk, starts, vectors_graph

_reg = Registry()
add, verdict = _reg.add, _reg.verdict
QUERIES, ORACLES = _reg.queries, _reg.oracles


def _planted(spark):
    return graphs.planted(spark, n=240, edges=420)


def _small_planted(spark):
    return graphs.planted(spark, n=120, edges=200)


SWEEPS = {"K": (2, 10, 20), "beta": (0.1, 1.0, 10.0), "r": (8, 16, 24), "alpha": (0.001, 0.1, 0.3), "tau": (1, 3, 5), "b": (16, 64, 128)}
#: Experiments, with the planted graph of each.
EXPERIMENTS = {
    "exp_node_cls": (ex.node_classification, _planted), "exp_edge_cls": (ex.edge_classification, _planted), "exp_link": (ex.link_prediction, _planted),
    "exp_time": (ex.running_time, _planted), "exp_ablation": (ex.ablation, _planted), "exp_extended_baselines": (ex.extended_baselines, _planted),
    "exp_grid": (lambda spark, w: ex.grid(spark, w, ks=(5,), ranks=(8, 16)), _small_planted),
} | {f"exp_{what}": (lambda spark, w, what=what, values=values: ex.sweep(spark, w, what, values), _small_planted) for what, values in SWEEPS.items()}


def _experiment(name, run, planted):
    """`name` and its runs on the other workloads, each over the whole table."""
    for suffix, source in WORKLOADS.items():
        if suffix == "_planted":
            add(name=name + suffix)(lambda spark, sf_dir: run(spark, planted(spark)))
        else:
            add(name=name + suffix)(lambda spark, sf_dir, source=source: run(spark, source(spark, sf_dir)))


for _name, (_run, _graph) in EXPERIMENTS.items():
    _experiment(_name, _run, _graph)


@add()
def task_node(spark, sf_dir):
    """Node classification on the event hypergraph (its label carries little signal; mechanics only)."""
    return ex.node_classification(spark, graphs.user_days(spark, sf_dir), compared=())


@add()
def task_edge(spark, sf_dir):
    return ex.edge_classification(spark, graphs.user_days(spark, sf_dir))


@add()
def task_link(spark, sf_dir):
    return ex.link_prediction(spark, graphs.user_days(spark, sf_dir))


@add()
def exp_scale(spark, sf_dir):
    return ex.scaling(spark)


@add()
def exp_mae(spark, sf_dir):
    return ex.approximation_error(spark, graphs.user_days(spark, sf_dir))


@verdict("both_methods_close", "full_beats_no_attributes", "full_beats_one_hop", "dense_mae_not_larger")
def reported_shapes(spark, sf_dir):
    """What the experiments should show on the planted graph: order of the methods, not their values."""
    w = _planted(spark)
    mean = {(x["method"], x["metric"]): x["mean"] for x in ex.repeat_average(ex.node_classification(spark, w, compared=())).collect()}
    abl = {(x["method"], x["metric"]): x["mean"] for x in ex.repeat_average(ex.ablation(spark, w)).collect()}
    mae = {(x["method"], x["metric"]): x["value"] for x in ex.approximation_error(spark, w).collect()}
    full = abl["full", "micro_f1"]
    return {"both_methods_close": abs(mean["final method", "micro_f1"] - mean["base method", "micro_f1"]) < 0.15, "full_beats_no_attributes": full >= abl["no attribute hyperedges", "micro_f1"] - 0.02,
            "full_beats_one_hop": full >= abl["one hop", "micro_f1"] - 0.03, "dense_mae_not_larger": mae["base method", "mae_node"] <= mae["final method", "mae_node"] + 1e-9}


#: Results of runs from a table: a customer's segment is the graph, a balance above 5000 or not the method, the key the split.
_RUNS = "SELECT c_mktsegment AS g, CASE WHEN c_acctbal > 5000 THEN 'a' ELSE 'b' END AS m, c_custkey AS s, c_acctbal / 1000 AS v FROM customer"


def _runs(spark, sf_dir):
    value = (F.col("c_acctbal") / 1000).alias("value")
    return graphs.read(spark, sf_dir, "customer").select(F.lit("e").alias("experiment"), F.col("c_mktsegment").alias("graph"), F.when(F.col("c_acctbal") > 5000, "a").otherwise("b").alias("method"),
                                                         F.lit("").alias("param"), F.lit("s").alias("metric"), F.col("c_custkey").alias("split"), value)


@add(f"""WITH t AS ({_RUNS}), k AS (SELECT g, m, avg(v) AS v FROM t GROUP BY g, m)
        SELECT a.g AS graph, round(a.v - b.v, 6) AS difference, round(b.v / a.v, 6) AS ratio FROM k a JOIN k b ON a.g = b.g WHERE a.m = 'a' AND b.m = 'b'""")
def metric_gain(spark, sf_dir):
    return ex.gain(_runs(spark, sf_dir), "a", "b").select("graph", r("difference"), r("ratio"))


@add(f"""WITH t AS ({_RUNS})
        SELECT g AS graph, m AS method, round(avg(v), 6) AS mean, round(coalesce(stddev(v), 0), 6) AS spread, count(*) AS runs FROM t GROUP BY g, m""")
def metric_repeat(spark, sf_dir):
    return ex.repeat_average(_runs(spark, sf_dir)).select("graph", "method", r("mean"), r("spread"), "runs")


# Sweeps that SQL can follow.

_V0 = sql_vectors(1)


@add(" UNION ALL ".join(f"SELECT * FROM (WITH {sql_vectors(k)} SELECT {k} AS k, (SELECT count(*) FROM x) AS nnz, round(w_a, 6) AS w_a FROM wa)" for k in (2, 5, 20)))
def sweep_K(spark, sf_dir):
    out = None
    for k in (2, 5, 20):
        w, near, x = vectors_graph(spark, sf_dir, k)
        row = x.inc.agg(F.count("*").alias("nnz")).crossJoin(hg.balance_weight(w.graph, hg.attribute_hyperedges(near, w.nodes))).select(F.lit(k).alias("k"), "nnz", r("w_a"))
        out = row if out is None else out.union(row)
    return out


@add(" UNION ALL ".join(f"SELECT * FROM (WITH {sql_vectors(10, b)} SELECT {b}::DOUBLE AS beta, round(w_a, 6) AS w_a, round((SELECT sum(w * gamma) FILTER (WHERE kind = 'A') / sum(w * gamma) FROM x), 6) AS attr_share FROM wa)" for b in (0.1, 1.0, 10.0)))
def sweep_beta(spark, sf_dir):
    """Weight of attribute hyperedges, and the share of walk mass that leaves through them."""
    out = None
    for b in (0.1, 1.0, 10.0):
        w, near, x = vectors_graph(spark, sf_dir, beta=b)
        mass = x.weighted.join(x.edges.select("eid", "kind"), "eid").agg((F.sum(F.when(F.col("kind") == "A", F.col("w") * F.col("gamma"))) / F.sum(F.col("w") * F.col("gamma"))).alias("attr_share"))
        row = hg.balance_weight(w.graph, hg.attribute_hyperedges(near, w.nodes), b).crossJoin(mass).select(F.lit(b).alias("beta"), r("w_a"), r("attr_share"))
        out = row if out is None else out.union(row)
    return out


@verdict("error_falls_with_rank")
def sweep_r(spark, sf_dir):
    w = graphs.planted(spark, n=120, edges=200)
    x = ex.extended(w, 5)
    svd = lr.svd_full(x)
    f = np.array(lr.factor(svd, x).orderBy("id").toPandas()["vec"].tolist())
    err = [((f[:, k:] @ f[:, k:].T) ** 2).sum() for k in (8, 16, 32, 64)]
    return {"error_falls_with_rank": all(a >= b for a, b in zip(err, err[1:]))}


@add("""WITH b AS (SELECT c_custkey, least(abs(c_acctbal) / 10000, 1)::DOUBLE AS s FROM customer)
        SELECT alpha, c_custkey, round(list_reduce([1.0::DOUBLE] || list_transform(range(10), lambda t: 0.0::DOUBLE), lambda f, t: alpha + (1 - alpha) * s * s * f), 6) AS phi
        FROM b, (VALUES (0.001::DOUBLE), (0.1), (0.3)) a(alpha)""")
def sweep_alpha(spark, sf_dir):
    """The walk's filter at the customers' balances, for each restart chance."""
    b = graphs.read(spark, sf_dir, "customer").select("c_custkey", F.expr("least(abs(c_acctbal) / 10000, 1)").alias("s"))
    s = b.select("c_custkey", "s", F.explode(F.array(F.lit(0.001), F.lit(0.1), F.lit(0.3))).alias("alpha"))
    phi = F.aggregate(F.sequence(F.lit(1), F.lit(10)), F.lit(1.0), lambda f, t: F.col("alpha") + (1 - F.col("alpha")) * F.col("s") * F.col("s") * f)
    return s.select("alpha", "c_custkey", F.round(phi, 6).alias("phi"))


@verdict("falls_with_b", "fit_improves_with_tau")
def sweep_tau_b(spark, sf_dir):
    """Sketch error falls with width, and the polynomial's misfit with its degree."""
    w = graphs.planted(spark, n=120, edges=200)
    x = ex.extended(w, 5)
    f = cut(lr.factor(lr.svd_full(x, 16), x))
    rows = np.array(f.orderBy("id").toPandas()["vec"].tolist())
    d = rows @ rows.T
    target, fits = np.log(np.maximum(d, 1)), []
    for tau in (1, 3, 5):
        theta, _ = lr.fit_poly(f, tau, 120)
        fits.append(((np.polyval(theta[::-1], d) - target) ** 2).mean())
    theta, top = lr.fit_poly(f, 2, 120)
    want, scaled = sum(t * d**p for p, t in enumerate(theta)), rows / np.sqrt(top)
    errs = []
    for b in (16, 64, 256):
        e = []
        for seed in range(8):
            y = lr.tensor_sketch_rows(scaled, 2, b, lr.sketch_tables(rows.shape[1], 2, b, 7 * seed))
            e.append(((y * lr.theta_diagonal(theta * top ** np.arange(3), b) @ y.T - want) ** 2).mean())
        errs.append(np.mean(e))
    return {"falls_with_b": errs[0] > errs[1] > errs[2], "fit_improves_with_tau": fits[0] >= fits[1] >= fits[2]}


@add("SELECT t AS steps, round(pow(0.9, t), 6) AS tail FROM range(1, 21) r(t)")
def walk_tail(spark, sf_dir):
    """Mass that a walk of so many steps leaves out."""
    return spark.range(1, 21).select(F.col("id").alias("steps"), F.round(F.pow(F.lit(0.9), "id"), 6).alias("tail"))


_S = sql_vectors().replace("x AS (SELECT eid, vid, gamma, 1.0::DOUBLE AS w, 'S' AS kind FROM inc UNION ALL SELECT eid, vid, gamma, w_a, 'A' FROM attr, wa)", "x AS (SELECT eid, vid, gamma, 1.0::DOUBLE AS w, 'S' AS kind FROM inc)")


@add(f"WITH {_S}, {sql_walk('node', 0.1, 4, 'SELECT DISTINCT vid AS id FROM x')} SELECT source, w4.id, round(ln(greatest(p / (d / vol), 1)), 6) AS sim FROM w4 JOIN vdeg ON vid = w4.id, vol")
def ablate_no_attr(spark, sf_dir):
    """Similarity on the given hyperedges alone."""
    x = graphs.vec_buckets(spark, sf_dir).graph
    return wk.similarity(x, starts(x), 0.1, 4).select("source", "id", r("sim"))


@add(f"WITH {sql_vectors()}, {sql_walk('node', 0.1, 1, 'SELECT DISTINCT vid AS id FROM x')} SELECT source, w1.id, round(ln(greatest(p / (d / vol), 1)), 6) AS sim FROM w1 JOIN vdeg ON vid = w1.id, vol")
def ablate_one_hop(spark, sf_dir):
    x = vectors_graph(spark, sf_dir)[2]
    return wk.similarity(x, starts(x), 0.1, 1).select("source", "id", r("sim"))
