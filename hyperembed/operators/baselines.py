"""Compared methods. Those marked stand-in are deterministic members of the named family, not the published systems.

All take an extended hypergraph or a given one and return (id, vec array<double>) of `k` columns.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window, functions as F

from ..functions.vectors import mix
from ..session import cut
from . import lowrank as lr, panels, rowfiles as rf, walkers
from .blocks import gram, half_step, times
from .hypergraph import Hypergraph, edge_degrees, mean_pool, node_degrees, normalise


def _pca(vecs: DataFrame, width: int, k: int) -> DataFrame:
    """Leading directions of the rows, by their Gram matrix; padded to k columns."""
    d, e = np.linalg.eigh(gram(vecs, width))
    m = e[:, np.argsort(-d)[: min(k, width)]]
    if m.shape[1] < k:
        m = np.concatenate([m, np.zeros((width, k - m.shape[1]))], axis=1)
    return times(vecs, m)


def _attrs(dense: DataFrame) -> DataFrame:
    return dense.select(F.col("vid").alias("id"), F.col("attrs").cast("array<double>").alias("vec"))


def walk_corpus(h: Hypergraph, walks: int = 4, length: int = 12, p: float = 0.5, seed: int = 51, restart: float | None = None) -> DataFrame:
    """(start, walk, step, vid): hash-seeded walks over hyperedges; with chance `p` a step stays in its hyperedge, else it changes to another of its node.

    With `restart` the walk goes back to its start with that chance instead (the restart walk of this package).
    """
    inc = cut(h.inc.select("eid", "vid"), "inc")
    size = inc.count()
    if size > walkers.JOINED:
        steps = walkers.Walkers(inc, size, p, seed, restart)
        places = inc.select("vid").distinct().select(F.col("vid").alias("start"), F.explode(F.sequence(F.lit(0), F.lit(walks - 1))).alias("walk"), "vid", F.lit(0).cast("long").alias("eid"), F.lit(False).alias("inside"))
        whole = None
        for t in range(length):
            places = cut(steps.step(places, t) if t else places, "walks")
            here = places.select("start", "walk", F.lit(t).alias("step"), "vid")
            whole = here if whole is None else whole.unionByName(here)
        return whole
    by_edge = cut(inc.groupBy("eid").agg(F.sort_array(F.collect_list("vid")).alias("members")), "members")
    by_node = cut(inc.groupBy("vid").agg(F.sort_array(F.collect_list("eid")).alias("edges")), "edges")
    at = inc.select("vid").distinct().select(F.col("vid").alias("start"), F.explode(F.sequence(F.lit(0), F.lit(walks - 1))).alias("walk"), "vid", F.lit(None).cast("long").alias("eid"))
    out = [at.select("start", "walk", F.lit(0).alias("step"), "vid")]
    key = F.col("start") * 131 + F.col("walk")
    for t in range(1, length):
        chance = lambda s: F.pmod(mix(key, t * 7 + s, seed), F.lit(1_000_000)) / 1_000_000  # noqa: E731, B023
        pick = lambda arr, s: F.element_at(arr, (F.pmod(mix(key, t * 7 + s, seed), F.size(arr)) + 1).cast("int"))  # noqa: E731, B023
        x = at.join(by_node, "vid").withColumn("eid", F.when(F.col("eid").isNotNull() & (chance(1) < p), F.col("eid")).otherwise(pick(F.col("edges"), 2)))
        x = x.join(by_edge, "eid").withColumn("vid", pick(F.col("members"), 3))
        if restart is not None:
            back = chance(4) < restart
            x = x.withColumn("vid", F.when(back, F.col("start")).otherwise(F.col("vid"))).withColumn("eid", F.when(back, None).otherwise(F.col("eid")))
        at = cut(x.select("start", "walk", "vid", "eid"), "walks")
        out.append(at.select("start", "walk", F.lit(t).alias("step"), "vid"))
    whole = out[0]
    for o in out[1:]:
        whole = whole.unionByName(o)
    return whole


def base_walk_skipgram(h: Hypergraph, k: int = 32, walks: int = 4, length: int = 12, p: float = 0.5, restart: float | None = None, seed: int = 51) -> DataFrame:
    """Hypergraph walks and skip-gram (full method of the family); with `restart`, driven by the restart walk."""
    from pyspark.ml.feature import Word2Vec
    from pyspark.ml.functions import vector_to_array

    steps = walk_corpus(h, walks, length, p, seed, restart)
    texts = steps.groupBy("start", "walk").agg(F.transform(F.sort_array(F.collect_list(F.struct("step", "vid"))), lambda x: x["vid"].cast("string")).alias("text"))
    model = Word2Vec(vectorSize=k, minCount=1, windowSize=4, seed=seed, maxIter=2, numPartitions=4, inputCol="text", outputCol="v").fit(texts)
    return model.getVectors().select(F.col("word").cast("long").alias("id"), vector_to_array("vector").alias("vec"))


def _smooth(h: Hypergraph, vecs: DataFrame, width: int, hops: int) -> DataFrame:
    """Vectors averaged over hyperedges and back, `hops` times."""
    rows = cut(h.weighted.select("eid", "vid", "gamma", "w"), "memberships")
    wide = panels.smooth(rows, vecs, width, hops)
    if wide is not None:
        return wide
    delta, d = rows.groupBy("eid").agg(F.sum("gamma").alias("delta")), rows.groupBy("vid").agg(F.sum(F.col("w") * F.col("gamma")).alias("d"))
    r = cut(rows.join(delta, "eid").join(d, "vid").select("eid", "vid", (F.col("w") * F.col("gamma") / F.col("d")).alias("up"), (F.col("gamma") / F.col("delta")).alias("down")), "rates")
    for _ in range(hops):
        mid = half_step(r.select("eid", "vid", F.col("down").alias("ell")), vecs, width, "vid", "eid", merge=True)
        vecs = cut(half_step(r.select("eid", "vid", F.col("up").alias("ell")), mid, width, "eid", "vid", merge=True), "smooth")
    return vecs


def base_linear_filter(h: Hypergraph, dense: DataFrame, width: int, k: int = 32, hops: int = 2) -> DataFrame:
    """Stand-in: attributes smoothed over the clique graph in two half steps, then PCA."""
    return _pca(_smooth(h, _attrs(dense), width, hops), width, k)


def base_affinity(h: Hypergraph, dense: DataFrame, width: int, k: int = 32, hops: int = 3) -> DataFrame:
    """Stand-in: log of forward affinity of nodes and attributes over walks, then its leading directions."""
    x = _smooth(h, _attrs(dense), width, hops)
    return _pca(x.select("id", F.transform("vec", lambda v: F.log1p(F.greatest(v, F.lit(0.0)) * 100)).alias("vec")), width, k)


def base_node_attr_graph(h: Hypergraph, dense: DataFrame, width: int, k: int = 32) -> DataFrame:
    """Stand-in: attributes as extra neighbours of each node: raw and smoothed attributes side by side, then PCA."""
    raw = _attrs(dense)
    both = raw.join(_smooth(h, raw, width, 1).withColumnRenamed("vec", "s"), "id", "left").select("id", F.concat("vec", F.coalesce("s", F.array_repeat(F.lit(0.0), width))).alias("vec"))
    return _pca(both, 2 * width, k)


def base_anchor(h: Hypergraph, k: int = 32, anchors: int = 64, hops: int = 2, seed: int = 61) -> DataFrame:
    """Stand-in: chances of walking from anchors (hash-chosen nodes) to each node, then PCA."""
    nodes = h.inc.select(F.col("vid").alias("id")).distinct()
    chosen = [r["id"] for r in nodes.orderBy(mix(F.col("id"), 0, seed), "id").limit(anchors).collect()]
    start = nodes.select("id", F.array(*[F.when(F.col("id") == a, 1.0).otherwise(0.0) for a in chosen]).alias("vec"))
    return _pca(_smooth(h, start, len(chosen), hops), len(chosen), k)


def base_als(h: Hypergraph, k: int = 32, side: str = "node", seed: int = 71) -> DataFrame:
    """Stand-in: implicit matrix factorisation of the incidence; vectors of both sides. Ids are numbered by rank for the learner."""
    from pyspark.ml.recommendation import ALS

    rank = lambda c: h.inc.select(c).distinct().select(c, (F.row_number().over(Window.orderBy(c)) - 1).cast("int").alias(f"{c}_n"))
    v, e = rank("vid"), rank("eid")
    rows = h.inc.join(v, "vid").join(e, "eid").select("vid_n", "eid_n", "gamma")
    model = ALS(rank=k, maxIter=4, implicitPrefs=True, userCol="eid_n", itemCol="vid_n", ratingCol="gamma", seed=seed).fit(rows)
    f, names, c = (model.itemFactors, v, "vid") if side == "node" else (model.userFactors, e, "eid")
    return f.join(names, f["id"] == names[f"{c}_n"]).select(F.col(c).alias("id"), F.col("features").cast("array<double>").alias("vec"))


def base_virtual_label(h: Hypergraph, dense: DataFrame, width: int, k: int = 32, clusters: int = 16, seed: int = 81) -> DataFrame:
    """Stand-in: k-means labels of the attributes spread over hyperedges; the spread shares are the vector."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    rows = _attrs(dense).withColumn("f", array_to_vector("vec"))
    model = KMeans(k=clusters, seed=seed, maxIter=6, featuresCol="f", predictionCol="c").fit(rows)
    hot = model.transform(rows).select("id", F.array(*[(F.col("c") == i).cast("double") for i in range(clusters)]).alias("vec"))
    return _pca(_smooth(h, hot, clusters, 1), clusters, k)


def base_two_view(h: Hypergraph, dense: DataFrame, width: int, k: int = 32, drop: int = 20, seed: int = 91) -> DataFrame:
    """Stand-in: two hash-dropped views of the smoothed attributes; directions that the views share most (their cross-correlation)."""
    x = _attrs(dense)
    views = []
    for s in (seed, seed + 7):
        part = Hypergraph(h.inc.where(F.pmod(mix(F.col("eid"), F.col("vid"), s), F.lit(100)) >= drop), h.edges)
        views.append(_smooth(part, x, width, 1))
    both = views[0].join(views[1].withColumnRenamed("vec", "o"), "id").select("id", F.concat("vec", "o").alias("vec"))
    g = gram(both, 2 * width)
    u, _, _ = np.linalg.svd(g[:width, width:])
    m = u[:, : min(k, width)]
    out = times(_smooth(h, x, width, 1), m)
    return out if m.shape[1] == k else out.select("id", F.concat("vec", F.array_repeat(F.lit(0.0), k - m.shape[1])).alias("vec"))


def base_two_view_rows(h: Hypergraph, dense: DataFrame, width: int, rows: rf.RowFiles, k: int = 32, drop: int = 20, seed: int = 91) -> DataFrame:
    """`base_two_view` with the rows of a similarity appended to the attributes, for any number of rows: the views' cross-correlation is not
    formed, only multiplied with blocks."""
    ids, n = rows.ids, len(rows.ids)
    t = _attrs(dense).toArrow()
    at = t.column("id").to_numpy()
    known = np.isin(at, ids)
    attrs, has = np.zeros((n, width)), np.zeros((n, 1))
    here = np.searchsorted(ids, at[known])
    attrs[here], has[here] = t.column("vec").combine_chunks().flatten().to_numpy().reshape(-1, width)[known], 1
    x = lambda z: has * (attrs @ z[:width] + rows @ z[width:])
    turned = lambda y: np.vstack([attrs.T @ y, rows @ (has * y)])
    one, two = (rf.smoothing(Hypergraph(h.inc.where(F.pmod(mix(F.col("eid"), F.col("vid"), s), F.lit(100)) >= drop), h.edges), ids) for s in (seed, seed + 7))

    def both(z):
        """The correlation on the right half, its transpose on the left half."""
        a, b = np.split(z, 2)
        c = a.shape[1]
        y = x(np.hstack([b, a]))
        y = np.hstack([rf.through(one[0], one[2], rf.through(two[0], two[1], y[:, :c])), rf.through(two[0], two[2], rf.through(one[0], one[1], y[:, c:]))])
        y = turned(y)
        return np.vstack([y[:, :c], y[:, c:]])

    _, pairs = rf.leading_pairs(both, 2 * (width + n), min(k, width + n))
    u = pairs[: width + n] * np.sqrt(2)
    u = lr.canonical(u, u)
    places, forth, _ = rf.smoothing(h, ids)
    out = rf.through(places, forth, x(u))[places]
    return lr.to_frame(h.inc.sparkSession, ids[places], np.hstack([out, np.zeros((len(out), k - out.shape[1]))]))


def leave_one_out_mean(h: Hypergraph, vecs: DataFrame, width: int) -> DataFrame:
    """(eid, vid, vec): mean of a hyperedge's other members' vectors."""
    rows = h.inc.select("eid", "vid").join(vecs.withColumnRenamed("id", "vid"), "vid")
    s = rows.groupBy("eid").agg(F.count("*").alias("n"), *[F.sum(F.col("vec")[i]).alias(f"s{i}") for i in range(width)]).where("n > 1")
    return rows.join(s, "eid").select("eid", "vid", F.array(*[(F.col(f"s{i}") - F.col("vec")[i]) / (F.col("n") - 1) for i in range(width)]).alias("vec"))


def base_fill(h: Hypergraph, dense: DataFrame, width: int, k: int = 32, ridge: float = 1e-2) -> DataFrame:
    """Stand-in: ridge map from the mean of the other members to a member; nodes are averages of their predictions."""
    x = cut(_attrs(dense), "attrs")
    rest = cut(leave_one_out_mean(h, x, width), "rest")
    both = rest.join(x.select(F.col("id").alias("vid"), F.col("vec").alias("own")), "vid").select(F.col("vid").alias("id"), F.concat("vec", "own").alias("vec"))
    g = gram(both, 2 * width)
    beta = np.linalg.solve(g[:width, :width] + ridge * max(np.trace(g[:width, :width]) / width, 1e-12) * np.eye(width), g[:width, width:])
    u = np.linalg.svd(beta)[0][:, : min(k, width)]
    means = rest.groupBy(F.col("vid").alias("id")).agg(*[F.avg(F.col("vec")[i]).alias(f"s{i}") for i in range(width)])
    out = times(means.select("id", F.array(*[F.col(f"s{i}") for i in range(width)]).alias("vec")), u)
    return out if u.shape[1] == k else out.select("id", F.concat("vec", F.array_repeat(F.lit(0.0), k - u.shape[1])).alias("vec"))


def clique_adjacency(h: Hypergraph, most: int = 5000):
    """(ids, weights) of the clique graph on the driver, for small inputs."""
    vids, _, _ = lr.dense_incidence(h, most)
    p = h.weighted.toPandas()
    eids = np.unique(p["eid"])
    g = np.zeros((len(eids), len(vids)))
    at = np.searchsorted(eids, p["eid"])
    g[at, np.searchsorted(vids, p["vid"])] = p["gamma"]
    w = np.zeros(len(eids))
    w[at] = p["w"]
    a = g.T @ (g * w[:, None])
    np.fill_diagonal(a, 0)
    return vids, a


def base_dense_mf(h: Hypergraph, k: int = 32, window: int = 5, negative: float = 1.0) -> DataFrame:
    """Full method of the family: log of the averaged powers of the clique graph's walk, then its leading eigenpairs. Quadratic in nodes."""
    from ..plans.embed import symmetric_embedding

    if not rf.fits_driver(h):
        rows = rf.similarity_rows(h.inc.sparkSession, rf.clique_chain(h), [0.0] + [1 / window] * window, negative)
        return lr.to_frame(h.inc.sparkSession, rows.ids, rf.embedding(rows.__matmul__, rows.ids, k))
    ids, a = clique_adjacency(h, rf.ENTRIES)
    d = np.maximum(a.sum(1), 1e-12)
    p = a / d[:, None]
    power, total = np.eye(len(ids)), np.zeros_like(a)
    for _ in range(window):
        power = power @ p
        total += power
    m = np.log(np.maximum(total / window * d.sum() / d / negative, 1.0))
    return lr.to_frame(h.inc.sparkSession, ids, symmetric_embedding(m, k)[0])


def base_sparse_mf(h: Hypergraph, k: int = 32, walks: int = 8, length: int = 6, seed: int = 51) -> DataFrame:
    """Walk pairs counted, truncated log of their lift, block SVD of that sparse table."""
    steps = cut(walk_corpus(h, walks, length, 0.5, seed), "corpus")
    pairs = steps.alias("a").where("step = 0").join(steps.alias("b").where("step > 0"), ["start", "walk"]).select(F.col("start").alias("i"), F.col("b.vid").alias("j"))
    both = pairs.unionByName(pairs.select(F.col("j").alias("i"), F.col("i").alias("j")))
    n = both.groupBy("i", "j").agg(F.count("*").alias("n"))
    ri, total = both.groupBy("i").agg(F.count("*").alias("ni")), both.agg(F.count("*").alias("t"))
    lift = n.join(ri, "i").join(ri.withColumnsRenamed({"i": "j", "ni": "nj"}), "j").crossJoin(F.broadcast(total))
    table = lift.select(F.col("i").alias("eid"), F.col("j").alias("vid"), F.log(F.greatest(F.lit(1.0), F.col("n") * F.col("t") / (F.col("ni") * F.col("nj")))).alias("ell")).where("ell > 0")
    table = cut(table, "lift")
    ids = table.select(F.col("vid").alias("id")).distinct()
    width = min(k + 8, ids.count())
    v = lr.start_block(ids, width, seed)
    for _ in range(3):
        v, width = lr._orthonormal(cut(half_step(table, v, width, "vid", "eid"), "block"), width)
        v = cut(v, "block")
    d, e = np.linalg.eigh(gram(cut(half_step(table, v, width, "vid", "eid"), "block"), width))
    order = np.argsort(-d)[: min(k, width)]
    m = e[:, order] * np.maximum(d[order], 0) ** 0.25
    if m.shape[1] < k:
        m = np.concatenate([m, np.zeros((width, k - m.shape[1]))], axis=1)
    return times(v, m)


def base_spectral(h: Hypergraph, k: int = 32) -> DataFrame:
    """Leading right singular vectors of the given hypergraph's normalised incidence (its Laplacian's spectrum)."""
    svd = lr.svd_block(h, k)
    return svd.v if svd.rank == k else svd.v.select("id", F.concat("vec", F.array_repeat(F.lit(0.0), k - svd.rank)).alias("vec"))


def clique_rates(h: Hypergraph, stay: DataFrame | None = None) -> DataFrame:
    """(eid, own, vid, up, down): the clique graph's walk without its table of pairs, as two half steps.

    From a node to its hyperedges by w gamma / d and on to all members by gamma; `own` rows, one a node, take the way back to the
    node itself off again. d is the node's degree in the clique graph. Hyperedges of one member have no pairs. Ids of `stay`
    without a neighbour get a row of rate zero.
    """
    sums = h.inc.groupBy("eid").agg(F.sum("gamma").alias("delta"), F.count("*").alias("size")).where("size > 1")
    rows = h.weighted.join(sums, "eid")
    loop = F.sum(F.col("w") * F.col("gamma") * F.col("gamma"))
    d = rows.groupBy("vid").agg(F.sum(F.col("w") * F.col("gamma") * (F.col("delta") - F.col("gamma"))).alias("d"), loop.alias("loop"))
    given = rows.join(d, "vid").select("eid", F.lit(False).alias("own"), "vid", (F.col("w") * F.col("gamma") / F.col("d")).alias("up"), F.col("gamma").alias("down"))
    back = d.select("vid", (-F.col("loop") / F.col("d")).alias("up"))
    if stay is not None:
        back = back.join(stay.select(F.col("id").alias("vid")).distinct(), "vid", "full").select("vid", F.coalesce("up", F.lit(0.0)).alias("up"))
    return given.unionByName(back.select(F.col("vid").alias("eid"), F.lit(True).alias("own"), "vid", "up", F.lit(1.0).alias("down")))


def clique_step(x: DataFrame, rates: DataFrame) -> DataFrame:
    """(source, id, p) one step further; nodes that the walk has left come out too, with a p of zero up to rounding."""
    half = x.join(rates.select("eid", "own", F.col("vid").alias("id"), "up"), "id").groupBy("source", "eid", "own").agg(F.sum(F.col("p") * F.col("up")).alias("p"))
    full = half.join(rates.select("eid", "own", F.col("vid").alias("id"), "down"), ["eid", "own"])
    return full.groupBy("source", "id").agg(F.sum(F.col("p") * F.col("down")).alias("p"))


#: Rates that a worker may hold, about 32 bytes each, and rows that it makes at once.
RATES, ROWS_AT_ONCE = 700_000, 4_000_000


def _walk_in_workers(rates: DataFrame, sources: DataFrame, alpha: float, steps: int, average: bool) -> DataFrame:
    """The walk from each source with all rates at hand: no row is sent between steps."""
    import pyarrow as pa

    t = rates.select("eid", "own", "vid", "up", "down").toPandas()
    vids, v = np.unique(t["vid"].to_numpy(), return_inverse=True)
    e = np.unique(t["eid"].to_numpy(), return_inverse=True)[1] * 2 + t["own"].to_numpy()
    n, m = len(vids), int(e.max(initial=-1)) + 1

    def grouped(at, size, to, weight):
        order = np.lexsort((to, at))
        return np.r_[0, np.cumsum(np.bincount(at, minlength=size))], to[order].astype(np.int32), weight[order]

    out, back = grouped(v, n, e, t["up"].to_numpy()), grouped(e, m, v, t["down"].to_numpy())
    portion = int(min(64, max(1, ROWS_AT_ONCE // max(1, len(t)))))

    def hop(row, at, p, table, width):
        first, to, weight = table
        count = first[at + 1] - first[at]
        place = np.repeat(first[at] - np.cumsum(count) + count, count) + np.arange(count.sum())
        key, inside = np.unique(np.repeat(row, count) * width + to[place], return_inverse=True)
        return key // width, key % width, np.bincount(inside, np.repeat(p, count) * weight[place], len(key))

    def run(batches):
        for b in batches:
            ids = b.column("id").to_numpy()
            ids = ids[np.isin(ids, vids)]
            for i in range(0, len(ids), portion):
                part = ids[i:i + portion]
                home = np.searchsorted(vids, part)
                row, at, p, seen = np.arange(len(part)), home, np.ones(len(part)), []
                for _ in range(steps):
                    row, at, p = hop(*hop(row, at, p, out, m), back, n)
                    p = (1 - alpha) * p + alpha * (home[row] == at)
                    seen.append((row * n + at, p))
                if average:
                    key, inside = np.unique(np.concatenate([k for k, _ in seen]), return_inverse=True)
                    row, at, p = key // n, key % n, np.bincount(inside, np.concatenate([x for _, x in seen]), len(key)) / steps
                for j in range(0, len(p), 100_000):
                    s = slice(j, j + 100_000)
                    yield pa.RecordBatch.from_arrays([pa.array(part[row[s]]), pa.array(vids[at[s]]), pa.array(p[s])], ["source", "id", "p"])

    parts = min(4096, max(8, sources.count() // 256))
    return sources.select("id").repartition(parts, "id").mapInArrow(run, "source long, id long, p double")


def _clique_walk(h: Hypergraph, sources: DataFrame, stay: DataFrame | None, alpha: float, steps: int, average: bool) -> DataFrame:
    rates = cut(clique_rates(h, stay), "clique")
    if rates.count() <= RATES:
        return _walk_in_workers(rates, sources, alpha, steps, average)
    x = start = sources.select(F.col("id").alias("source"), "id", F.lit(1.0).alias("p"))
    # A step brings every node that the walk has been at back, the source among them.
    home = F.when(F.col("source") == F.col("id"), F.lit(float(alpha))).otherwise(F.lit(0.0))
    parts = []
    for _ in range(steps):
        x = cut(clique_step(x, rates).select("source", "id", ((1 - alpha) * F.col("p") + home).alias("p")), "pagerank")
        parts.append(x)
    if not average:
        return x
    whole = start.where("false")
    for part in parts:
        whole = whole.unionByName(part)
    return whole.groupBy("source", "id").agg((F.sum("p") / steps).alias("p"))


def pagerank_pairs(h: Hypergraph, sources: DataFrame, alpha: float = 0.1, steps: int = 10) -> DataFrame:
    """(source, id, p): the restart walk on the clique graph without loops, for contrast with the walk over hyperedges."""
    return _clique_walk(h, sources, sources, alpha, steps, False)


def clique_powers_average(h: Hypergraph, steps: int = 3) -> DataFrame:
    """(source, id, p) from every node: average of the first `steps` (two at least) powers of the clique graph's walk."""
    return _clique_walk(h, h.inc.select(F.col("vid").alias("id")).distinct(), None, 0.0, steps, True)


__all__ = [n for n in dir() if n.startswith(("base_", "walk_", "pagerank", "clique_", "leave_"))] + ["mean_pool", "node_degrees", "edge_degrees", "normalise"]
