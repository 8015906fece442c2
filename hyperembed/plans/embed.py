"""Both embedding methods, fold-in of new rows, and saving a model."""

from __future__ import annotations

import json
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession, functions as F

from ..operators import lowrank as lr, rowfiles as rf
from ..operators.blocks import gram, times
from ..operators.hypergraph import Hypergraph
from ..session import cut, work_folder


@dataclass(frozen=True)
class Settings:
    k: int = 32
    rank: int = 32
    alpha: float = 0.1
    steps: int = 10
    tau: int = 3
    b: int = 128
    c: int = 10
    seed: int = 1
    negative: str = "drop"
    svd: str = "block"
    oversample: int = 10
    power: int = 2


@dataclass
class Side:
    """What is needed to place a new row on one side: factor scale, sketch seed, coefficients and the last matrix."""

    theta: np.ndarray
    scale: float
    matrix: np.ndarray
    eigenvalues: np.ndarray
    vectors: DataFrame = field(repr=False)


@dataclass
class Model:
    settings: Settings
    svd: lr.Svd
    vol: float
    sides: dict[str, Side]

    def vectors(self, side: str = "node") -> DataFrame:
        """(id, vec array<float>)."""
        return self.sides[side].vectors.select("id", F.col("vec").cast("array<float>").alias("vec"))


def _svd(h: Hypergraph, s: Settings, edges: bool) -> lr.Svd:
    if s.svd == "full":
        return lr.svd_full(h, s.rank)
    if s.svd == "lanczos":
        return lr.svd_lanczos(h, s.rank, seed=s.seed)
    return lr.svd_block(h, s.rank, s.oversample, s.power, s.seed, edges=edges)


def embed_sketch(h: Hypergraph, settings: Settings = Settings(), sides: tuple[str, ...] = ("node", "edge"), tail: str = "sketch") -> Model:
    """The linear-cost method on an extended hypergraph: one SVD for both sides, then factor, sketch, fit and eigenpairs.

    tail 'exact' forms the truncated logarithm of all dot products on the driver, for small inputs, to tell the error of the
    SVD from that of the sketch.
    """
    from ..operators.hypergraph import volume, weighed

    h = weighed(h)
    svd = _svd(h, settings, "edge" in sides)
    out = {}
    for side in sides:
        f = cut(lr.factor(svd, h, settings.alpha, settings.steps, side), "factor")
        if tail == "exact":
            out[side] = _exact_tail(f, settings)
            continue
        theta, top = lr.fit_poly(f, settings.tau, settings.c)
        # Rows are divided by the root of the largest dot product: powers of the sketch stay near 1.
        scale = float(np.sqrt(top))
        # Far wider than the factor: made again for each of the two passes, not written.
        y = lr.tensor_sketch(f, svd.rank, settings.tau, settings.b, scale=scale)
        width = 1 + settings.tau * settings.b
        diagonal = lr.theta_diagonal(theta * top ** np.arange(settings.tau + 1), settings.b)
        lam, m = lr.eig_gram(y, diagonal, width, settings.k, settings.negative)
        out[side] = Side(theta, scale, m, lam, cut(times(y, m), "vectors"))
    return Model(settings, svd, float(volume(h).first()["vol"]), out)


def _exact_tail(f: DataFrame, s: Settings, most: int = 5000) -> Side:
    rows = f.orderBy("id").limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError(f"the exact tail takes at most {most} rows")
    ids, x = [r["id"] for r in rows], np.array([r["vec"] for r in rows])
    z, lam = symmetric_embedding(np.log(np.maximum(x @ x.T, 1.0)), s.k, s.negative)
    return Side(np.zeros(0), 1.0, np.zeros((0, 0)), lam, lr.to_frame(f.sparkSession, ids, z))


def symmetric_embedding(sim: np.ndarray, k: int, negative: str = "drop") -> tuple[np.ndarray, np.ndarray]:
    """(Z, eigenvalues): k leading eigenpairs of a symmetric matrix, Z = vectors times root of the values, padded to k columns."""
    lam, e = np.linalg.eigh((sim + sim.T) / 2)
    order = np.argsort(-(lam if negative == "drop" else np.abs(lam)), kind="stable")[:k]
    lam, e = lam[order], e[:, order]
    if negative == "drop":
        lam, e = lam[lam > 0], e[:, lam > 0]
    z = lr.canonical(e * np.sqrt(np.abs(lam)), e)
    return (z if z.shape[1] == k else np.concatenate([z, np.zeros((len(z), k - z.shape[1]))], axis=1)), lam


def dense_similarity(h: Hypergraph, alpha: float = 0.1, steps: int = 10, side: str = "node", most: int = 5000):
    """(ids, similarity matrix) on the driver, given hyperedges only on the hyperedge side; refuses inputs over `most`."""
    p = h.weighted.select("eid", "vid", "gamma", "w")
    sizes = p.agg(F.count_distinct("vid"), F.count_distinct("eid")).first()
    if (sizes[0] if side == "node" else sizes[1]) > most:
        raise ValueError(f"{sizes[0]} nodes and {sizes[1]} hyperedges are too many for the dense method (limit {most})")
    p = p.toPandas()
    vids, eids = np.unique(p["vid"]), np.unique(p["eid"])
    g = np.zeros((len(eids), len(vids)))
    w = np.zeros(len(eids))
    at = np.searchsorted(eids, p["eid"])
    g[at, np.searchsorted(vids, p["vid"])] = p["gamma"]
    w[at] = p["w"]
    d, delta = w @ g, g.sum(1)
    up, down = (g * w[:, None] / d).T, g / delta[:, None]  # node to hyperedge, hyperedge to node
    step, mass, ids = (up @ down, d, vids) if side == "node" else (down @ up, w * delta, eids)
    x = eye = np.eye(len(ids))
    for _ in range(steps):
        x = alpha * eye + (1 - alpha) * x @ step
    sim = np.log(np.maximum(x * mass.sum() / mass, 1.0))
    if side == "edge":
        given = {r["eid"] for r in h.edges.where("kind = 'S'").select("eid").collect()}
        keep = np.array([e in given for e in ids.tolist()], bool)
        ids, sim = ids[keep], sim[np.ix_(keep, keep)]
    return ids, sim


def stored_similarity(h: Hypergraph, alpha: float = 0.1, steps: int = 10, side: str = "node") -> rf.RowFiles:
    """The matrix of `dense_similarity` for any number of rows, made by executors and kept in files."""
    chain = rf.walk_chain(h, side)
    keep = rf.given_places(h, chain.ids) if side == "edge" else None
    return rf.similarity_rows(h.inc.sparkSession, chain, rf.restart_powers(alpha, steps), keep=keep)


def similarity_error(h: Hypergraph, z: DataFrame, alpha: float = 0.1, steps: int = 10) -> float:
    """Mean over all pairs of nodes of the distance from similarity to the dot product of (id, vec), both divided by the mean of their own diagonal."""
    chain = rf.walk_chain(h, "node")
    t = z.select("id", F.col("vec").cast("array<double>").alias("vec")).toArrow()
    width = len(t.column("vec")[0]) if len(t) else 0
    vectors = np.zeros((len(chain.ids), width))
    known = np.isin(t.column("id").to_numpy(), chain.ids)
    vectors[np.searchsorted(chain.ids, t.column("id").to_numpy()[known])] = t.column("vec").combine_chunks().flatten().to_numpy().reshape(-1, width)[known]
    return rf.similarity_error(h.inc.sparkSession, chain, rf.restart_powers(alpha, steps), vectors)


def embed_dense(h: Hypergraph, k: int = 32, alpha: float = 0.1, steps: int = 10, side: str = "node", most: int | None = None, negative: str = "drop") -> DataFrame:
    """The base method: the full similarity, then its leading eigenpairs. (id, vec). With `most`, larger inputs are refused."""
    spark = h.inc.sparkSession
    if most is None and not rf.fits_driver(h, side):
        rows = stored_similarity(h, alpha, steps, side)
        return lr.to_frame(spark, rows.ids, rf.embedding(rows.__matmul__, rows.ids, k, negative))
    ids, sim = dense_similarity(h, alpha, steps, side, most or rf.DENSE)
    return lr.to_frame(spark, ids, symmetric_embedding(sim, k, negative)[0])


def fold_in(model: Model, rows: DataFrame, side: str = "edge") -> DataFrame:
    """(id, vec) of new hyperedges (or nodes) from their normalised memberships (id, other, ell, mass).

    `mass` is w * delta of a new hyperedge, or d of a new node. The new row is projected on the other side's singular
    vectors, scaled as in `factor`, sketched and multiplied by the model's last matrix: no pass over the old data.
    """
    s, svd, m = model.settings, model.svd, model.sides[side]
    base = svd.v if side == "edge" else svd.u
    r = svd.rank
    parts = rows.join(base.select(F.col("id").alias("other"), "vec"), "other")
    sums = parts.groupBy("id").agg(F.first("mass").alias("mass"), *[F.sum(F.col("ell") * F.col("vec")[i]).alias(f"s{i}") for i in range(r)])
    phi = np.sqrt(lr.walk_filter(svd.sigma, s.alpha, s.steps) * model.vol) / svd.sigma
    f = sums.select("id", F.array(*[F.col(f"s{i}") * float(phi[i]) / F.sqrt("mass") for i in range(r)]).alias("vec"))
    return times(lr.tensor_sketch(f, r, s.tau, s.b, scale=m.scale), m.matrix)


def save_model(model: Model, path: str) -> None:
    """Parquet for vector tables, one JSON row for the small matrices."""
    spark = model.svd.v.sparkSession
    model.svd.u.write.mode("overwrite").parquet(f"{path}/u")
    model.svd.v.write.mode("overwrite").parquet(f"{path}/v")
    small = {"settings": model.settings.__dict__, "sigma": model.svd.sigma.tolist(), "vol": model.vol, "sides": {}}
    for name, side in model.sides.items():
        side.vectors.write.mode("overwrite").parquet(f"{path}/vectors_{name}")
        small["sides"][name] = {"theta": side.theta.tolist(), "scale": side.scale, "matrix": side.matrix.tolist(), "eigenvalues": side.eigenvalues.tolist()}
    spark.createDataFrame([(json.dumps(small),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/small")


def load_model(spark: SparkSession, path: str) -> Model:
    small = json.loads(spark.read.text(f"{path}/small").first()[0])
    read = lambda name: spark.read.parquet(f"{path}/{name}")
    sides = {n: Side(np.array(x["theta"]), x["scale"], np.array(x["matrix"]), np.array(x["eigenvalues"]), read(f"vectors_{n}")) for n, x in small["sides"].items()}
    return Model(Settings(**small["settings"]), lr.Svd(read("u"), np.array(small["sigma"]), read("v")), small["vol"], sides)


def default_model_path(spark: SparkSession, name: str) -> str:
    return f"{work_folder(spark)}/models/{name}"

