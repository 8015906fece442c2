"""Similarities that are too large for one place: executors make their rows and keep them in files, and products with blocks of vectors give
the leading eigenpairs. Nothing is left out: rows hold every entry that is not zero.
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession, functions as F

from ..session import work_folder
from .blocks import VEC, vec_batch
from .hypergraph import Hypergraph

#: Sides up to this size, with incidence matrices up to so many entries, are done as matrices on the driver.
DENSE, ENTRIES = 3000, 20_000_000
#: Rows that a task makes at once; numbers that it gathers at once; numbers that a block of distributions may have.
BLOCK, GATHER, HELD = 64, 250_000, 8_000_000


def fits_driver(h: Hypergraph, side: str = "node") -> bool:
    n, m = h.inc.agg(F.count_distinct("vid"), F.count_distinct("eid")).first()
    return (n if side == "node" else m) <= DENSE and n * m <= ENTRIES


class Product:
    """A sparse matrix without empty rows; rows of equal length lie together, so that a product is a few stacked ones."""

    def __init__(self, at: np.ndarray, size: int, to: np.ndarray, weight: np.ndarray):
        length = np.bincount(at, minlength=size)
        self.order = np.argsort(length, kind="stable")
        rank = np.empty(size, np.int64)
        rank[self.order] = np.arange(size)
        by_row = np.lexsort((to, rank[at]))
        self.to, self.weight = to[by_row].astype(np.int32), weight[by_row].astype(float)
        self.start = np.r_[0, np.cumsum(length[self.order])]

    def __matmul__(self, x: np.ndarray) -> np.ndarray:
        out, width = np.zeros((len(self.order), x.shape[1])), x.shape[1]
        length = np.diff(self.start)
        ends = np.r_[np.flatnonzero(np.diff(length)) + 1, len(length)]
        a = 0
        for b in ends:
            n = int(length[a]) if b > a else 0
            step = max(1, GATHER // max(1, n * width))
            for s in range(a, b if n else a, step):
                e = min(b, s + step)
                part = slice(self.start[s], self.start[e])
                rows = np.take(x, self.to[part], axis=0).reshape(e - s, n, width)
                out[self.order[s:e]] = (self.weight[part].reshape(e - s, 1, n) @ rows)[:, 0]
            a = b
        return out


@dataclass
class Chain:
    """A walk over two halves, turned round: second @ (first @ x) - loop * x is a block of distributions one step later."""

    ids: np.ndarray
    first: Product
    second: Product
    loop: np.ndarray | None
    chance: np.ndarray


def _incidence(h: Hypergraph):
    t = h.weighted.select("eid", "vid", "gamma", "w").toArrow()
    eid, vid, gamma, w = (t.column(c).to_numpy() for c in ("eid", "vid", "gamma", "w"))
    eids, e = np.unique(eid, return_inverse=True)
    vids, v = np.unique(vid, return_inverse=True)
    return eids, e, vids, v, gamma, w


def walk_chain(h: Hypergraph, side: str) -> Chain:
    """The walk over hyperedges, from nodes or from hyperedges."""
    eids, e, vids, v, gamma, w = _incidence(h)
    n, m = len(vids), len(eids)
    d, delta = np.bincount(v, w * gamma, n), np.bincount(e, gamma, m)
    up, down = w * gamma / d[v], gamma / delta[e]
    if side == "node":
        return Chain(vids, Product(e, m, v, up), Product(v, n, e, down), None, d / d.sum())
    mass = np.bincount(e, w * gamma, m)
    return Chain(eids, Product(v, n, e, down), Product(e, m, v, up), None, mass / mass.sum())


def smoothing(h: Hypergraph, ids: np.ndarray):
    """(places, forth, back): vectors averaged over hyperedges and back as two products, and the transposed two. `places` are the nodes' among `ids`."""
    eids, e, vids, v, gamma, w = _incidence(h)
    n, m = len(vids), len(eids)
    up, down = w * gamma / np.bincount(v, w * gamma, n)[v], gamma / np.bincount(e, gamma, m)[e]
    return np.searchsorted(ids, vids), (Product(e, m, v, down), Product(v, n, e, up)), (Product(e, m, v, up), Product(v, n, e, down))


def through(places: np.ndarray, halves, x: np.ndarray, columns: int = 16) -> np.ndarray:
    """Both products on the rows at `places`, a few columns at a time; other rows come out as zero."""
    out = np.zeros_like(x)
    for s in range(0, x.shape[1], columns):
        out[places, s:s + columns] = halves[1] @ (halves[0] @ x[places, s:s + columns])
    return out


def clique_chain(h: Hypergraph) -> Chain:
    """The walk on the clique graph, the way back to the node itself taken off."""
    eids, e, vids, v, gamma, w = _incidence(h)
    n, m = len(vids), len(eids)
    d = np.maximum(np.bincount(v, w * gamma * (np.bincount(e, gamma, m)[e] - gamma), n), 1e-12)
    loop = np.bincount(v, w * gamma * gamma, n) / d
    return Chain(vids, Product(e, m, v, w * gamma / d[v]), Product(v, n, e, gamma), loop, d / d.sum())


def restart_powers(alpha: float, steps: int) -> list[float]:
    """Weights of the walk's powers 0 to `steps` in the restart walk."""
    return [alpha * (1 - alpha) ** t for t in range(steps)] + [(1 - alpha) ** steps]


@dataclass
class RowFiles:
    """A symmetric matrix in files of Arrow batches (place, at, sim), one file a partition."""

    spark: SparkSession
    ids: np.ndarray
    folder: str
    files: int

    def __matmul__(self, x: np.ndarray) -> np.ndarray:
        folder, held = self.folder, self.spark.sparkContext.broadcast(np.ascontiguousarray(x))

        def run(batches):
            from pyarrow import fs as pafs

            fs, base = pafs.FileSystem.from_uri(folder)
            block = held.value
            for b in batches:
                for i in b.column(0).to_pylist():
                    with fs.open_input_file(f"{base}/{i}.arrow") as f:
                        for rows in pa.ipc.open_stream(f):
                            start = rows.column("at").offsets.to_numpy()
                            at, sim = rows.column("at").flatten().to_numpy(), rows.column("sim").flatten().to_numpy()
                            out = np.array([sim[s:t] @ block[at[s:t]] for s, t in zip(start, start[1:])]).reshape(len(rows), block.shape[1])
                            yield vec_batch(rows.column("place"), out)

        got = self.spark.range(0, self.files, 1, self.files).mapInArrow(run, VEC).toArrow()
        out = np.zeros((len(self.ids), x.shape[1]))
        out[got.column("id").to_numpy()] = got.column("vec").combine_chunks().flatten().to_numpy().reshape(-1, x.shape[1])
        held.destroy()
        return out


def similarity_rows(spark: SparkSession, chain: Chain, powers: list[float], negative: float = 1.0, keep: np.ndarray | None = None) -> RowFiles:
    """Log of how much likelier the weighted powers of the walk end there than by chance, at least 0; `keep` (places) limits both sides."""
    places = np.arange(len(chain.ids)) if keep is None else keep
    files = int(max(1, min(512, -(-len(places) // (4 * BLOCK)))))
    folder = f"{work_folder(spark)}/graph-rows-{uuid.uuid4().hex}"
    if "://" not in folder and not folder.startswith("file:"):
        folder = f"file://{folder}"
    held = spark.sparkContext.broadcast((chain, places))
    n, share = len(places), -(-len(places) // files)

    def run(batches):
        from pyarrow import fs as pafs

        c, places = held.value
        fs, base = pafs.FileSystem.from_uri(folder)
        fs.create_dir(base, recursive=True)
        floor = (c.chance[places] * negative)[:, None]
        schema = pa.schema([("place", pa.int64()), ("at", pa.list_(pa.int32())), ("sim", pa.list_(pa.float64()))])
        for b in batches:
            for i in b.column(0).to_pylist():
                made = 0
                with fs.open_output_stream(f"{base}/{i}.arrow", compression=None) as out, pa.ipc.new_stream(out, schema) as writer:
                    for s in range(i * share, min(n, (i + 1) * share), BLOCK):
                        mine = np.arange(s, min(n, (i + 1) * share, s + BLOCK))
                        x = np.zeros((len(c.ids), len(mine)))
                        x[places[mine], np.arange(len(mine))] = 1
                        total = powers[0] * x
                        for weight in powers[1:]:
                            step = c.second @ (c.first @ x)
                            x = step if c.loop is None else step - c.loop[:, None] * x
                            total += weight * x
                        ratio = (total[places] / floor).T
                        row, at = np.nonzero(ratio > 1)
                        offsets = pa.array(np.r_[0, np.cumsum(np.bincount(row, minlength=len(mine)))].astype(np.int32))
                        lists = [pa.ListArray.from_arrays(offsets, pa.array(a)) for a in (at.astype(np.int32), np.log(ratio[row, at]))]
                        writer.write_batch(pa.RecordBatch.from_arrays([pa.array(mine), *lists], schema=schema))
                        made += len(mine)
                yield pa.RecordBatch.from_pydict({"made": [made]})

    made = spark.range(0, files, 1, files).mapInArrow(run, "made long").agg(F.sum("made")).first()[0] or 0
    held.destroy()
    if made != n:
        raise RuntimeError(f"{made} rows of {n} were made")
    return RowFiles(spark, chain.ids[places], folder, files)


def similarity_error(spark: SparkSession, chain: Chain, powers: list[float], z: np.ndarray) -> float:
    """Mean over all pairs of the distance from similarity to dot product of `z`, both divided by the mean of their own diagonal.

    Executors make the similarity's rows a few at a time and keep none. The diagonal's mean comes first; the walk from a node and back to it
    is two walks of half its steps that meet, as chances turn round with those of being there.
    """
    n, tall = len(chain.ids), max(len(chain.ids), len(chain.first.order), 1)
    block = int(max(1, min(BLOCK, HELD // tall)))
    tasks = int(max(1, min(512, -(-n // block))))
    held = spark.sparkContext.broadcast((chain, np.ascontiguousarray(z, float)))
    share, own = -(-n // tasks), max(float((z * z).sum() / max(n, 1)), 1e-12)

    def added(block_sum) -> float:
        def run(batches):
            c, vectors = held.value
            for b in batches:
                for i in b.column(0).to_pylist():
                    total, made = 0.0, 0
                    for s in range(i * share, min(n, (i + 1) * share), block):
                        mine = np.arange(s, min(n, (i + 1) * share, s + block))
                        x = np.zeros((n, len(mine)))
                        x[mine, np.arange(len(mine))] = 1
                        total += block_sum(c, vectors, mine, x)
                        made += len(mine)
                    yield pa.RecordBatch.from_pydict({"made": [made], "total": [float(total)]})

        got = spark.range(0, tasks, 1, tasks).mapInArrow(run, "made long, total double").agg(F.sum("made"), F.sum("total")).first()
        if got[0] != n:
            raise RuntimeError(f"{got[0]} rows of {n} were made")
        return got[1]

    def diagonal(c, vectors, mine, x):
        chance, ratio = c.chance[:, None], np.zeros(len(mine))
        for t, weight in enumerate(powers):
            if t % 2:
                before, x = x, c.second @ (c.first @ x)
            ratio += weight * (x * (before if t % 2 else x) / chance).sum(axis=0)
        return np.log(np.maximum(ratio, 1.0)).sum()

    def distance(c, vectors, mine, x):
        total = powers[0] * x
        for weight in powers[1:]:
            x = c.second @ (c.first @ x)
            total += weight * x
        sim = np.log(np.maximum(total / c.chance[:, None], 1.0))
        return np.abs(sim / mean - (vectors @ vectors[mine].T) / own).sum()

    mean = added(diagonal) / max(n, 1)
    error = added(distance) / max(n, 1) ** 2
    held.destroy()
    return error


def leading_pairs(times, n: int, k: int, negative: str = "drop", tolerance: float = 1e-8, seed: int = 1) -> tuple[np.ndarray, np.ndarray]:
    """(k leading eigenvalues, vectors) of the symmetric operator `times` on n x b blocks.

    The space grows by the residuals of the pairs that are still open and is cut back to the leading pairs when it is six blocks wide;
    it ends when every residual is below `tolerance` times the largest value, or the space is whole.
    """
    k = min(k, n)
    width = min(n, k + 8)
    new = np.random.default_rng(seed).standard_normal((n, width))
    basis, image = np.zeros((n, 0)), np.zeros((n, 0))
    while True:
        for _ in range(2):
            new = new / np.maximum(np.linalg.norm(new, axis=0), 1e-300)
            new = new - basis @ (basis.T @ new)
            u, s, _ = np.linalg.svd(new, full_matrices=False)
            new = u[:, s > s.max(initial=0) * 1e-8] if s.max(initial=0) > 1e-10 else u[:, :0]
        new = new[:, : n - basis.shape[1]]
        if new.shape[1]:
            basis, image = np.hstack([basis, new]), np.hstack([image, times(new)])
        small = basis.T @ image
        value, turn = np.linalg.eigh((small + small.T) / 2)
        order = np.argsort(-(value if negative == "drop" else np.abs(value)), kind="stable")
        value, turn = value[order], turn[:, order]
        vectors = basis @ turn[:, :k]
        rest = image @ turn[:, :k] - vectors * value[:k]
        still = np.linalg.norm(rest, axis=0) > tolerance * max(np.abs(value).max(initial=0), 1e-300)
        if not still.any() or basis.shape[1] >= n or not new.shape[1]:
            return value[:k], vectors
        if basis.shape[1] + width > 6 * width:
            basis, image = basis @ turn[:, : k + width], image @ turn[:, : k + width]
        new = rest[:, still]


def embedding(times, ids: np.ndarray, k: int, negative: str = "drop") -> np.ndarray:
    """Eigenvectors times root of the values, padded to k columns."""
    from .lowrank import canonical

    value, e = leading_pairs(times, len(ids), k, negative)
    if negative == "drop":
        value, e = value[value > 0], e[:, value > 0]
    z = canonical(e * np.sqrt(np.abs(value)), e)
    return z if z.shape[1] == k else np.concatenate([z, np.zeros((len(z), k - z.shape[1]))], axis=1)


def given_places(h: Hypergraph, ids: np.ndarray) -> np.ndarray:
    given = h.edges.where("kind = 'S'").select("eid").toArrow().column("eid").to_numpy()
    return np.flatnonzero(np.isin(ids, given))
