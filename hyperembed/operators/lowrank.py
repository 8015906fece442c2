"""Truncated SVD of the normalised incidence, walk filter, factors, tensor sketch, polynomial fit, eigenpairs, bounds."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..session import cut
from . import panels
from .blocks import VEC, gram, half_step, rows_of, times, vec_batch
from .hypergraph import Hypergraph, edge_degrees, node_degrees, normalise, volume


@dataclass
class Svd:
    """ell = U diag(sigma) V^T, leading part: u (hyperedges) and v (nodes) as vector tables."""

    u: DataFrame
    sigma: np.ndarray
    v: DataFrame

    @property
    def rank(self) -> int:
        return len(self.sigma)


def _normal(ids: np.ndarray, width: int, seed: int) -> np.ndarray:
    """Standard normal entries that depend on (id, column, seed) alone, by Box-Muller on hashes."""
    i, c = ids.astype(np.uint64)[:, None], np.arange(width, dtype=np.uint64)[None]
    with np.errstate(over="ignore"):
        x = i * np.uint64(0x9E3779B97F4A7C15) + c * np.uint64(0xC2B2AE3D27D4EB4F) + np.uint64(seed * 0x165667B19E3779F9 % (1 << 64))
        draws = []
        for k in (1, 2):
            z = x + np.uint64(k * 0x27D4EB2F165667C5)
            z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
            z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
            draws.append(((z ^ (z >> np.uint64(31))) >> np.uint64(11)).astype(float) / float(1 << 53))
    return np.sqrt(-2 * np.log(np.maximum(draws[0], 1e-300))) * np.cos(2 * np.pi * draws[1])


def start_block(ids: DataFrame, width: int, seed: int) -> DataFrame:
    """A row of `_normal` entries for each id."""

    def run(batches):
        for b in batches:
            yield vec_batch(b.column(0), _normal(b.column(0).to_numpy(), width, seed))

    return ids.select("id").mapInArrow(run, VEC)


def _orthonormal(vecs: DataFrame, width: int) -> tuple[DataFrame, np.ndarray]:
    """(basis of the columns' span, its width): by the eigenpairs of the Gram matrix, twice for accuracy."""
    for _ in range(2):
        d, e = np.linalg.eigh(gram(vecs, width))
        keep = d > max(d.max(initial=0) * 1e-13, 1e-300)
        m = e[:, keep] / np.sqrt(d[keep])
        vecs, width = times(vecs, m), int(keep.sum())
    return vecs, width


def _svd_panels(h: Hypergraph, rank: int, oversample: int, power: int, seed: int, edges: bool) -> Svd | None:
    """`svd_block` on panels of columns in node space: hyperedges' vectors are not kept but for the result's, which wait until they are asked for.

    With x = sqrt(d) y the step ell^T ell x is sqrt(d) times y averaged over hyperedges and back. The span of the block is the same as that
    of the form by joins; x^T ell^T ell x is the Gram matrix of the hyperedges' block. None where joins are the better way.
    """
    rows = h.weighted.select("eid", "vid", "gamma", "w")
    size = rows.count()
    if size * (rank + oversample) <= panels.JOINED:
        return None
    ids = np.sort(rows.select("vid").distinct().limit(panels.NODES + 1).toArrow().column(0).to_numpy())
    width = min(rank + oversample, len(ids), rows.select("eid").distinct().count())
    if len(ids) > panels.NODES or width < 2:
        return None
    p = panels.Panels(rows.sparkSession, rows, size, ids, width)

    def first(batches):
        for b in batches:
            top = rows_of(b)
            if len(top):
                # The first right vector is known: square roots of degrees, with singular value 1.
                yield vec_batch(b.column("id"), np.hstack([np.ones_like(top), _normal(b.column("id").to_numpy(), width - 1, seed) / top]))

    p.after(p.degrees().mapInArrow(first, VEC), 0, "block-0")
    turn = np.eye(width)
    for t in range(power + 1):
        p.after(times(p.table(f"block-{t}"), np.pad(turn, ((0, 0), (0, width - turn.shape[1])))), 1, f"block-{t + 1}")
        if t < power:
            p.forget(f"block-{t}")
            turn = np.eye(width)
            for _ in range(2):
                d, e = np.linalg.eigh(gram(times(p.table(f"block-{t + 1}", weigh=True), turn), turn.shape[1]))
                keep = d > max(d.max(initial=0) * 1e-13, 1e-300)
                turn = turn @ (e[:, keep] / np.sqrt(d[keep]))
    # Columns: what went into the last step, before its turn, and what came out.
    g = gram(p.table(f"block-{power}", f"block-{power + 1}", weigh=True), 2 * width)
    n = turn.shape[1]
    inner = turn.T @ g[:width, width:width + n]
    d, e = np.linalg.eigh((inner + inner.T) / 2)
    keep = d > max(d.max(initial=0) * 1e-13, 1e-300)
    straight = e[:, keep] / np.sqrt(d[keep])
    outer = straight.T @ g[width:width + n, width:width + n] @ straight
    d, e = np.linalg.eigh((outer + outer.T) / 2)
    order = np.argsort(-d)[:rank]
    d, e = np.maximum(d[order], 0), e[:, order]
    keep = d > 1e-16
    sigma, last = np.sqrt(d[keep]), straight @ e[:, keep]
    v = cut(times(p.table(f"block-{power + 1}", weigh=True), np.pad(last / sigma, ((0, width - n), (0, 0)))), "v")
    flip = _signs(v, len(sigma))
    # ell times what went in gives the hyperedges' vectors; without that, ell v / sigma does up to the residual.
    before = cut(times(p.table(f"block-{power}", weigh=True), turn @ last * flip), "u") if edges else times(v, np.diag(flip / sigma))
    p.forget_all()
    return Svd(half_step(normalise(h), before, len(sigma), "vid", "eid"), np.minimum(sigma, 1.0), times(v, np.diag(flip)))


def svd_block(h: Hypergraph, rank: int, oversample: int = 10, power: int = 2, seed: int = 1, warm: Svd | None = None, edges: bool = True) -> Svd:
    """Block subspace iteration: 2 * power + 2 passes over the incidence, each two joins with partial vector sums; large graphs go by
    panels of columns, where without `edges` the vectors of hyperedges are right up to the residual only.

    With `warm`, the decomposition of an earlier state of the graph, the block starts from its right vectors, so that fewer
    passes do; nodes that are new since then start at zero there and join in at the first pass.
    """
    by_panels = _svd_panels(h, rank, oversample, power, seed, edges) if warm is None else None
    if by_panels is not None:
        return by_panels
    ell = cut(normalise(h), "ell")
    nodes = node_degrees(h).select(F.col("vid").alias("id"), F.sqrt("d").alias("top"))
    n, m = nodes.count(), ell.select("eid").distinct().count()
    width = min(rank + oversample, n, m)
    # The first right vector is known: square roots of degrees, with singular value 1.
    v = start_block(nodes, width - 1, seed).join(nodes, "id").select("id", F.concat(F.array("top"), "vec").alias("vec")) if width > 1 else nodes.select("id", F.array("top").alias("vec"))
    if warm is not None and width > 1:
        held = min(warm.rank, width) - 1
        old = warm.v.select("id", F.slice("vec", 2, held).alias("old")) if held else warm.v.select("id", F.array().cast("array<double>").alias("old"))
        zeros = F.array_repeat(F.lit(0.0), held)
        v = v.join(old, "id", "left").select("id", F.concat(F.slice("vec", 1, width - held), F.coalesce("old", zeros)).alias("vec"))
    v = cut(v, "block")
    for _ in range(power + 1):
        u = cut(half_step(ell, v, width, "vid", "eid"), "block")
        u, width = _orthonormal(u, width)
        u = cut(u, "block")
        v = cut(half_step(ell, u, width, "eid", "vid"), "block")
    # ell^T u = v, so the Gram matrix of v has the squared singular values within span(u).
    d, e = np.linalg.eigh(gram(v, width))
    order = np.argsort(-d)[:rank]
    d, e = np.maximum(d[order], 0), e[:, order]
    keep = d > 1e-16
    d, e = d[keep], e[:, keep]
    sigma = np.sqrt(d)
    v = cut(times(v, e / sigma), "v")
    flip = _signs(v, len(sigma))
    return Svd(cut(times(u, e * flip), "u"), np.minimum(sigma, 1.0), cut(times(v, np.diag(flip)), "v"))


def _signs(v: DataFrame, width: int) -> np.ndarray:
    """Per column the sign of its product with a fixed hash vector, so that sketches do not depend on the order of sums."""
    from ..functions.vectors import mix

    h = F.pmod(mix(F.col("id"), 0, 17), F.lit(2001)) - 1000
    row = v.agg(*[F.sum(h * F.col("vec")[i]) for i in range(width)]).first()
    return np.array([-1.0 if (x or 0) < 0 else 1.0 for x in row])


def dense_incidence(h: Hypergraph, most: int = 5000):
    """(node ids, hyperedge ids, ell as a matrix hyperedges x nodes) on the driver; refuses larger inputs."""
    rows = normalise(h)
    sizes = rows.agg(F.count_distinct("vid"), F.count_distinct("eid")).first()
    if sizes[0] > most or sizes[1] > 4 * most:
        raise ValueError(f"{sizes[0]} nodes and {sizes[1]} hyperedges are too many for the dense path (limit {most}); use the sketch")
    p = rows.toPandas()
    vids, eids = np.unique(p["vid"]), np.unique(p["eid"])
    ell = np.zeros((len(eids), len(vids)))
    ell[np.searchsorted(eids, p["eid"]), np.searchsorted(vids, p["vid"])] = p["ell"]
    return vids, eids, ell


def to_frame(spark, ids, x: np.ndarray) -> DataFrame:
    return spark.createDataFrame(pa.Table.from_batches([vec_batch(pa.array(np.asarray(ids, np.int64)), np.asarray(x, float))]))


def svd_full(h: Hypergraph, rank: int | None = None, most: int = 5000) -> Svd:
    """Exact reduced SVD on the driver, for small inputs."""
    vids, eids, ell = dense_incidence(h, most)
    u, s, vt = np.linalg.svd(ell, full_matrices=False)
    k = len(s) if rank is None else min(rank, len(s))
    spark = h.inc.sparkSession
    v = to_frame(spark, vids, vt[:k].T)
    flip = _signs(v, k)
    return Svd(to_frame(spark, eids, u[:, :k] * flip), s[:k], to_frame(spark, vids, vt[:k].T * flip))


def svd_mllib(h: Hypergraph, rank: int, most: int = 50_000) -> np.ndarray:
    """Leading singular values by `RowMatrix.computeSVD` of mllib, as a cross-check of the other forms.

    The smaller of both sides gives the columns, by its place in the order of ids: the values of a matrix and of its transpose are
    the same. The library holds vectors of all columns on the driver, hence the limit; where both sides are larger it is refused.
    """
    from pyspark.mllib.linalg import Vectors
    from pyspark.mllib.linalg.distributed import RowMatrix

    ell = cut(normalise(h), "ell")
    sizes = ell.agg(F.count_distinct("vid").alias("vid"), F.count_distinct("eid").alias("eid")).first()
    column, row = ("vid", "eid") if sizes["vid"] <= sizes["eid"] else ("eid", "vid")
    n = sizes[column]
    if n > most:
        raise ValueError(f"more than {most} nodes and hyperedges are too many for the cross-check; use svd_block")
    if not n:
        return np.zeros(0)
    ids = [r[0] for r in ell.select(column).distinct().orderBy(column).collect()]
    columns = F.broadcast(ell.sparkSession.createDataFrame(list(zip(ids, range(n))), f"{column} long, place int"))
    entry = F.sort_array(F.collect_list(F.struct("place", "ell")))
    rows = ell.join(columns, column).groupBy(row).agg(entry.alias("row")).select("row.place", "row.ell")
    matrix = RowMatrix(rows.rdd.map(lambda r: Vectors.sparse(n, r[0], r[1])), numCols=n)
    return np.array(matrix.computeSVD(min(rank, n)).s.toArray())


def block_lanczos(apply, start: DataFrame, width: int, rank: int, limit: int, tolerance: float, most: int = 40, largest: bool = True) -> tuple[np.ndarray, DataFrame]:
    """(leading eigenvalues, their vectors as a table) of a symmetric operator on vector tables.

    `apply(block, width)` multiplies a block. The basis stands in one table, orthogonalised against all of itself at every
    step. Steps go on until the residual of each of the `rank` leading pairs is below `tolerance` times the largest value,
    the basis spans `limit` dimensions, or the operator leaves it no new direction.
    """
    basis, total = _orthonormal(start, width)
    basis = cut(basis, "lanczos")
    width, form = total, np.zeros((0, 0))
    for _ in range(most):
        last = basis.select("id", F.slice("vec", total - width + 1, width).alias("vec"))
        image = apply(last, width).select("id", F.col("vec").alias("image"))
        nothing = F.array(*[F.lit(0.0)] * width)
        both = cut(basis.join(image, "id", "left").select("id", F.concat("vec", F.coalesce("image", nothing)).alias("vec")), "lanczos")
        g = gram(both, total + width)
        grown = np.zeros((total, total))
        grown[: len(form), : len(form)] = form
        grown[:, total - width:] = g[:total, total:]
        grown[total - width:] = g[:total, total:].T
        form = grown
        # The basis is orthonormal up to rounding; its own Gram matrix corrects for the rest.
        root = np.linalg.cholesky(g[:total, :total])
        inner = np.linalg.solve(root, np.linalg.solve(root, (form + form.T) / 2).T)
        value, vector = np.linalg.eigh((inner + inner.T) / 2)
        order = np.argsort(-value if largest else -np.abs(value), kind="stable")[:rank]
        value, vector = value[order], np.linalg.solve(root.T, vector[:, order])
        cross = np.linalg.solve(g[:total, :total], g[:total, total:])
        rest = g[total:, total:] - g[total:, :total] @ cross
        d, e = np.linalg.eigh((rest + rest.T) / 2)
        scale = max(np.abs(value).max(initial=0), 1e-300)
        tail = vector[total - width:]
        residual = np.sqrt(np.maximum(np.einsum("ij,ik,kj->j", tail, rest, tail), 0))
        keep = d > max(1e-20, (1e-10 * scale) ** 2)
        if (len(value) == min(rank, limit) and residual.max(initial=0) <= tolerance * scale) or total >= limit or not keep.any():
            break
        keep &= np.arange(len(d)) >= len(d) - (limit - total)  # no more directions than there are left
        turn = e[:, keep] / np.sqrt(d[keep])
        step = np.zeros((total + width, total + turn.shape[1]))
        step[:total, :total] = np.eye(total)
        step[:total, total:], step[total:, total:] = -cross @ turn, turn
        basis = cut(times(both, step), "lanczos")
        width = turn.shape[1]
        total += width
    return value, times(basis, vector)


def svd_lanczos(h: Hypergraph, rank: int, tolerance: float = 1e-9, block: int | None = None, seed: int = 1) -> Svd:
    """Golub-Kahan Lanczos in blocks, with full re-orthogonalisation, until every kept value's residual is below `tolerance`.

    A block as wide as the rank and a little more finds values that repeat; the known top right vector is in the first block.
    """
    ell = cut(normalise(h), "ell")
    nodes = node_degrees(h).select(F.col("vid").alias("id"), F.sqrt("d").alias("top"))
    n, m = nodes.count(), ell.select("eid").distinct().count()
    width = min(block or rank + 2, n, m)
    start = start_block(nodes, width - 1, seed).join(nodes, "id").select("id", F.concat(F.array("top"), "vec").alias("vec")) if width > 1 else nodes.select("id", F.array("top").alias("vec"))
    step = lambda v, w: cut(half_step(ell, cut(half_step(ell, v, w, "vid", "eid"), "lanczos"), w, "eid", "vid"), "lanczos")
    value, v = block_lanczos(step, start, width, rank, n, tolerance)
    keep = value > 1e-16
    sigma, v = np.sqrt(value[keep]), cut(times(v, np.eye(len(value))[:, keep]), "v")
    flip = _signs(v, len(sigma))
    u = half_step(ell, v, len(sigma), "vid", "eid")
    return Svd(cut(times(u, np.diag(flip / sigma)), "u"), np.minimum(sigma, 1.0), cut(times(v, np.diag(flip)), "v"))


def walk_filter(sigma, alpha: float = 0.1, steps: int = 10) -> np.ndarray:
    """Weight of each singular direction in the restart walk, by the recursion."""
    s2 = np.asarray(sigma, float) ** 2
    phi = np.ones_like(s2)
    for _ in range(steps):
        phi = alpha + (1 - alpha) * s2 * phi
    return phi


def walk_filter_sum(sigma, alpha: float = 0.1, steps: int = 10) -> np.ndarray:
    """The same as a sum of powers."""
    s2 = np.asarray(sigma, float) ** 2
    x = (1 - alpha) * s2
    return alpha * sum(x**t for t in range(steps)) + x**steps if steps else np.ones_like(s2)


def factor(svd: Svd, h: Hypergraph, alpha: float = 0.1, steps: int = 10, side: str = "node") -> DataFrame:
    """(id, vec): rows whose dot products give volume times walk probability over degree. Hyperedges: given ones only."""
    vol = volume(h).first()["vol"]
    phi = np.sqrt(walk_filter(svd.sigma, alpha, steps) * vol)
    if side == "node":
        scale, base = node_degrees(h).select(F.col("vid").alias("id"), F.col("d").alias("mass")), svd.v
    else:
        given = h.edges.where("kind = 'S'").select("eid", "w")
        scale = edge_degrees(h).join(given, "eid").select(F.col("eid").alias("id"), (F.col("w") * F.col("delta")).alias("mass"))
        base = svd.u
    rows = base.join(scale, "id").select("id", F.transform("vec", lambda x: x / F.sqrt("mass")).alias("vec"))
    return times(rows, np.diag(phi))


def svd_error_bound(h: Hypergraph, sigma_all, rank: int, alpha: float = 0.1, steps: int = 10, side: str = "node") -> float:
    """Right side of the rank bound; hyperedges with the restart mass of the directions outside the incidence's span."""
    phi = walk_filter(np.asarray(sigma_all)[rank:], alpha, steps).sum()
    d = node_degrees(h).agg(F.sum("d"), F.sum(1 / F.col("d")), F.count("*")).first()
    if side == "node":
        return float((d[0] * d[1] * phi) ** 2)
    e = h.weighted.groupBy("eid").agg(F.sum(F.col("w") * F.col("gamma")).alias("x")).agg(F.sum(1 / F.col("x")), F.count("*")).first()
    return float((d[0] * e[0] * (phi + alpha * e[1])) ** 2)


# Sketches.


def sketch_tables(width: int, tau: int, b: int, seed: int = 3) -> tuple[np.ndarray, np.ndarray]:
    """(buckets, signs) of tau count sketches of vectors of `width` entries, from the package's hash."""
    p = 2147483647

    def mix(a, c, s):
        f = lambda t, k: (t * 48271 + c * 69621 + k * 16807 + 12345) % p
        t = f(a % p, s)
        return f((t * t + 12345) % p, s + 1)

    bucket = np.array([[mix(i, t, seed) % b for i in range(width)] for t in range(tau)])
    sign = np.array([[1 - 2 * (mix(i, t, seed + 50) % 2) for i in range(width)] for t in range(tau)], float)
    return bucket, sign


def count_sketch(x: np.ndarray, bucket: np.ndarray, sign: np.ndarray, b: int) -> np.ndarray:
    out = np.zeros((len(x), b))
    np.add.at(out.T, bucket, (x * sign).T)
    return out


def tensor_sketch_rows(x: np.ndarray, tau: int, b: int, tables) -> np.ndarray:
    """[1, S_1, .., S_tau]: dot products of S_p estimate the p-th power of the rows' dot products."""
    bucket, sign = tables
    parts, s = [np.ones((len(x), 1))], None
    for t in range(tau):
        c = count_sketch(x, bucket[t], sign[t], b)
        s = c if s is None else np.fft.irfft(np.fft.rfft(s) * np.fft.rfft(c), b)
        parts.append(s)
    return np.concatenate(parts, axis=1)


def tensor_sketch(f: DataFrame, width: int, tau: int = 3, b: int = 128, seed: int = 3, scale: float = 1.0) -> DataFrame:
    """Sketch of every row (divided by `scale` first), row by row without any exchange."""
    tables = sketch_tables(width, tau, b, seed)

    def run(batches):
        for batch in batches:
            x = rows_of(batch)
            yield vec_batch(batch.column("id"), tensor_sketch_rows(x / scale, tau, b, tables) if len(x) else np.zeros((0, 1 + tau * b)))

    return f.mapInArrow(run, VEC)


def sample_rows(f: DataFrame, c: int, seed: int = 5) -> np.ndarray:
    """c rows, the first in the order of a hash of their id."""
    from ..functions.vectors import mix

    return np.array([r["vec"] for r in f.orderBy(mix(F.col("id"), 0, seed), "id").limit(c).select("vec").collect()])


def sample_centres(f: DataFrame, c: int, seed: int = 5) -> np.ndarray:
    """c rows by greedy k-centre: the first by hash, then each time the row farthest from all picked (ties: least id).

    Each pick is one pass that sends one row per partition; fewer rows come back where fewer differ.
    """
    picked = sample_rows(f, 1, seed)
    while 0 < len(picked) < c:
        centres = picked

        def farthest(batches):
            best = None
            for b in batches:
                x = rows_of(b)
                if len(x):
                    d = ((x[:, None, :] - centres[None]) ** 2).sum(axis=2).min(axis=1)
                    ids = b.column("id").to_numpy()
                    i = np.lexsort((ids, -d))[0]
                    if best is None or (-d[i], ids[i]) < best[:2]:
                        best = (-d[i], ids[i], x[i])
            if best is not None:
                yield pa.RecordBatch.from_pydict({"far": [float(-best[0])], "least": [-int(best[1])], "vec": [best[2].tolist()]})

        top = f.select("id", "vec").mapInArrow(farthest, "far double, least long, vec array<double>").agg(F.max(F.struct("far", "least", "vec")).alias("top")).first()["top"]
        if top is None or top["far"] <= 0:
            break
        picked = np.vstack([picked, top["vec"]])
    return picked


def fit_poly(f: DataFrame, tau: int = 3, c: int = 10, fn=None, seed: int = 5, sample: str = "hash") -> tuple[np.ndarray, float]:
    """(theta for powers 0..tau of the dot product, largest dot product): least squares of fn on sampled rows against all rows.

    `sample` chooses the rows: 'hash' order or 'kcenter'. Partitions add up moments of the dot products scaled by their
    largest; the driver solves (tau + 1) equations.
    """
    fn = fn or (lambda x: np.log(np.maximum(x, 1.0)))
    picked = {"hash": sample_rows, "kcenter": sample_centres}[sample](f, c, seed)
    if not len(picked):
        return np.zeros(tau + 1), 1.0

    def largest(batches):
        top = 0.0
        for b in batches:
            x = rows_of(b)
            if len(x):
                top = max(top, float(np.abs(x @ picked.T).max()))
        yield pa.RecordBatch.from_pydict({"top": [top]})

    top = max((f.mapInArrow(largest, "top double").agg(F.max("top")).first()[0] or 0.0), 1e-12)

    def moments(batches):
        a, y = np.zeros(2 * tau + 1), np.zeros(tau + 1)
        for b in batches:
            x = rows_of(b)
            if len(x):
                d = (x @ picked.T).ravel()
                z, v = d / top, fn(d)
                a += [(z**p).sum() for p in range(2 * tau + 1)]
                y += [(z**p * v).sum() for p in range(tau + 1)]
        yield pa.RecordBatch.from_arrays([pa.array([a.tolist()]), pa.array([y.tolist()])], ["a", "y"])

    sums = f.mapInArrow(moments, "a array<double>, y array<double>").agg(
        *[F.sum(F.col("a")[p]).alias(f"a{p}") for p in range(2 * tau + 1)], *[F.sum(F.col("y")[p]).alias(f"y{p}") for p in range(tau + 1)]
    ).first()
    a, y = np.array(sums[: 2 * tau + 1]), np.array(sums[2 * tau + 1:])
    normal = np.array([[a[p + q] for q in range(tau + 1)] for p in range(tau + 1)])
    theta = np.linalg.lstsq(normal, y, rcond=1e-12)[0]
    return theta / top ** np.arange(tau + 1), top


def theta_diagonal(theta: np.ndarray, b: int) -> np.ndarray:
    """Coefficients laid out over the columns of the sketch."""
    return np.r_[theta[0], np.repeat(theta[1:], b)]


def eig_gram(y: DataFrame, theta: np.ndarray, width: int, k: int, negative: str = "drop") -> tuple[np.ndarray, np.ndarray]:
    """(eigenvalues, M): the k leading eigenvectors of Y diag(theta) Y^T, scaled by root eigenvalues, are Y M."""
    d, e = np.linalg.eigh(gram(y, width))
    keep = d > d.max(initial=0) * 1e-12
    d, e = d[keep], e[:, keep]
    core = (e * np.sqrt(d)).T @ (theta[:, None] * (e * np.sqrt(d)))
    lam, a = np.linalg.eigh((core + core.T) / 2)
    order = np.argsort(-(lam if negative == "drop" else np.abs(lam)), kind="stable")[:k]
    lam, a = lam[order], a[:, order]
    if negative == "drop":
        lam, a = lam[lam > 0], a[:, lam > 0]
    m = (e / np.sqrt(d)) @ a * np.sqrt(np.abs(lam))
    if m.shape[1] < k:
        m = np.concatenate([m, np.zeros((len(m), k - m.shape[1]))], axis=1)
    return lam, m


def lowrank_matvec(y: DataFrame, theta: np.ndarray, width: int, v: DataFrame, columns: int = 1) -> DataFrame:
    """Y (theta * (Y^T v)) for a vector table v of `columns` columns."""
    joined = y.join(v.select("id", F.col("vec").alias("x")), "id").select("id", F.concat("vec", "x").alias("vec"))
    inner = gram(joined, width + columns)[:width, width:]
    return times(y, theta[:, None] * inner)


def eig_lanczos(y: DataFrame, theta: np.ndarray, width: int, k: int, tolerance: float = 1e-9, seed: int = 1) -> tuple[np.ndarray, DataFrame]:
    """(k leading eigenvalues of Y diag(theta) Y^T, their vectors as a table), by block Lanczos on distributed products."""
    y = cut(y, "lanczos")
    n = y.count()
    columns = min(k + 2, n, width)
    step = lambda v, w: cut(lowrank_matvec(y, theta, width, v, w), "lanczos")
    value, vectors = block_lanczos(step, start_block(y, columns, seed), columns, k, min(n, width), tolerance)
    return value, cut(vectors, "lanczos")


def canonical(m: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Signs such that the largest absolute entry of each column of x is positive."""
    if not len(x):
        return m
    top = np.abs(x).argmax(axis=0)
    s = np.where(x[top, np.arange(x.shape[1])] < 0, -1.0, 1.0)
    return m * s
