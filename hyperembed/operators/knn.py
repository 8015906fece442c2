"""K nearest neighbours by cosine. Ties: cosine rounded to 12 digits, then the smaller vid. Rows: (vid, nbr, cos).

Rows of null vid or null vector have no neighbours and are nobody's; a null or NaN entry of a vector counts as 0, as do entries
that a shorter vector lacks. Of the rows that repeat a vid the least vector counts. Zero vectors have cosine 0 with all. Empty
tables give empty results; further columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from ..session import BROADCAST_BYTES, cut, small

OUT = "vid long, nbr long, cos double"
CODED = "vid long, attrs array<double>, homes array<long>, looks array<long>"
#: Rows of one side that a task compares at once.
TILE = 4096


def _best(df: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("vid").orderBy(F.desc("cos"), "nbr")
    return df.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).drop("rank")


def _rows(nodes: DataFrame) -> DataFrame:
    """(vid, attrs array<double>), one row for each vid."""
    clean = nodes.where("vid IS NOT NULL AND attrs IS NOT NULL").select("vid", F.transform(F.col("attrs").cast("array<double>"), lambda x: F.coalesce(F.nanvl(x, F.lit(0.0)), F.lit(0.0))).alias("attrs"))
    return clean.groupBy("vid").agg(F.min("attrs").alias("attrs"))


def _width(rows: DataFrame) -> tuple[int, int]:
    """(number of rows, length of the longest vector)."""
    r = rows.agg(F.count("*").alias("n"), F.max(F.size("attrs")).alias("q")).first()
    return r["n"], r["q"] or 0


def _even(rows: DataFrame, q: int) -> DataFrame:
    """Vectors filled up with zeros to length q."""
    return rows.withColumn("attrs", F.concat("attrs", F.array_repeat(F.lit(0.0), F.greatest(F.lit(q) - F.size("attrs"), F.lit(0)))))


def _matrix(column) -> np.ndarray:
    rows = column.to_pylist() if hasattr(column, "to_pylist") else column
    x = np.array(rows, dtype=np.float64)
    if not x.size:
        return x.reshape(len(rows), 0)
    n = np.linalg.norm(x, axis=1, keepdims=True)
    return np.divide(x, n, out=np.zeros_like(x), where=n > 0)


def _top(ids: np.ndarray, x: np.ndarray, other_ids: np.ndarray, y: np.ndarray, k: int):
    """Columns (vid, nbr, cos) of the k best of `other_ids` for each of `ids`, itself excluded."""
    vid, nbr, cos = [], [], []
    step = max(1, 4_000_000 // max(1, len(other_ids)))
    for s in range(0, len(ids), step):
        c = np.round(x[s: s + step] @ y.T, 12) + 0.0
        c[ids[s: s + step, None] == other_ids[None, :]] = -np.inf
        for i, row in zip(ids[s: s + step], c):
            cut = np.partition(row, -k)[-k] if len(row) > k else -np.inf
            near = np.flatnonzero((row >= cut) & (row > -np.inf))
            near = near[np.lexsort((other_ids[near], -row[near]))][:k]
            vid.append(np.full(len(near), i))
            nbr.append(other_ids[near])
            cos.append(row[near])
    cat = lambda parts, t: np.concatenate(parts) if parts else np.zeros(0, t)
    return cat(vid, np.int64), cat(nbr, np.int64), cat(cos, float)


def knn_broadcast(nodes: DataFrame, k: int) -> DataFrame:
    """Exact, the whole attribute matrix sent to every task; for matrices whose measured size fits the broadcast limit."""
    n, q = _width(nodes := _rows(nodes))
    if n * q * 8 > BROADCAST_BYTES * 4:
        raise ValueError("attribute matrix is too large to send to every task; use knn_exact or knn_lsh")
    nodes = _even(nodes, q)
    rows = nodes.select("vid", "attrs").toPandas().sort_values("vid")
    held = nodes.sparkSession.sparkContext.broadcast((rows["vid"].to_numpy(np.int64), _matrix(rows["attrs"].tolist())))

    def run(batches):
        ids, y = held.value
        for b in batches:
            v = b.column(0).to_numpy()
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in _top(v, _matrix(b.column(1)), ids, y, k)], ["vid", "nbr", "cos"])

    return nodes.select("vid", "attrs").mapInArrow(run, OUT)


def _cell(k: int):
    """Group function: the k best of the rows of side 1 for each row of side 0."""

    def run(key, t):
        side, ids, x = t.column("side").to_numpy(), t.column("vid").to_numpy(), _matrix(t.column("attrs"))
        a, b = side == 0, side == 1
        if not a.any() or not b.any():
            return pa.table({"vid": pa.array([], pa.int64()), "nbr": pa.array([], pa.int64()), "cos": pa.array([], pa.float64())})
        return pa.table(dict(zip(("vid", "nbr", "cos"), _top(ids[a], x[a], ids[b], x[b], k))))

    return run


def knn_exact(nodes: DataFrame, k: int, blocks: int | None = None) -> DataFrame:
    """Exact, over a grid of block pairs: every pair of blocks is one task, its partial top k meet by vid.

    All pairs are compared, so the cost is quadratic; blocks hold about TILE rows where `blocks` is not given.
    """
    n, q = _width(rows := _rows(nodes))
    blocks = blocks or -(-n // TILE) or 1
    rows = _even(rows, q).withColumn("block", F.pmod(F.xxhash64("vid"), F.lit(blocks)))
    cells = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long")))
    left = rows.select("vid", "attrs", "block", cells.alias("other"), F.lit(0).alias("side"))
    right = rows.select("vid", "attrs", F.col("block").alias("other"), F.lit(1).alias("side"), cells.alias("block"))
    return _best(left.unionByName(right).groupBy("block", "other").applyInArrow(_cell(k), OUT), k)


def knn_sparse(attrs: DataFrame, k: int) -> DataFrame:
    """Exact on sparse attributes (vid, dim, x): dot products by a join on the dimension; pairs without a common dimension have cosine 0 and are left out."""
    norms = attrs.groupBy("vid").agg(F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("n"))
    unit = attrs.join(norms, "vid").where("n > 0").select("vid", "dim", (F.col("x") / F.col("n")).alias("u"))
    a, b = (unit.select("dim", F.col("vid").alias(v), F.col("u").alias(u)) for v, u in (("vid", "ua"), ("nbr", "ub")))
    pairs = a.join(b, "dim").where("vid != nbr").groupBy("vid", "nbr").agg(F.round(F.sum(F.col("ua") * F.col("ub")), 12).alias("cos"))
    return _best(pairs, k)


def _search(coded: DataFrame, k: int) -> DataFrame:
    """k best of (vid, attrs, homes, looks): a row is compared with the rows that have one of its `looks` among their `homes`.

    Cells go to tasks as vectors of both sides; only the k best of a cell come out. A cell with more than TILE rows on a side is dealt
    out in tiles by hash, all of which meet: more tasks, the same result.
    """
    coded = cut(coded, "cells")
    sides = [coded.select(F.explode(c).alias("cell"), "vid", "attrs", F.lit(s).alias("side")) for s, c in ((0, "looks"), (1, "homes"))]
    both = sides[0].unionByName(sides[1])
    sizes = both.groupBy("cell").agg(*[F.count(F.when(F.col("side") == s, 1)).alias(f"n{s}") for s in (0, 1)]).where((F.col("n0") > TILE) | (F.col("n1") > TILE))
    tiles = small(cut(sizes.select("cell", *[F.ceil(F.col(f"n{s}") / TILE).alias(f"t{s}") for s in (0, 1)]), "tiles"))
    own = lambda s: F.pmod(F.xxhash64("vid"), F.coalesce(F.col(f"t{s}"), F.lit(1)))
    every = lambda s: F.sequence(F.lit(0).cast("long"), F.greatest(F.coalesce(F.col(f"t{s}"), F.lit(1)), F.lit(1)) - 1)
    at = F.when(F.col("side") == 0, F.transform(every(1), lambda j: F.struct(own(0).alias("i"), j.alias("j")))).otherwise(F.transform(every(0), lambda i: F.struct(i.alias("i"), own(1).alias("j"))))
    dealt = both.join(tiles, "cell", "left").select("cell", "vid", "attrs", "side", F.explode(at).alias("at")).select("cell", "at.i", "at.j", "vid", "attrs", "side")
    found = dealt.groupBy("cell", "i", "j").applyInArrow(_cell(k), OUT)
    return _best(found.groupBy("vid", "nbr").agg(F.max("cos").alias("cos")), k)


def _by_vector(nodes: DataFrame, k: int, code) -> DataFrame:
    """Neighbours by a search among distinct vectors only, so that rows with one vector never meet in a cell.

    `code(vectors, n, q)` gives (vid, attrs, homes, looks). The k + 1 least vids of each vector stand for all rows that have it.
    """
    rows = cut(_rows(nodes), "vectors")
    distinct = rows.groupBy("attrs").agg(F.min("vid").alias("vid"))
    n, q = _width(distinct)
    if not n:
        return nodes.sparkSession.createDataFrame([], OUT)
    distinct = cut(distinct.select("vid", "attrs"), "distinct")
    member = cut(rows.join(distinct.withColumnRenamed("vid", "head"), "attrs").select("head", "vid", F.exists("attrs", lambda x: x != 0).cast("double").alias("own")), "members")
    first = Window.partitionBy("head").orderBy("vid")
    few = member.withColumn("r", F.row_number().over(first)).where(F.col("r") <= k + 1).drop("r")
    near = _search(code(_even(distinct, q), n, q), k)
    reach = near.join(few.select(F.col("head").alias("nbr"), F.col("vid").alias("other")), "nbr").select(F.col("vid").alias("head"), F.col("other").alias("nbr"), "cos")
    reach = reach.unionByName(few.select("head", F.col("vid").alias("nbr"), F.col("own").alias("cos")))
    w = Window.partitionBy("head").orderBy(F.desc("cos"), "nbr")
    reach = reach.withColumn("r", F.row_number().over(w)).where(F.col("r") <= k + 1).drop("r")
    return _best(member.select("head", "vid").join(reach, "head").where("vid != nbr").select("vid", "nbr", "cos"), k)


def knn_lsh(nodes: DataFrame, k: int, bits: int | None = None, tables: int = 24, flips: int = 3, seed: int = 7) -> DataFrame:
    """Approximate: random hyperplanes give each vector a bucket per table; it looks there and, per table, in the `flips` buckets beyond
    its nearest planes. Where `bits` is not given, buckets hold about 256 vectors at every size of the input.
    """

    def code(distinct, n, q):
        b = min(bits if bits is not None else max(0, round(np.log2(max(n, 1) / 256))), 40)
        planes = np.random.default_rng(seed).standard_normal((q, b * tables))
        powers, base = 1 << np.arange(b, dtype=np.int64), np.arange(tables, dtype=np.int64) << b

        def run(batches):
            for batch in batches:
                far = (_matrix(batch.column(1)) @ planes).reshape(batch.num_rows, tables, b)
                home = ((far > 0) * powers).sum(2) + base
                turn = np.argsort(np.abs(far), axis=2, kind="stable")[:, :, :flips]
                looks = np.concatenate([home[:, :, None], (home[:, :, None] ^ (1 << turn.astype(np.int64)))], axis=2).reshape(batch.num_rows, -1)
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *(pa.array(c.tolist(), pa.list_(pa.int64())) for c in (home, looks))], ["vid", "attrs", "homes", "looks"])

        return distinct.mapInArrow(run, CODED)

    return _by_vector(nodes, k, code)


def _probes(distinct: DataFrame, centroids: np.ndarray, k: int, recall: float, seed: int, most: int = 256) -> int:
    """How many lists hold `recall` of the true k nearest of `most` hash-chosen vectors, each compared with all vectors."""
    asked = distinct.orderBy(F.xxhash64("vid", F.lit(seed)), "vid").limit(most).collect()
    ids, x = np.array([r["vid"] for r in asked]), _matrix([r["attrs"] for r in asked])
    norms = (centroids ** 2).sum(1)
    place = np.argsort(np.argsort(norms - 2 * (x @ centroids.T), axis=1, kind="stable"), axis=1)

    def run(batches):
        for batch in batches:
            v, y = batch.column(0).to_numpy(), _matrix(batch.column(1))
            vid, nbr, cos = _top(ids, x, v, y, k)
            order, row = np.argsort(v), {i: n for n, i in enumerate(ids)}
            home = np.argmin(norms - 2 * (y @ centroids.T), axis=1)[order[np.searchsorted(v, nbr, sorter=order)]]
            rank = place[np.array([row[i] for i in vid], np.int64), home]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in (vid, nbr, cos, rank)], ["vid", "nbr", "cos", "rank"])

    found = _best(distinct.select("vid", "attrs").mapInArrow(run, OUT + ", rank long").withColumnRenamed("rank", "list"), k)
    counts = sorted((r["list"], r["n"]) for r in found.groupBy("list").agg(F.count("*").alias("n")).collect())
    reached = np.cumsum([n for _, n in counts])
    return int(counts[int(np.searchsorted(reached, recall * reached[-1]))][0]) + 1 if counts else 1


def knn_ivf(nodes: DataFrame, k: int, lists: int | None = None, probe: int | None = None, recall: float = 0.95, seed: int = 7) -> DataFrame:
    """Approximate: k-means lists of unit vectors; each vector looks through the lists of its `probe` nearest centroids.

    Where `lists` is not given, TILE vectors or fewer are one list, which is exact; more are dealt to lists of about 256 vectors, until
    the centroids fill the broadcast limit. They are fitted on about 64 * `lists` hash-chosen vectors; every vector is then put in a
    list. Where `probe` is not given, it is the number of lists that reaches `recall` on 256 hash-chosen vectors, searched in full:
    few lists where vectors cluster, many where they do not.
    """
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    def code(distinct, n, q):
        many = lists or (1 if n <= TILE else max(1, min(-(-n // 256), 65_536, BROADCAST_BYTES // (8 * max(q, 1)))))
        if many == 1 or not q:
            return distinct.withColumn("homes", F.array(F.lit(0).cast("long"))).withColumn("looks", F.col("homes"))
        length = F.sqrt(F.aggregate("attrs", F.lit(0.0), lambda s, x: s + x * x))
        unit = distinct.select("vid", F.when(length > 0, F.transform("attrs", lambda x: x / length)).otherwise(F.col("attrs")).alias("x"))
        share = min(1.0, 64 * many / n)
        sample = unit.where(F.pmod(F.xxhash64("vid", F.lit(seed)), F.lit(1 << 20)) < int(share * (1 << 20)) + 1)
        model = KMeans(k=many, seed=seed, maxIter=8, featuresCol="f").fit(cut(sample.orderBy("vid"), "sample").select(array_to_vector("x").alias("f")))
        centroids = np.array(model.clusterCenters())
        norms, seek = (centroids ** 2).sum(1), min(probe or _probes(distinct, centroids, k, recall, seed), len(centroids))

        def run(batches):
            for batch in batches:
                order = np.argsort(norms - 2 * (_matrix(batch.column(1)) @ centroids.T), axis=1, kind="stable")[:, :seek]
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *(pa.array(c.tolist(), pa.list_(pa.int64())) for c in (order[:, :1], order))], ["vid", "attrs", "homes", "looks"])

        return distinct.mapInArrow(run, CODED)

    return _by_vector(nodes, k, code)


def recall(found: DataFrame, exact: DataFrame) -> DataFrame:
    """One row (recall): share of the exact neighbours found; a neighbour as near as the exact last one counts."""
    last = exact.groupBy("vid").agg(F.min("cos").alias("last"), F.count("*").alias("k"))
    hit = found.join(last, "vid").where("cos >= last").groupBy("vid").agg(F.count("*").alias("hits"))
    return last.join(hit, "vid", "left").agg((F.sum(F.least(F.coalesce("hits", F.lit(0)), F.col("k"))) / F.sum("k")).alias("recall"))
