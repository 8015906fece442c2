"""Restart walks over hyperedges and the similarities made of them. A step is two joins with partial sums; P is never formed."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from ..functions.vectors import tlog
from ..session import cut
from .hypergraph import Hypergraph, edge_degrees, node_degrees

#: Steps between lineage cuts.
CUT_EVERY = 3


def _rates(h: Hypergraph) -> DataFrame:
    """(eid, vid, out, into, edge_out, edge_into): factors of both halves of a step, on both sides.

    Node side: u -> e with w gamma / d, e -> v with gamma / delta. Hyperedge side: e -> v with gamma / delta, v -> f with
    w gamma / d.
    """
    rows = h.weighted.join(edge_degrees(h), "eid").join(node_degrees(h), "vid")
    return rows.select("eid", "vid", (F.col("w") * F.col("gamma") / F.col("d")).alias("up"), (F.col("gamma") / F.col("delta")).alias("down"))


def node_transition(h: Hypergraph) -> DataFrame:
    """(i, j, p), for inputs small enough to look at; refuses others."""
    _small(h, "eid")
    r = _rates(h)
    a, b = r.select("eid", F.col("vid").alias("i"), "up"), r.select("eid", F.col("vid").alias("j"), "down")
    return a.join(b, "eid").groupBy("i", "j").agg(F.sum(F.col("up") * F.col("down")).alias("p"))


def edge_transition(h: Hypergraph) -> DataFrame:
    """(i, j, p) over hyperedges, with the weight of the hyperedge gone to."""
    _small(h, "vid")
    r = _rates(h)
    a, b = r.select("vid", F.col("eid").alias("i"), "down"), r.select("vid", F.col("eid").alias("j"), "up")
    return a.join(b, "vid").groupBy("i", "j").agg(F.sum(F.col("down") * F.col("up")).alias("p"))


def _small(h: Hypergraph, by: str, most: int = 100_000_000) -> None:
    pairs = h.inc.groupBy(by).agg(F.count("*").alias("s")).agg(F.sum(F.col("s") * F.col("s"))).first()[0] or 0
    if pairs > most:
        raise ValueError(f"the transition table would have up to {pairs} entries; walk from chosen sources instead")


def stationary(h: Hypergraph, side: str = "node") -> DataFrame:
    """(id, p): d / vol of nodes, or w delta / vol of hyperedges."""
    rows = h.weighted.groupBy(F.col("vid" if side == "node" else "eid").alias("id")).agg(F.sum(F.col("w") * F.col("gamma")).alias("mass"))
    total = rows.agg(F.sum("mass").alias("vol"))
    return rows.crossJoin(F.broadcast(total)).select("id", (F.col("mass") / F.col("vol")).alias("p"))


def walk(h: Hypergraph, sources: DataFrame, alpha: float = 0.1, steps: int = 10, side: str = "node", form: str = "restart") -> DataFrame:
    """(source, id, p) after `steps` steps from each `id` of `sources`: with probability alpha back to the source.

    form 'restart' repeats alpha * start + (1 - alpha) * step; form 'sum' adds up the powers, which is the same.
    """
    rates = cut(_rates(h), "rates")
    here, there, first, second = ("vid", "eid", "up", "down") if side == "node" else ("eid", "vid", "down", "up")
    start = sources.select(F.col("id").alias("source"), "id", F.lit(1.0).alias("p"))

    def step(x: DataFrame) -> DataFrame:
        half = x.join(rates.select(F.col(here).alias("id"), F.col(there).alias("mid"), F.col(first).alias("f")), "id")
        half = half.groupBy("source", "mid").agg(F.sum(F.col("p") * F.col("f")).alias("p"))
        full = half.join(rates.select(F.col(there).alias("mid"), F.col(here).alias("id"), F.col(second).alias("f")), "mid")
        return full.groupBy("source", "id").agg(F.sum(F.col("p") * F.col("f")).alias("p"))

    scaled = lambda df, k: df.select("source", "id", (F.col("p") * k).alias("p"))
    x = start
    if form == "restart":
        for t in range(steps):
            x = scaled(step(x), 1 - alpha).unionByName(scaled(start, alpha)).groupBy("source", "id").agg(F.sum("p").alias("p"))
            if (t + 1) % CUT_EVERY == 0 and t + 1 < steps:
                x = cut(x, "walk")
        return x
    parts = [scaled(start, alpha if steps else 1.0)]
    for t in range(1, steps + 1):
        x = cut(step(x), "walk") if t % CUT_EVERY == 0 else step(x)
        parts.append(scaled(x, (1 - alpha) ** t * (alpha if t < steps else 1.0)))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.groupBy("source", "id").agg(F.sum("p").alias("p"))


def similarity(h: Hypergraph, sources: DataFrame, alpha: float = 0.1, steps: int = 10, side: str = "node", targets: DataFrame | None = None) -> DataFrame:
    """(source, id, sim): log of how much likelier the walk ends there than by chance, at least 0."""
    x = walk(h, sources, alpha, steps, side).join(stationary(h, side).withColumnRenamed("p", "chance"), "id")
    if targets is not None:
        x = x.join(targets.select("id"), "id", "left_semi")
    return x.select("source", "id", tlog(F.col("p") / F.col("chance")).alias("sim"))


def objective(sim: DataFrame, vectors: DataFrame) -> DataFrame:
    """One row (objective): squared distance of similarities and dot products over the pairs of `sim`."""
    from ..functions.vectors import dot

    a, b = (vectors.select(F.col("id").alias(i), F.col("vec").alias(v)) for i, v in (("source", "va"), ("id", "vb")))
    return sim.join(a, "source").join(b, "id").agg(F.sum(F.pow(F.col("sim") - dot(F.col("va"), F.col("vb")), 2)).alias("objective"))
