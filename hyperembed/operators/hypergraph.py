"""Attributed hypergraphs as incidence tables: construction, degrees, extension by attribute hyperedges, dual, components.

Incidence rows are (eid, vid, gamma); edges are (eid, kind, w), kind 'S' for given hyperedges and 'A' for those made of
attribute neighbours. All steps are joins and partial sums; no table of n x n is formed here.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window, functions as F

from ..session import cut

#: Attribute hyperedge of node v has the id ATTR + v.
ATTR = 1 << 40


@dataclass(frozen=True)
class Hypergraph:
    """inc (eid, vid, gamma), edges (eid, kind, w)."""

    inc: DataFrame
    edges: DataFrame

    @property
    def weighted(self) -> DataFrame:
        """(eid, vid, gamma, w)."""
        return self.inc.join(self.edges.select("eid", "w"), "eid")


@dataclass(frozen=True)
class Weighed(Hypergraph):
    """With its weighted memberships written out, so that they are joined once."""

    rows: DataFrame

    @property
    def weighted(self) -> DataFrame:
        return self.rows


def weighed(h: Hypergraph) -> Hypergraph:
    return h if isinstance(h, Weighed) else Weighed(h.inc, h.edges, cut(h.weighted.select("eid", "vid", "gamma", "w"), "memberships"))


def hypergraph_from(df: DataFrame, eid, vid, gamma=None, w=None, min_size: int = 2) -> Hypergraph:
    """Hyperedges of at least `min_size` distinct nodes from rows (one per membership).

    Repeated memberships collapse: gamma is the sum of `gamma` over the rows, or 1. `w` is an expression over
    (eid, size), or 1. Rows with a null id are no memberships; memberships of weight zero or less are dropped.
    """
    as_col = lambda c: c if isinstance(c, Column) else F.col(c)
    rows = df.select(as_col(eid).alias("eid"), as_col(vid).alias("vid"), (F.lit(1.0) if gamma is None else as_col(gamma)).cast("double").alias("g"))
    inc = rows.where("eid is not null and vid is not null").groupBy("eid", "vid").agg((F.lit(1.0) if gamma is None else F.sum("g")).alias("gamma"))
    inc = inc.where("gamma > 0")
    size = inc.groupBy("eid").agg(F.count("*").alias("size")).where(F.col("size") >= min_size)
    edges = size.select("eid", F.lit("S").alias("kind"), (F.lit(1.0) if w is None else w).cast("double").alias("w"))
    return Hypergraph(inc.join(edges.select("eid"), "eid", "left_semi"), edges)


def node_degrees(h: Hypergraph) -> DataFrame:
    """(vid, d): sum of w * gamma."""
    return h.weighted.groupBy("vid").agg(F.sum(F.col("w") * F.col("gamma")).alias("d"))


def edge_degrees(h: Hypergraph) -> DataFrame:
    """(eid, delta): sum of gamma."""
    return h.inc.groupBy("eid").agg(F.sum("gamma").alias("delta"))


def volume(h: Hypergraph) -> DataFrame:
    """One row (vol)."""
    return h.weighted.agg(F.sum(F.col("w") * F.col("gamma")).alias("vol"))


def stats(h: Hypergraph) -> DataFrame:
    """One row: nodes, hyperedges, incidence rows, mean node degree, mean hyperedge size, largest hyperedge."""
    size = h.inc.groupBy("eid").agg(F.count("*").alias("s"))
    a = h.inc.agg(F.count_distinct("vid").alias("n"), F.count("*").alias("nnz"))
    b = size.agg(F.count("*").alias("m"), F.avg("s").alias("mean_size"), F.max("s").alias("max_size"))
    return a.crossJoin(b).select("n", "m", "nnz", (F.col("nnz") / F.col("n")).alias("mean_degree"), "mean_size", "max_size")


def attribute_hyperedges(neighbours: DataFrame, vids: DataFrame) -> DataFrame:
    """Incidence rows of kind 'A' from neighbours (vid, nbr, cos): each node with itself (weight 1) and its neighbours; cosines under 0 go."""
    near = neighbours.where("cos > 0").select((F.lit(ATTR) + F.col("vid")).alias("eid"), F.col("nbr").alias("vid"), F.col("cos").cast("double").alias("gamma"))
    own = vids.select((F.lit(ATTR) + F.col("vid")).alias("eid"), F.col("vid"), F.lit(1.0).alias("gamma"))
    return near.unionByName(own)


def balance_weight(h: Hypergraph, attr_inc: DataFrame, beta: float = 1.0) -> DataFrame:
    """One row (w_a): attribute hyperedges together get beta times the volume of the given ones."""
    s = h.weighted.agg(F.sum(F.col("w") * F.col("gamma")).alias("vol_s"))
    a = attr_inc.agg(F.sum("gamma").alias("sum_a"))
    return s.crossJoin(a).select((F.lit(float(beta)) * F.col("vol_s") / F.col("sum_a")).alias("w_a"))


def extend(h: Hypergraph, neighbours: DataFrame, vids: DataFrame, beta: float = 1.0, w_attr: float | None = None) -> Hypergraph:
    """The hypergraph with one attribute hyperedge per node. `vids` are all nodes, also those in no hyperedge."""
    attr = attribute_hyperedges(neighbours, vids)
    weight = balance_weight(h, attr, beta) if w_attr is None else h.inc.sparkSession.range(1).select(F.lit(float(w_attr)).alias("w_a"))
    # One row against one row per node: the broadcast holds a single number.
    edges = vids.select((F.lit(ATTR) + F.col("vid")).alias("eid")).crossJoin(F.broadcast(weight)).select("eid", F.lit("A").alias("kind"), F.col("w_a").alias("w"))
    return Hypergraph(h.inc.select("eid", "vid", "gamma").unionByName(attr), h.edges.unionByName(edges))


def dual(h: Hypergraph) -> Hypergraph:
    """Nodes and hyperedges change places; memberships take the hyperedge weight, hyperedge weights become 1."""
    inc = h.weighted.select(F.col("vid").alias("eid"), F.col("eid").alias("vid"), (F.col("w") * F.col("gamma")).alias("gamma"))
    return Hypergraph(inc, h.inc.select(F.col("vid").alias("eid")).distinct().select("eid", F.lit("S").alias("kind"), F.lit(1.0).alias("w")))


def normalise(h: Hypergraph) -> DataFrame:
    """(eid, vid, ell): sqrt(w / delta) * gamma / sqrt(d)."""
    rows = h.weighted.join(edge_degrees(h), "eid").join(node_degrees(h), "vid")
    return rows.select("eid", "vid", (F.sqrt(F.col("w") / F.col("delta")) * F.col("gamma") / F.sqrt("d")).alias("ell"))


def components(h: Hypergraph) -> DataFrame:
    """(vid, component): least node reachable. Labels spread over hyperedges, with a jump to the label's own label each round."""
    inc = cut(h.inc.select("eid", "vid"), "inc")
    label = cut(inc.select("vid").distinct().select("vid", F.col("vid").alias("label")), "label")
    while True:
        edge = inc.join(label, "vid").groupBy("eid").agg(F.min("label").alias("label"))
        node = inc.join(edge, "eid").groupBy("vid").agg(F.min("label").alias("label"))
        jump = node.select(F.col("vid").alias("label"), F.col("label").alias("further"))
        new = cut(node.join(jump, "label").select("vid", F.least("label", "further").alias("label")), "label")
        moved = new.join(label.withColumnRenamed("label", "old"), "vid").where("label != old").limit(1).count()
        label = new
        if not moved:
            return label.select("vid", F.col("label").alias("component"))


# Expansions to graphs.


def pair_cost(h: Hypergraph) -> DataFrame:
    """One row (pairs): rows that expansions into pairs would make."""
    return h.inc.groupBy("eid").agg(F.count("*").alias("s")).agg(F.sum(F.col("s") * (F.col("s") - 1) / 2).cast("long").alias("pairs"))


def clique_expand(h: Hypergraph, most_pairs: int = 200_000_000) -> DataFrame:
    """(i, j, weight), i < j: co-membership summed over hyperedges, w * gamma_i * gamma_j. Refuses inputs with too many pairs."""
    pairs = pair_cost(h).first()["pairs"] or 0
    if pairs > most_pairs:
        raise ValueError(f"clique expansion would make {pairs} pairs; use walks, which take two hops instead")
    a = h.weighted.select("eid", "w", F.col("vid").alias("i"), F.col("gamma").alias("gi"))
    b = h.inc.select("eid", F.col("vid").alias("j"), F.col("gamma").alias("gj"))
    return a.join(b, "eid").where("i < j").groupBy("i", "j").agg(F.sum(F.col("w") * F.col("gi") * F.col("gj")).alias("weight"))


def star_expand(h: Hypergraph) -> DataFrame:
    """(node, star, weight): the bipartite graph of nodes and hyperedges."""
    return h.weighted.select(F.col("vid").alias("node"), F.col("eid").alias("star"), (F.col("w") * F.col("gamma")).alias("weight"))


def line_graph(h: Hypergraph, most_pairs: int = 200_000_000) -> DataFrame:
    """(e, f, shared): hyperedges with common nodes."""
    pairs = h.inc.groupBy("vid").agg(F.count("*").alias("s")).agg(F.sum(F.col("s") * (F.col("s") - 1) / 2).cast("long").alias("p")).first()["p"] or 0
    if pairs > most_pairs:
        raise ValueError(f"the line graph would make {pairs} pairs")
    a, b = (h.inc.select("vid", F.col("eid").alias(x)) for x in "ef")
    return a.join(b, "vid").where("e < f").groupBy("e", "f").agg(F.count("*").alias("shared"))


#: Nodes in more hyperedges than this are joined with themselves, which Spark can split, in place of one row with a list.
LISTED = 2000


def shared_members(h: Hypergraph) -> DataFrame:
    """(e, f, shared): as `line_graph`, for any number of pairs. Nodes go out in ranges of their ids, so that pairs of hyperedges whose
    nodes lie near each other are counted before they are sent."""
    lists = cut(h.inc.groupBy("vid").agg(F.collect_list("eid").alias("es")), "lists")
    near = lists.where(F.size("es") <= LISTED).repartitionByRange("vid").select("es", F.explode("es").alias("e"))
    pairs = near.select("e", F.explode(F.filter("es", lambda f: f > F.col("e"))).alias("f"))
    many = lists.where(F.size("es") > LISTED).select("vid", F.explode("es").alias("e"))
    far = many.join(many.withColumnRenamed("e", "f"), "vid").where("e < f").select("e", "f")
    return pairs.unionByName(far).groupBy("e", "f").agg(F.count("*").alias("shared"))


def mean_pool(vectors: DataFrame, h: Hypergraph, width: int) -> DataFrame:
    """(eid, vec): mean of the members' vectors, as `width` codegen sums."""
    rows = h.inc.select("eid", "vid").join(vectors.select(F.col("id").alias("vid"), "vec"), "vid")
    sums = rows.groupBy("eid").agg(*[F.avg(F.col("vec")[i]).alias(f"s{i}") for i in range(width)])
    return sums.select("eid", F.array(*[F.col(f"s{i}") for i in range(width)]).alias("vec"))


def top_members(h: Hypergraph, k: int) -> DataFrame:
    """(eid, vid, gamma, rank): the k strongest members of each hyperedge."""
    w = Window.partitionBy("eid").orderBy(F.desc("gamma"), "vid")
    return h.inc.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)
