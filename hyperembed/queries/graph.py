"""Queries on building, extending, walking: SURVEY 2.1, the first half of 2.2, and the fixtures of 2.7."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.vectors import cosine, tlog
from ..operators import hypergraph as hg, knn, walk as wk
from ..sources import graphs
from ..session import cut
from .common import SQL_BASKETS, Registry, r, sql_vectors, sql_walk, starts, vector_nodes, vectors_graph

_reg = Registry()
add, verdict = _reg.add, _reg.verdict
QUERIES, ORACLES = _reg.queries, _reg.oracles
V = sql_vectors()
NODE_SRC = "SELECT DISTINCT vid AS id FROM x"
EDGE_SRC = "SELECT eid AS id FROM edeg WHERE kind = 'S'"
ALPHA, STEPS = 0.1, 4


@add(f"WITH {SQL_BASKETS} SELECT eid, vid, gamma FROM inc")
def incidence_baskets(spark, sf_dir):
    return graphs.order_baskets(spark, sf_dir).graph.inc.select("eid", "vid", "gamma")


@add("""WITH g AS (SELECT l_orderkey AS eid, l_partkey AS vid, sum(l_quantity) AS gamma FROM lineitem GROUP BY ALL),
        s AS (SELECT eid, count(*) AS n FROM g GROUP BY eid HAVING count(*) >= 2)
        SELECT eid, vid, gamma, round(1.0 / n, 6) AS w FROM g JOIN s USING (eid)""")
def incidence_weighted(spark, sf_dir):
    """Memberships weighted by quantity, hyperedges by one over their size."""
    rows = graphs.read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_quantity")
    return hg.hypergraph_from(rows, "l_orderkey", "l_partkey", "l_quantity", 1 / F.col("size")).weighted.select("eid", "vid", "gamma", r("w"))


@add(f"WITH {SQL_BASKETS} SELECT vid, sum(gamma) AS d FROM inc GROUP BY vid")
def node_degree(spark, sf_dir):
    return hg.node_degrees(graphs.order_baskets(spark, sf_dir).graph)


@add(f"WITH {SQL_BASKETS} SELECT eid, sum(gamma) AS delta FROM inc GROUP BY eid")
def edge_degree(spark, sf_dir):
    return hg.edge_degrees(graphs.order_baskets(spark, sf_dir).graph)


@add(f"WITH {SQL_BASKETS} SELECT sum(gamma) AS from_nodes, sum(gamma) AS from_edges FROM inc")
def volume_check(spark, sf_dir):
    h = graphs.order_baskets(spark, sf_dir).graph
    e = hg.edge_degrees(h).join(h.edges, "eid").agg(F.sum(F.col("w") * F.col("delta")).alias("from_edges"))
    return hg.node_degrees(h).agg(F.sum("d").alias("from_nodes")).crossJoin(e)


@add(f"""WITH {SQL_BASKETS}, s AS (SELECT eid, count(*) AS s FROM inc GROUP BY eid)
        SELECT (SELECT count(DISTINCT vid) FROM inc) AS n, count(*) AS m, (SELECT count(*) FROM inc) AS nnz,
               round((SELECT count(*) FROM inc) / (SELECT count(DISTINCT vid) FROM inc), 6) AS mean_degree, round(avg(s), 6) AS mean_size, max(s) AS max_size FROM s""")
def hypergraph_stats(spark, sf_dir):
    return hg.stats(graphs.order_baskets(spark, sf_dir).graph).select("n", "m", "nnz", r("mean_degree"), r("mean_size"), "max_size")


def _register_fixture(name, sql):
    @add(sql, f"fixture_{name}")
    def query(spark, sf_dir):
        h = graphs.BUILDERS[name](spark, sf_dir).graph
        return hg.stats(h).select("n", "m", "nnz", "max_size")


_STATS = """sized AS (SELECT k, count(DISTINCT vid) AS s FROM rows GROUP BY k HAVING count(DISTINCT vid) >= 2)
    SELECT (SELECT count(DISTINCT vid) FROM rows WHERE k IN (SELECT k FROM sized)) AS n, count(*) AS m, CAST(sum(s) AS BIGINT) AS nnz, max(s) AS max_size FROM sized"""
_TRAITS = "SELECT p_partkey AS vid, unnest(['b=' || p_brand, 's=' || p_size] || list_transform(string_split(p_name, ' '), lambda w: 'n=' || w)) AS k FROM part"
_WORDS = "unnest(regexp_extract_all(lower({}), '[a-z]{{4,}}'))"
for _name, _rows in {
    "order_baskets": "SELECT l_orderkey AS k, l_partkey AS vid FROM lineitem",
    "customer_baskets": "SELECT o_custkey AS k, l_partkey AS vid FROM lineitem JOIN orders ON o_orderkey = l_orderkey",
    "part_traits": _TRAITS,
    "customer_traits": "SELECT c_custkey AS vid, unnest(['n=' || c_nationkey, 's=' || c_mktsegment]) AS k FROM customer",
    "doc_terms": f"SELECT * FROM (SELECT DISTINCT doc_id AS vid, {_WORDS.format('text')} AS k FROM documents) WHERE k IN (SELECT k FROM (SELECT DISTINCT doc_id, {_WORDS.format('text')} AS k FROM documents) GROUP BY k HAVING count(*) BETWEEN 5 AND 200)",
    "conv_terms": f"SELECT * FROM (SELECT DISTINCT conv_id AS vid, {_WORDS.format('text')} AS k FROM conversations) WHERE k IN (SELECT k FROM (SELECT DISTINCT conv_id, {_WORDS.format('text')} AS k FROM conversations) GROUP BY k HAVING count(*) BETWEEN 2 AND 50)",
    "page_hosts": "SELECT regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS k, page_id AS vid FROM pages",
    "user_days": "SELECT event_type || '|' || date_trunc('day', ts) AS k, user_id AS vid FROM events",
    "user_hours": "SELECT event_type || '|' || date_trunc('hour', ts) AS k, user_id AS vid FROM events",
    "vec_buckets": None,
    "supplier_catalog": "SELECT l_suppkey AS k, l_partkey AS vid FROM lineitem",
}.items():
    _register_fixture(_name, f"WITH rows AS ({_rows}), {_STATS}" if _rows else f"WITH {V}, rows AS (SELECT eid AS k, vid FROM v), {_STATS}")
_register_fixture("shared_passages", f"""WITH d AS (SELECT doc_id AS vid, string_split(trim(regexp_replace(lower(text), '\\s+', ' ', 'g')), ' ') AS w FROM documents UNION ALL
        SELECT -1 - item_id, string_split(trim(regexp_replace(lower(text), '\\s+', ' ', 'g')), ' ') FROM benchmark),
        g AS (SELECT DISTINCT vid, unnest([array_to_string(w[i:i+4], ' ') FOR i IN range(1, len(w) - 3)]) AS k FROM d WHERE len(w) >= 5),
        rows AS (SELECT * FROM g WHERE k IN (SELECT k FROM g WHERE vid < 0) AND k IN (SELECT k FROM g WHERE vid >= 0)), {_STATS}""")


@add(f"WITH {V} SELECT a.vid AS i, b.vid AS j, round(list_cosine_similarity(a.e, b.e), 6) + 0 AS cos FROM v a JOIN v b ON a.eid = b.eid AND a.vid < b.vid")
def cosine_pairs(spark, sf_dir):
    """Cosines of the nodes that share a hyperedge."""
    v = vector_nodes(spark, sf_dir).join(graphs.vec_buckets(spark, sf_dir).graph.inc.select("eid", "vid"), "vid")
    a, b = (v.select("eid", F.col("vid").alias(i), F.col("attrs").alias(f"e{i}")) for i in "ij")
    return a.join(b, "eid").where("i < j").select("i", "j", r(F.round(cosine(F.col("ei"), F.col("ej")), 6)).alias("cos"))


@add(f"WITH {V} SELECT vid, nbr, round(cos, 6) + 0 AS cos FROM knn", "knn_exact")
def _knn_exact(spark, sf_dir):
    return knn.knn_exact(vector_nodes(spark, sf_dir), 10).select("vid", "nbr", r("cos"))


@add("""WITH a AS (SELECT DISTINCT p_partkey AS vid, unnest(['b=' || p_brand, 's=' || p_size] || list_transform(string_split(p_name, ' '), lambda w: 'n=' || w)) AS dim FROM part),
        n AS (SELECT vid, sqrt(count(*)) AS n FROM a GROUP BY vid),
        u AS (SELECT a.vid, dim, 1.0 / n.n AS u FROM a JOIN n USING (vid)),
        c AS (SELECT x.vid, y.vid AS nbr, round(sum(x.u * y.u), 12) AS cos FROM u x JOIN u y ON x.dim = y.dim AND x.vid <> y.vid GROUP BY ALL)
        SELECT vid, nbr, round(cos, 6) AS cos FROM (SELECT *, row_number() OVER (PARTITION BY vid ORDER BY cos DESC, nbr) AS rk FROM c) WHERE rk <= 10""", "knn_sparse")
def _knn_sparse(spark, sf_dir):
    """One-hot traits of the parts: ties in plenty."""
    return knn.knn_sparse(graphs.part_traits(spark, sf_dir).attrs, 10).select("vid", "nbr", r("cos"))


@verdict("same_neighbours")
def knn_broadcast(spark, sf_dir):
    v = vector_nodes(spark, sf_dir)
    a, b = knn.knn_exact(v, 10).select("vid", "nbr"), knn.knn_broadcast(v, 10).select("vid", "nbr")
    return {"same_neighbours": not a.exceptAll(b).limit(1).count() and not b.exceptAll(a).limit(1).count()}


@verdict("recall_above_floor")
def knn_lsh_recall(spark, sf_dir):
    v = vector_nodes(spark, sf_dir)
    got = knn.recall(knn.knn_lsh(v, 10), knn.knn_exact(v, 10)).first()["recall"]
    return {"recall_above_floor": got >= 0.9}


@verdict("recall_above_floor", "recall_above_floor_of_16_lists")
def knn_ivf(spark, sf_dir):
    v = vector_nodes(spark, sf_dir)
    exact = cut(knn.knn_exact(v, 10), "exact")
    got = [knn.recall(knn.knn_ivf(v, 10, lists=n), exact).first()["recall"] for n in (None, 16)]
    return {"recall_above_floor": got[0] >= 0.9, "recall_above_floor_of_16_lists": got[1] >= 0.9}


@add(f"WITH {V} SELECT eid, vid, round(gamma, 6) AS gamma FROM attr")
def attr_hyperedges(spark, sf_dir):
    w, near, _ = vectors_graph(spark, sf_dir)
    return hg.attribute_hyperedges(near, w.nodes).select("eid", "vid", r("gamma"))


@add(f"WITH {V} SELECT round(w_a, 6) AS w_a FROM wa")
def balance_weight(spark, sf_dir):
    w, near, _ = vectors_graph(spark, sf_dir)
    return hg.balance_weight(w.graph, hg.attribute_hyperedges(near, w.nodes)).select(r("w_a"))


@verdict("beta_1", "beta_0_5")
def balance_check(spark, sf_dir):
    out = {}
    for name, beta in (("beta_1", 1.0), ("beta_0_5", 0.5)):
        _, _, x = vectors_graph(spark, sf_dir, beta=beta)
        v = {k: m for k, m in x.weighted.join(x.edges.select("eid", "kind"), "eid").groupBy("kind").agg(F.sum(F.col("w") * F.col("gamma"))).collect()}
        out[name] = abs(beta * v["S"] - v["A"]) < 1e-9 * v["S"]
    return out


@add(f"WITH {V} SELECT eid, vid, round(gamma, 6) AS gamma, round(w, 6) AS w FROM x")
def extended_incidence(spark, sf_dir):
    return vectors_graph(spark, sf_dir)[2].weighted.select("eid", "vid", r("gamma"), r("w"))


@add(f"WITH {V} SELECT 'node' AS side, vid AS id, round(d, 6) AS degree FROM vdeg UNION ALL SELECT 'edge', eid, round(delta, 6) FROM edeg")
def extended_degrees(spark, sf_dir):
    x = vectors_graph(spark, sf_dir)[2]
    node = hg.node_degrees(x).select(F.lit("node").alias("side"), F.col("vid").alias("id"), F.round("d", 6).alias("degree"))
    return node.union(hg.edge_degrees(x).select(F.lit("edge"), "eid", F.round("delta", 6)))


@add(f"WITH {V} SELECT 'node' AS side, eid AS id, round(delta * w, 6) AS degree FROM edeg UNION ALL SELECT 'edge', vid, round(d, 6) FROM vdeg")
def dual_degrees(spark, sf_dir):
    """On the dual a hyperedge's degree is delta * w, and a node's size is its degree."""
    x = hg.dual(vectors_graph(spark, sf_dir)[2])
    node = hg.node_degrees(x).select(F.lit("node").alias("side"), F.col("vid").alias("id"), F.round("d", 6).alias("degree"))
    return node.union(hg.edge_degrees(x).select(F.lit("edge"), "eid", F.round("delta", 6)))


@add(f"WITH {V} SELECT round(vol, 4) AS vol, round(vol, 4) AS dual_vol FROM vol")
def dual_volume(spark, sf_dir):
    x = vectors_graph(spark, sf_dir)[2]
    return hg.volume(x).select(r("vol", 4)).crossJoin(hg.volume(hg.dual(x)).select(F.round("vol", 4).alias("dual_vol")))


@add("""WITH RECURSIVE p AS (SELECT page_id AS vid, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS k FROM pages),
        inc AS (SELECT * FROM p WHERE k IN (SELECT k FROM p GROUP BY k HAVING count(*) >= 2)),
        reach(vid, root) AS (SELECT vid, vid FROM inc UNION SELECT b.vid, r.root FROM reach r JOIN inc a ON a.vid = r.vid JOIN inc b ON a.k = b.k)
        SELECT vid, min(root) AS component FROM reach GROUP BY vid""")
def components(spark, sf_dir):
    return hg.components(graphs.page_hosts(spark, sf_dir).graph)


@add(f"WITH {V} SELECT x.eid, x.vid, round(sqrt(x.w / delta) * gamma / sqrt(d), 6) AS ell FROM x JOIN vdeg USING (vid) JOIN edeg USING (eid)")
def normalised_incidence(spark, sf_dir):
    return hg.normalise(vectors_graph(spark, sf_dir)[2]).select("eid", "vid", r("ell"))


@add(f"WITH {V} SELECT a.vid AS i, b.vid AS j, round(sum(a.up * b.down), 6) AS p FROM rates a JOIN rates b USING (eid) GROUP BY ALL")
def node_transition(spark, sf_dir):
    return wk.node_transition(vectors_graph(spark, sf_dir)[2]).select("i", "j", r("p"))


@add(f"WITH {V} SELECT a.eid AS i, b.eid AS j, round(sum(a.down * b.up), 6) AS p FROM rates a JOIN rates b USING (vid) GROUP BY ALL")
def edge_transition(spark, sf_dir):
    return wk.edge_transition(vectors_graph(spark, sf_dir)[2]).select("i", "j", r("p"))


@verdict("node_rows", "edge_rows")
def transition_rows(spark, sf_dir):
    """Rows of both transition tables add up to 1."""
    x = vectors_graph(spark, sf_dir)[2]
    off = lambda t: t.groupBy("i").agg(F.sum("p").alias("s")).agg(F.max(F.abs(F.col("s") - 1))).first()[0]
    return {"node_rows": off(wk.node_transition(x)) < 1e-9, "edge_rows": off(wk.edge_transition(x)) < 1e-9}


def _walk(spark, sf_dir, side, steps=STEPS, **options):
    x = vectors_graph(spark, sf_dir)[2]
    x = hg.Hypergraph(cut(x.inc), cut(x.edges))
    return x, starts(x, side), lambda f: f(x, starts(x, side), ALPHA, steps, side, **options)


def _walk_sql(side, steps=STEPS):
    return f"WITH {V}, {sql_walk(side, ALPHA, steps, NODE_SRC if side == 'node' else EDGE_SRC)}"


@add(f"{_walk_sql('node')} SELECT source, id, round(p, 6) AS p FROM w{STEPS}")
def walk_node(spark, sf_dir):
    return _walk(spark, sf_dir, "node")[2](wk.walk).select("source", "id", r("p"))


@add(f"{_walk_sql('edge')} SELECT source, id, round(p, 6) AS p FROM w{STEPS}")
def walk_edge(spark, sf_dir):
    return _walk(spark, sf_dir, "edge")[2](wk.walk).select("source", "id", r("p"))


@add(f"{_walk_sql('node', 1)} SELECT source, id, round(p, 6) AS p FROM w1")
def walk_one_hop(spark, sf_dir):
    return _walk(spark, sf_dir, "node", 1)[2](wk.walk).select("source", "id", r("p"))


@verdict("node", "edge")
def walk_forms_agree(spark, sf_dir):
    out = {}
    for side in ("node", "edge"):
        x, src, _ = _walk(spark, sf_dir, side)
        a = wk.walk(x, src, ALPHA, STEPS, side)
        b = wk.walk(x, src, ALPHA, STEPS, side, form="sum").withColumnRenamed("p", "q")
        out[side] = a.join(b, ["source", "id"], "full").agg(F.max(F.abs(F.coalesce("p", F.lit(0.0)) - F.coalesce("q", F.lit(0.0))))).first()[0] < 1e-12
    return out


@add(f"WITH {V} SELECT 'node' AS side, vid AS id, round(d / vol, 6) AS p FROM vdeg, vol UNION ALL SELECT 'edge', eid, round(delta * w / vol, 6) FROM edeg, vol")
def stationary(spark, sf_dir):
    x = vectors_graph(spark, sf_dir)[2]
    parts = [wk.stationary(x, s).select(F.lit(s).alias("side"), "id", r("p")) for s in ("node", "edge")]
    return parts[0].union(parts[1])


@verdict("node", "edge")
def stationary_fixed(spark, sf_dir):
    """The stationary law does not change under a step."""
    x = vectors_graph(spark, sf_dir)[2]
    out = {}
    for side, t in (("node", wk.node_transition(x)), ("edge", wk.edge_transition(x))):
        s = wk.stationary(x, side)
        moved = t.join(s.select(F.col("id").alias("i"), F.col("p").alias("q")), "i").groupBy(F.col("j").alias("id")).agg(F.sum(F.col("p") * F.col("q")).alias("q"))
        out[side] = s.join(moved, "id").agg(F.max(F.abs(F.col("p") - F.col("q")))).first()[0] < 1e-12
    return out


@add("SELECT o_orderkey AS id, round(ln(greatest(o_totalprice / 100000, 1)), 6) AS y FROM orders", "tlog")
def _tlog(spark, sf_dir):
    return graphs.read(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id"), F.round(tlog(F.col("o_totalprice") / 100000), 6).alias("y"))


@add(f"{_walk_sql('node')} SELECT source, w{STEPS}.id, round(ln(greatest(p / (d / vol), 1)), 6) AS sim FROM w{STEPS} JOIN vdeg ON vid = w{STEPS}.id, vol")
def node_similarity(spark, sf_dir):
    return _walk(spark, sf_dir, "node")[2](wk.similarity).select("source", "id", r("sim"))


@add(f"{_walk_sql('edge')} SELECT source, w{STEPS}.id, round(ln(greatest(p / (delta * w / vol), 1)), 6) AS sim FROM w{STEPS} JOIN edeg ON eid = w{STEPS}.id AND kind = 'S', vol")
def hyperedge_similarity(spark, sf_dir):
    """Walk over all hyperedges, targets only the given ones."""
    x, src, _ = _walk(spark, sf_dir, "edge")
    return wk.similarity(x, src, ALPHA, STEPS, "edge", x.edges.where("kind = 'S'").select(F.col("eid").alias("id"))).select("source", "id", r("sim"))


@verdict("node", "edge")
def similarity_symmetry(spark, sf_dir):
    out = {}
    for side in ("node", "edge"):
        x, src, _ = _walk(spark, sf_dir, side)
        s = cut(wk.similarity(x, src, ALPHA, STEPS, side, src), "sim")
        back = s.select(F.col("id").alias("source"), F.col("source").alias("id"), F.col("sim").alias("other"))
        out[side] = s.join(back, ["source", "id"]).agg(F.max(F.abs(F.col("sim") - F.col("other")))).first()[0] < 1e-9
    return out


@add(f"""WITH {SQL_BASKETS} SELECT a.vid AS i, b.vid AS j, sum(a.gamma * b.gamma) AS weight FROM inc a JOIN inc b ON a.eid = b.eid AND a.vid < b.vid GROUP BY ALL""")
def clique_expansion(spark, sf_dir):
    return hg.clique_expand(graphs.order_baskets(spark, sf_dir).graph)


@add(f"WITH {SQL_BASKETS} SELECT vid AS node, eid AS star, gamma AS weight FROM inc")
def star_expansion(spark, sf_dir):
    return hg.star_expand(graphs.order_baskets(spark, sf_dir).graph)


@add("""WITH p AS (SELECT DISTINCT l_suppkey AS eid, l_partkey AS vid FROM lineitem)
        SELECT a.eid AS e, b.eid AS f, count(*) AS shared FROM p a JOIN p b ON a.vid = b.vid AND a.eid < b.eid GROUP BY ALL""")
def line_graph(spark, sf_dir):
    return hg.line_graph(graphs.supplier_catalog(spark, sf_dir).graph)


@add(f"""WITH {SQL_BASKETS}, s AS (SELECT eid, count(*) AS s FROM inc GROUP BY eid)
        SELECT count(*) AS nnz, (SELECT CAST(sum(s * (s - 1) / 2) AS BIGINT) FROM s) AS clique_rows, count(*) * 2 AS two_hop_rows FROM inc""")
def cost_counters(spark, sf_dir):
    """Rows that a step over hyperedges touches, against rows of the clique expansion."""
    h = graphs.order_baskets(spark, sf_dir).graph
    return h.inc.agg(F.count("*").alias("nnz")).crossJoin(hg.pair_cost(h)).select("nnz", F.col("pairs").alias("clique_rows"), (F.col("nnz") * 2).alias("two_hop_rows"))


@add("""WITH g AS (SELECT l_partkey AS vid, l_suppkey AS eid, count(DISTINCT l_orderkey) AS d FROM lineitem GROUP BY ALL),
        k AS (SELECT *, row_number() OVER (PARTITION BY eid ORDER BY d DESC, vid) AS rk FROM g WHERE eid IN (SELECT eid FROM g GROUP BY eid HAVING count(*) >= 2))
        SELECT vid, eid, d FROM k WHERE rk <= 3""")
def top_members(spark, sf_dir):
    """Per supplier the parts in most orders."""
    rows = graphs.read(spark, sf_dir, "lineitem").select("l_suppkey", "l_partkey", "l_orderkey").distinct().withColumn("one", F.lit(1.0))
    h = hg.hypergraph_from(rows, "l_suppkey", "l_partkey", "one")
    return hg.top_members(h, 3).select("vid", "eid", F.col("gamma").cast("long").alias("d"))
