"""Registration of queries, verdict tables, and shared fixtures of the queries."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..operators import hypergraph as hg, knn
from ..session import cut, small
from ..sources import graphs

BETA, NEIGHBOURS = 1.0, 10
#: Suffix of a query: the workload it runs on, over whole tables; the planted graph reads none.
WORKLOADS = {"": graphs.order_baskets, "_days": graphs.user_days, "_vectors": graphs.vec_buckets, "_planted": lambda spark, sf_dir: graphs.planted(spark)}


class Registry:
    def __init__(self):
        self.queries, self.oracles = {}, {}

    def add(self, sql: str | None = None, name: str | None = None):
        def keep(f):
            key = name or f.__name__
            self.queries[key] = f
            if sql is not None:
                self.oracles[key] = sql
            return f

        return keep

    def verdict(self, *checks: str):
        """The query gives (check_name, ok); SQL expects every check to hold."""
        rows = ", ".join(f"('{c}', true)" for c in checks)

        def keep(f):
            def run(spark: SparkSession, sf_dir: str) -> DataFrame:
                found = f(spark, sf_dir)
                return spark.createDataFrame([(c, bool(found[c])) for c in checks], "check_name string, ok boolean")

            self.queries[f.__name__] = run
            self.oracles[f.__name__] = f"SELECT check_name, ok FROM (VALUES {rows}) AS t(check_name, ok)"
            return f

        return keep


def r(column, digits: int = 6):
    """Rounded for comparison; minus zero becomes zero."""
    c = F.col(column) if isinstance(column, str) else column
    return (F.round(c, digits) + F.lit(0.0)).alias(column if isinstance(column, str) else "value")


def vectors_graph(spark: SparkSession, sf_dir: str, k: int = NEIGHBOURS, beta: float = BETA):
    """(workload, neighbours, extended hypergraph) of the embeddings table."""
    w = graphs.vec_buckets(spark, sf_dir)
    nodes = vector_nodes(spark, sf_dir)
    near = cut(knn.knn_exact(nodes, k), "near") if k else None
    if not k:
        return w, None, w.graph
    return w, near, hg.extend(w.graph, near, w.nodes, beta)


def vector_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("vid"), F.col("embedding").cast("array<double>").alias("attrs"))


def extended(spark: SparkSession, w: graphs.Workload, k: int = NEIGHBOURS, beta: float = BETA, dense: bool = True) -> hg.Hypergraph:
    """A workload with its attribute hyperedges, materialised."""
    near = knn.knn_ivf(graphs.dense_attributes(w), k) if dense else knn.knn_sparse(w.attrs, k)
    h = hg.extend(w.graph, cut(near, "near"), w.nodes, beta)
    return hg.Hypergraph(cut(h.inc, "inc"), cut(h.edges, "edges"))


def starts(h: hg.Hypergraph, side: str = "node") -> DataFrame:
    c = "vid" if side == "node" else "eid"
    ids = h.inc.select(F.col(c).alias("id")).distinct() if side == "node" else h.edges.where("kind = 'S'").select(F.col("eid").alias("id"))
    return small(ids, 16)


# SQL of the same fixtures.
SQL_BASKETS = """
    pairs AS (SELECT DISTINCT l_orderkey AS eid, l_partkey AS vid FROM lineitem),
    inc AS (SELECT eid, vid, 1.0::DOUBLE AS gamma FROM pairs WHERE eid IN (SELECT eid FROM pairs GROUP BY eid HAVING count(*) >= 2))"""


def sql_vectors(k: int = NEIGHBOURS, beta: float = BETA) -> str:
    pattern = " + ".join(f"CASE WHEN embedding[{i + 1}] > 0 THEN {1 << i} ELSE 0 END" for i in range(8))
    return f"""
    v AS (SELECT vec_id AS vid, embedding::DOUBLE[] AS e, CAST({pattern} AS BIGINT) AS eid FROM embeddings),
    inc AS (SELECT eid, vid, 1.0::DOUBLE AS gamma FROM v WHERE eid IN (SELECT eid FROM v GROUP BY eid HAVING count(*) >= 2)),
    cosines AS (SELECT a.vid, b.vid AS nbr, round(list_cosine_similarity(a.e, b.e), 12) AS cos FROM v a JOIN v b ON a.vid <> b.vid),
    knn AS (SELECT vid, nbr, cos FROM (SELECT *, row_number() OVER (PARTITION BY vid ORDER BY cos DESC, nbr) AS rk FROM cosines) WHERE rk <= {k}),
    attr AS (SELECT {hg.ATTR} + vid AS eid, nbr AS vid, cos AS gamma FROM knn WHERE cos > 0 UNION ALL SELECT {hg.ATTR} + vid, vid, 1.0 FROM v),
    wa AS (SELECT {beta} * (SELECT sum(gamma) FROM inc) / (SELECT sum(gamma) FROM attr) AS w_a),
    x AS (SELECT eid, vid, gamma, 1.0::DOUBLE AS w, 'S' AS kind FROM inc UNION ALL SELECT eid, vid, gamma, w_a, 'A' FROM attr, wa),
    vdeg AS (SELECT vid, sum(w * gamma) AS d FROM x GROUP BY vid),
    edeg AS (SELECT eid, sum(gamma) AS delta, min(w) AS w, min(kind) AS kind FROM x GROUP BY eid),
    rates AS (SELECT x.eid, x.vid, x.w * gamma / d AS up, gamma / delta AS down FROM x JOIN vdeg USING (vid) JOIN edeg USING (eid)),
    vol AS (SELECT sum(d) AS vol FROM vdeg)"""


def sql_walk(side: str, alpha: float, steps: int, sources: str) -> str:
    """CTEs w0 .. wT (source, id, p) of the restart walk; `sources` is a query of ids."""
    here, there, first, second = ("vid", "eid", "up", "down") if side == "node" else ("eid", "vid", "down", "up")
    out = [f"src AS ({sources})", "w0 AS (SELECT id AS source, id, 1.0::DOUBLE AS p FROM src)"]
    for t in range(1, steps + 1):
        out.append(f"h{t} AS (SELECT source, r.{there} AS mid, sum(p * r.{first}) AS p FROM w{t - 1} JOIN rates r ON r.{here} = id GROUP BY ALL)")
        out.append(f"w{t} AS (SELECT source, id, sum(p) AS p FROM (SELECT source, r.{here} AS id, {1 - alpha} * p * r.{second} AS p FROM h{t} JOIN rates r ON r.{there} = mid "
                   f"UNION ALL SELECT source, id, {alpha} * p FROM w0) GROUP BY ALL)")
    return ", ".join(out)
