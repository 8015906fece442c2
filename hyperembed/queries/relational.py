"""Scans, sources and sinks, filters, joins, aggregates, windows, sets and scalar functions around the methods: SURVEY 2.8 to 2.15."""

from __future__ import annotations

import uuid

from pyspark.sql import Window, functions as F

from ..functions import tables, vectors
from ..functions.vectors import mix_sql
from ..operators import hypergraph as hg
from ..session import work_folder
from ..sources import graphs, hyperedge_text, layout
from .common import SQL_BASKETS, Registry, r

_reg = Registry()
add, verdict = _reg.add, _reg.verdict
QUERIES, ORACLES = _reg.queries, _reg.oracles
read = graphs.read


@add("SELECT o_orderkey, o_totalprice FROM orders WHERE o_orderpriority = '1-URGENT' AND o_totalprice > 100000")
def scan_pruned(spark, sf_dir):
    return read(spark, sf_dir, "orders").where("o_orderpriority = '1-URGENT' and o_totalprice > 100000").select("o_orderkey", "o_totalprice")


def _round_trip(fmt, **options):
    @add("SELECT DISTINCT l_suppkey AS eid, l_partkey AS vid FROM lineitem", f"roundtrip_{fmt}")
    def query(spark, sf_dir):
        rows = graphs.supplier_catalog(spark, sf_dir).graph.inc.select("eid", "vid")
        path = f"{work_folder(spark)}/trip-{uuid.uuid4().hex}"
        if fmt == "text":
            rows.select(F.concat_ws(" ", "eid", "vid").alias("value")).write.text(path)
            cut = F.split("value", " ")
            return spark.read.text(path).select(cut[0].cast("long").alias("eid"), cut[1].cast("long").alias("vid"))
        rows.write.format(fmt).options(**options).save(path)
        return spark.read.format(fmt).options(**options).schema("eid long, vid long").load(path)


for _f in ("csv", "json", "orc", "text", "parquet"):
    _round_trip(_f)


@add("SELECT count(*) AS rows, count(DISTINCT vid) AS nodes, CAST(sum(vid) AS BIGINT) AS total FROM (SELECT DISTINCT l_suppkey AS eid, l_partkey AS vid FROM lineitem)")
def read_hyperedge_text(spark, sf_dir):
    """Write hyperedges one a line with the package's own data source, and read them back."""
    hyperedge_text.register(spark)
    path = f"{work_folder(spark)}/edges-{uuid.uuid4().hex}"
    rows = graphs.supplier_catalog(spark, sf_dir).graph.inc.select("eid", "vid").repartition(3, "eid").sortWithinPartitions("eid", "vid")
    rows.write.format("hyperedges").option("path", path).mode("append").save()
    back = spark.read.format("hyperedges").option("path", path).load()
    return back.agg(F.count("*").alias("rows"), F.count_distinct("vid").alias("nodes"), F.sum("vid").alias("total"))


@add("""SELECT p_partkey, CASE WHEN p_size > 40 THEN 'large' WHEN p_size BETWEEN 20 AND 40 THEN 'medium' ELSE 'small' END AS kind FROM part
        WHERE (p_brand LIKE 'Brand#1%' OR p_type IN (SELECT min(p_type) FROM part)) AND NOT p_retailprice < 1000 AND p_name IS NOT NULL""")
def filter_predicates(spark, sf_dir):
    p = read(spark, sf_dir, "part")
    first = p.agg(F.min("p_type").alias("p_type"))
    keep = p.join(F.broadcast(first.withColumn("hit", F.lit(True))), "p_type", "left").where((F.col("p_brand").like("Brand#1%") | F.col("hit")) & ~(F.col("p_retailprice") < 1000) & F.col("p_name").isNotNull())
    return keep.select("p_partkey", F.when(F.col("p_size") > 40, "large").when(F.col("p_size").between(20, 40), "medium").otherwise("small").alias("kind"))


@add("SELECT vid, dim, 1.0::DOUBLE AS x FROM (SELECT DISTINCT p_partkey AS vid, unnest(['brand=' || p_brand, 'size=' || p_size] || list_transform(string_split(p_name, ' '), lambda w: 'name=' || w)) AS dim FROM part)")
def one_hot_attributes(spark, sf_dir):
    return graphs.part_attributes(spark, sf_dir).where("dim != 'price'")


@add("SELECT s_suppkey AS vid, dim, x FROM (SELECT s_suppkey, s_acctbal, s_nationkey::DOUBLE AS nation FROM supplier) UNPIVOT (x FOR dim IN (s_acctbal, nation))")
def unpivot_attributes(spark, sf_dir):
    s = read(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("vid"), "s_acctbal", F.col("s_nationkey").cast("double").alias("nation"))
    return s.unpivot("vid", ["s_acctbal", "nation"], "dim", "x")


@add("SELECT l_orderkey AS eid, l_partkey AS vid, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_partkey) - 1 AS pos FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem)")
def explode_members(spark, sf_dir):
    nested = read(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("eid")).agg(F.sort_array(F.collect_set("l_partkey")).alias("members"))
    return nested.select("eid", F.posexplode("members").alias("pos", "vid")).select("eid", "vid", F.col("pos").cast("long").alias("pos"))


# Joins.


@add("SELECT o_orderkey, c_mktsegment FROM orders JOIN customer ON c_custkey = o_custkey")
def join_equi(spark, sf_dir):
    c = read(spark, sf_dir, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_mktsegment")
    return read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey").join(c.hint("shuffle_hash"), "o_custkey").select("o_orderkey", "c_mktsegment")


@add("SELECT s_suppkey, n_name FROM supplier JOIN nation ON n_nationkey = s_nationkey")
def join_broadcast(spark, sf_dir):
    n = read(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("s_nationkey"), "n_name")  # 25 rows
    return read(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey").join(F.broadcast(n), "s_nationkey").select("s_suppkey", "n_name")


@add("SELECT p_partkey AS vid, count(l_orderkey) AS d FROM part LEFT JOIN (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem WHERE l_returnflag = 'R') ON l_partkey = p_partkey GROUP BY 1")
def join_outer(spark, sf_dir):
    rows = read(spark, sf_dir, "lineitem").where("l_returnflag = 'R'").select("l_orderkey", F.col("l_partkey").alias("vid")).distinct()
    return graphs.part_nodes(spark, sf_dir).join(rows, "vid", "left").groupBy("vid").agg(F.count("l_orderkey").alias("d"))


@add("SELECT p_partkey, coalesce(q_n, 0) AS q_n, coalesce(s_n, 0) AS s_n FROM (SELECT l_partkey AS p_partkey, count(*) AS q_n FROM lineitem WHERE l_quantity > 45 GROUP BY 1) FULL JOIN (SELECT l_partkey AS p_partkey, count(*) AS s_n FROM lineitem WHERE l_discount = 0 GROUP BY 1) USING (p_partkey)")
def join_full(spark, sf_dir):
    rows = read(spark, sf_dir, "lineitem").withColumnRenamed("l_partkey", "p_partkey")
    a, b = (rows.where(c).groupBy("p_partkey").agg(F.count("*").alias(n)) for c, n in (("l_quantity > 45", "q_n"), ("l_discount = 0", "s_n")))
    return a.join(b, "p_partkey", "full").select("p_partkey", F.coalesce("q_n", F.lit(0)).alias("q_n"), F.coalesce("s_n", F.lit(0)).alias("s_n"))


@add("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 250000)")
def join_semi(spark, sf_dir):
    o = read(spark, sf_dir, "orders").where("o_totalprice > 250000").select(F.col("o_custkey").alias("c_custkey"))
    return read(spark, sf_dir, "customer").select("c_custkey").join(o, "c_custkey", "left_semi")


@add("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 250000)")
def join_anti(spark, sf_dir):
    o = read(spark, sf_dir, "orders").where("o_totalprice > 250000").select(F.col("o_custkey").alias("c_custkey"))
    return read(spark, sf_dir, "customer").select("c_custkey").join(o, "c_custkey", "left_anti")


@add("SELECT a.n_nationkey AS i, b.n_nationkey AS j FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND a.n_regionkey <> b.n_regionkey")
def join_theta(spark, sf_dir):
    n = read(spark, sf_dir, "nation")  # 25 rows
    a, b = (n.select(F.col("n_nationkey").alias(x), F.col("n_regionkey").alias(f"r{x}")) for x in "ij")
    return a.join(F.broadcast(b), (F.col("i") < F.col("j")) & (F.col("ri") != F.col("rj"))).select("i", "j")


@add("WITH p AS (SELECT DISTINCT l_orderkey AS e, l_partkey AS v FROM lineitem) SELECT a.v AS i, b.v AS j, count(*) AS n FROM p a JOIN p b ON a.e = b.e AND a.v < b.v GROUP BY ALL HAVING count(*) >= 2")
def co_membership(spark, sf_dir):
    p = read(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("e"), F.col("l_partkey").alias("v")).distinct()
    return p.select("e", F.col("v").alias("i")).join(p.select("e", F.col("v").alias("j")), "e").where("i < j").groupBy("i", "j").agg(F.count("*").alias("n")).where("n >= 2")


@add("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def join_range(spark, sf_dir):
    """Events of one user within an hour: equal (user, hour bin) against the bin and the one before, then the exact range."""
    e = read(spark, sf_dir, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    hour = 3_600_000_000
    a = e.select(F.col("event_id").alias("a"), "user_id", F.col("t").alias("ta"), F.explode(F.array(F.floor(F.col("t") / hour), F.floor(F.col("t") / hour) + 1)).alias("bin"))
    b = e.select(F.col("event_id").alias("b"), "user_id", F.col("t").alias("tb"), F.floor(F.col("t") / hour).alias("bin"))
    return a.join(b, ["user_id", "bin"]).where(f"tb > ta and tb <= ta + {hour}").select("a", "b")


@add("SELECT a.event_id AS id, coalesce(b.event_id, -1) AS before FROM events a ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = (SELECT min(event_type) FROM events)) b ON a.user_id = b.user_id AND a.ts > b.ts")
def join_asof(spark, sf_dir):
    """For each event the user's last earlier event of the first type: one pass over a window, no join."""
    e = read(spark, sf_dir, "events")
    first = F.broadcast(e.agg(F.min("event_type").alias("first")))
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, -1)
    rows = e.crossJoin(first).withColumn("ts", F.unix_micros(F.col("ts").cast("timestamp")))
    hit = F.when(F.col("event_type") == F.col("first"), F.col("event_id"))
    return rows.select(F.col("event_id").alias("id"), F.coalesce(F.last(hit, ignorenulls=True).over(w), F.lit(-1)).alias("before"))


@add("SELECT c_custkey, o_orderkey FROM customer, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2)")
def join_lateral(spark, sf_dir):
    """Per customer the two dearest orders, as a window with a group limit."""
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    o = read(spark, sf_dir, "orders").withColumn("k", F.row_number().over(w)).where("k <= 2")
    return o.select(F.col("o_custkey").alias("c_custkey"), "o_orderkey")


@add("WITH a AS (SELECT DISTINCT NULLIF(c_nationkey % 5, 0) AS k FROM customer), b AS (SELECT NULLIF(s_nationkey % 5, 0) AS k, count(*) AS n FROM supplier GROUP BY 1) SELECT coalesce(a.k, -1) AS k, n FROM a JOIN b ON a.k IS NOT DISTINCT FROM b.k")
def join_null_safe(spark, sf_dir):
    a = read(spark, sf_dir, "customer").select(F.expr("nullif(c_nationkey % 5, 0)").alias("k")).distinct()
    b = read(spark, sf_dir, "supplier").groupBy(F.expr("nullif(s_nationkey % 5, 0)").alias("k2")).agg(F.count("*").alias("n"))
    return a.join(b, F.col("k").eqNullSafe(F.col("k2"))).select(F.coalesce("k", F.lit(-1)).alias("k"), "n")


@add("""WITH p AS (SELECT DISTINCT l_orderkey AS e, l_partkey AS v FROM lineitem), s AS (SELECT e, count(*) AS s FROM p GROUP BY e),
        c AS (SELECT a.e AS x, b.e AS y, count(*) AS c FROM p a JOIN p b ON a.v = b.v AND a.e < b.e GROUP BY ALL)
        SELECT x, y, round(c / (sx.s + sy.s - c), 6) AS jaccard FROM c JOIN s sx ON sx.e = x JOIN s sy ON sy.e = y WHERE c >= 2""")
def edge_jaccard(spark, sf_dir):
    """Overlap of hyperedges as sets, pairs with two common members or more."""
    h = hg.hypergraph_from(read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey"), "l_orderkey", "l_partkey", min_size=1)
    s = h.inc.groupBy("eid").agg(F.count("*").alias("s"))
    c = hg.line_graph(h).where("shared >= 2")
    both = c.join(s.select(F.col("eid").alias("e"), F.col("s").alias("sx")), "e").join(s.select(F.col("eid").alias("f"), F.col("s").alias("sy")), "f")
    return both.select(F.col("e").alias("x"), F.col("f").alias("y"), F.round(F.col("shared") / (F.col("sx") + F.col("sy") - F.col("shared")), 6).alias("jaccard"))


# Aggregates.


@add("SELECT l_returnflag, count(*) AS n, round(sum(l_extendedprice), 2) AS total, round(avg(l_discount), 6) AS mean, min(l_quantity) AS lo, max(l_quantity) AS hi, round(stddev(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS corr FROM lineitem GROUP BY 1")
def agg_basic(spark, sf_dir):
    return read(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(
        F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("total"), F.round(F.avg("l_discount"), 6).alias("mean"), F.min("l_quantity").alias("lo"), F.max("l_quantity").alias("hi"),
        F.round(F.stddev("l_quantity"), 6).alias("sd"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("corr"))


@add("SELECT l_linestatus, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1")
def agg_distinct(spark, sf_dir):
    return read(spark, sf_dir, "lineitem").groupBy("l_linestatus").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


@verdict("distinct_within_5_percent", "median_within_2_percent")
def agg_approx(spark, sf_dir):
    x = read(spark, sf_dir, "lineitem").agg(F.approx_count_distinct("l_orderkey", 0.02), F.count_distinct("l_orderkey"), F.percentile_approx("l_extendedprice", 0.5, 10000), F.percentile("l_extendedprice", 0.5)).first()
    return {"distinct_within_5_percent": abs(x[0] / x[1] - 1) < 0.05, "median_within_2_percent": abs(x[2] / x[3] - 1) < 0.02}


_GROUPS = {"agg_rollup": ("ROLLUP (lang, source)", "rollup"), "agg_cube": ("CUBE (lang, source)", "cube")}
for _n, (_sql, _m) in _GROUPS.items():
    add(f"SELECT lang, source, GROUPING(lang, source) AS gid, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY {_sql}", _n)(
        lambda spark, sf_dir, m=_m: getattr(read(spark, sf_dir, "documents"), m)("lang", "source").agg(F.grouping_id().alias("gid"), F.count("*").alias("n"), F.sum("n_chars").alias("chars")))


@add("SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def agg_grouping_sets(spark, sf_dir):
    d = read(spark, sf_dir, "documents")
    return d.groupingSets([[F.col("lang")], [F.col("source")], []], F.col("lang"), F.col("source")).agg(F.count("*").alias("n"))


@add("SELECT l_returnflag, count(*) FILTER (WHERE l_linestatus = 'F') AS f, count(*) FILTER (WHERE l_linestatus = 'O') AS o FROM lineitem GROUP BY 1")
def agg_pivot(spark, sf_dir):
    p = read(spark, sf_dir, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1)))
    return p.select("l_returnflag", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o"))


@add("SELECT size, count(*) AS edges FROM (SELECT count(DISTINCT l_partkey) AS size FROM lineitem GROUP BY l_orderkey) GROUP BY size")
def size_histogram(spark, sf_dir):
    s = read(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.count_distinct("l_partkey").alias("size"))
    return s.groupBy("size").agg(F.count("*").alias("edges"))


@add("SELECT label, i, round(sum(v), 4) + 0 AS total FROM (SELECT label, unnest(range(8)) AS i, unnest(embedding[1:8]::DOUBLE[]) AS v FROM embeddings) GROUP BY ALL")
def agg_vector_sum(spark, sf_dir):
    """Elementwise sum of arrays: one codegen sum per place."""
    s = read(spark, sf_dir, "embeddings").groupBy("label").agg(*[F.sum(F.col("embedding")[i].cast("double")).alias(f"s{i}") for i in range(8)])
    return s.select("label", F.posexplode(F.array(*[F.col(f"s{i}") for i in range(8)])).alias("i", "total")).select("label", F.col("i").cast("long").alias("i"), r("total", 4))


@add("SELECT o_orderpriority, count(*) FILTER (WHERE o_totalprice > 200000) AS dear, bool_and(o_totalprice > 0) AS all_positive, max_by(o_orderkey, o_totalprice) AS top FROM orders GROUP BY 1")
def agg_filtered(spark, sf_dir):
    return read(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(F.count_if(F.col("o_totalprice") > 200000).alias("dear"), F.bool_and(F.col("o_totalprice") > 0).alias("all_positive"), F.max_by("o_orderkey", "o_totalprice").alias("top"))


@add("SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1")
def agg_list(spark, sf_dir):
    return read(spark, sf_dir, "nation").groupBy("n_regionkey").agg(F.array_join(F.sort_array(F.collect_list("n_name")), ",").alias("names"))


# Windows.


@add("""SELECT s_suppkey, rank() OVER w AS rk, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd, ntile(4) OVER v AS nt
        FROM (SELECT *, round(s_acctbal / 1000) AS b FROM supplier) WINDOW w AS (PARTITION BY s_nationkey % 5 ORDER BY b), v AS (PARTITION BY s_nationkey % 5 ORDER BY b, s_suppkey)""")
def win_rank(spark, sf_dir):
    s = read(spark, sf_dir, "supplier").withColumns({"b": F.round(F.col("s_acctbal") / 1000), "g": F.col("s_nationkey") % 5})
    w, v = Window.partitionBy("g").orderBy("b"), Window.partitionBy("g").orderBy("b", "s_suppkey")
    return s.select("s_suppkey", F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"), F.ntile(4).over(v).alias("nt"))


@add("SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM orders) WHERE k <= 3")
def win_topk_per_group(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return read(spark, sf_dir, "orders").withColumn("k", F.row_number().over(w)).where(F.col("k") <= 3).select("o_custkey", "o_orderkey")


@add("SELECT event_id, coalesce(epoch_us(ts) - epoch_us(lag(ts) OVER w), -1) AS gap, first_value(event_type) OVER w AS first, lead(event_type) OVER w AS next FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag_gap(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    t = F.unix_micros(F.col("ts").cast("timestamp"))
    return read(spark, sf_dir, "events").select("event_id", F.coalesce(t - F.lag(t).over(w), F.lit(-1)).alias("gap"), F.first("event_type").over(w).alias("first"), F.lead("event_type").over(w).alias("next"))


@add("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS n, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), 4) AS total FROM events")
def win_running(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return read(spark, sf_dir, "events").select("event_id", F.count("*").over(w).alias("n"), F.round(F.sum("value").over(w), 4).alias("total"))


@add("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS n FROM events")
def win_moving_range(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("t").rangeBetween(-86_400_000_000, 0)
    return read(spark, sf_dir, "events").withColumn("t", F.unix_micros(F.col("ts").cast("timestamp"))).select("event_id", F.count("*").over(w).alias("n"))


# Sorts, limits, samples, sets.


@add("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5")
def topk_global(spark, sf_dir):
    return read(spark, sf_dir, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(20).select("o_orderkey", "o_totalprice")


@add(f"SELECT o_orderkey FROM orders WHERE {vectors.mix_sql('o_orderkey', '1', 9)} % 10 = 0")
def sample_hash(spark, sf_dir):
    return read(spark, sf_dir, "orders").where(F.pmod(vectors.mix(F.col("o_orderkey"), 1, 9), F.lit(10)) == 0).select("o_orderkey")


_A, _B = "SELECT l_partkey AS v FROM lineitem WHERE l_returnflag = 'R'", "SELECT l_partkey AS v FROM lineitem WHERE l_quantity > 48"


def _sides(spark, sf_dir):
    l = read(spark, sf_dir, "lineitem")  # noqa: E741
    return (l.where(c).select(F.col("l_partkey").alias("v")) for c in ("l_returnflag = 'R'", "l_quantity > 48"))


for _n, _sql, _f in (
    ("set_union", "UNION", lambda a, b: a.union(b).distinct()), ("set_union_all", "UNION ALL", lambda a, b: a.unionByName(b)), ("set_intersect", "INTERSECT", lambda a, b: a.intersect(b)),
    ("set_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)), ("set_except", "EXCEPT", lambda a, b: a.subtract(b)), ("set_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
):
    add(f"{_A} {_sql} {_B}", _n)(lambda spark, sf_dir, f=_f: f(*_sides(spark, sf_dir)))


@add("WITH p AS (SELECT DISTINCT l_suppkey AS e, l_partkey AS v FROM lineitem) SELECT a.e, b.e AS f, count(*) AS both FROM p a JOIN p b ON a.v = b.v AND a.e < b.e GROUP BY ALL")
def edge_intersection(spark, sf_dir):
    """Common members of hyperedges that have any. A hyperedge may have one member only."""
    h = hg.hypergraph_from(read(spark, sf_dir, "lineitem").select("l_suppkey", "l_partkey"), "l_suppkey", "l_partkey", min_size=1)
    return hg.shared_members(h).select("e", "f", F.col("shared").alias("both"))


# Scalar functions.


@add("""SELECT p_partkey, upper(p_name) AS up, replace(p_brand, '#', '-') AS brand, substr(p_type, 1, 3) AS head, length(p_name) AS n, levenshtein(split_part(p_name, ' ', 1), split_part(p_name, ' ', 2)) AS lev,
        translate(p_name, 'aeiou', '12345') AS tr FROM part""")
def fn_string(spark, sf_dir):
    p = read(spark, sf_dir, "part")
    return p.select("p_partkey", F.upper("p_name").alias("up"), F.replace("p_brand", F.lit("#"), F.lit("-")).alias("brand"), F.substring("p_type", 1, 3).alias("head"), F.char_length("p_name").cast("long").alias("n"),
                    F.levenshtein(F.split_part("p_name", F.lit(" "), F.lit(1)), F.split_part("p_name", F.lit(" "), F.lit(2))).cast("long").alias("lev"), F.translate("p_name", "aeiou", "12345").alias("tr"))


@add("SELECT doc_id, len(w) AS n, len(list_distinct(w)) AS kinds FROM (SELECT doc_id, regexp_extract_all(lower(text), '[a-z]{4,}') AS w FROM documents)")
def fn_tokens(spark, sf_dir):
    w = read(spark, sf_dir, "documents").select("doc_id", graphs.words(F.col("text")).alias("w"))
    return w.select("doc_id", F.size("w").cast("long").alias("n"), F.size(F.array_distinct("w")).cast("long").alias("kinds"))


@add("""WITH t AS (SELECT doc_id AS vid, unnest(regexp_extract_all(lower(text), '[a-z]{4,}')) AS dim FROM documents), f AS (SELECT vid, dim, count(*) AS tf FROM t GROUP BY ALL),
        d AS (SELECT dim, count(*) AS df FROM f GROUP BY dim HAVING count(*) BETWEEN 5 AND 200), n AS (SELECT count(*) AS n FROM documents)
        SELECT vid, dim, round(tf * (ln((1 + n) / (1 + df)) + 1), 6) AS x FROM f JOIN d USING (dim), n""")
def fn_tfidf(spark, sf_dir):
    return graphs.doc_terms(spark, sf_dir).attrs.select("vid", "dim", r("x"))


@add("SELECT o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, year(o_orderdate) AS y, dayofweek(o_orderdate) + 1 AS dow, date_diff('day', DATE '1992-01-01', o_orderdate::DATE) AS days FROM orders")
def fn_date(spark, sf_dir):
    o = read(spark, sf_dir, "orders")
    return o.select("o_orderkey", F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("month"), F.year("o_orderdate").cast("long").alias("y"), F.dayofweek("o_orderdate").cast("long").alias("dow"),
                    F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).cast("long").alias("days"))


@add("SELECT o_orderkey, round(ln(o_totalprice), 6) AS l, round(sqrt(o_totalprice), 6) AS s, round(pow(o_totalprice / 1000, 1.5), 4) AS p, o_orderkey % 7 AS m, greatest(o_custkey, o_orderkey) AS g FROM orders")
def fn_math(spark, sf_dir):
    o = read(spark, sf_dir, "orders")
    return o.select("o_orderkey", F.round(F.log("o_totalprice"), 6).alias("l"), F.round(F.sqrt("o_totalprice"), 6).alias("s"), F.round(F.pow(F.col("o_totalprice") / 1000, F.lit(1.5)), 4).alias("p"),
                    F.pmod("o_orderkey", F.lit(7)).alias("m"), F.greatest("o_custkey", "o_orderkey").alias("g"))


@add("""WITH a AS (SELECT l_orderkey AS e, list_sort(list_distinct(list(l_partkey))) AS m FROM lineitem GROUP BY 1)
        SELECT e, CAST(list_sum(list_transform(m, lambda x: x % 10)) AS BIGINT) AS digits, len(list_filter(m, lambda x: x % 2 = 0)) AS even, m[1] AS first, list_contains(m, 7) AS has7 FROM a""")
def fn_array(spark, sf_dir):
    a = read(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("e")).agg(F.array_sort(F.collect_set("l_partkey")).alias("m"))
    return a.select("e", F.aggregate(F.transform("m", lambda x: x % 10), F.lit(0).cast("long"), lambda s, x: s + x).alias("digits"), F.size(F.filter("m", lambda x: x % 2 == 0)).cast("long").alias("even"),
                    F.element_at("m", 1).alias("first"), F.array_contains("m", 7).alias("has7"))


@add("SELECT user_id, event_type AS k, count(*) AS n FROM events GROUP BY ALL")
def fn_map(spark, sf_dir):
    """Counts as a map per user, then back to rows."""
    n = read(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = n.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.explode(F.map_entries("m")).alias("e")).select("user_id", F.col("e.key").alias("k"), F.col("e.value").alias("n"))


@add("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def fn_json(spark, sf_dir):
    return read(spark, sf_dir, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "long").alias("k"))


@add("SELECT vec_id, round(list_inner_product(e, e), 6) AS dot, round(sqrt(list_inner_product(e, e)), 6) AS norm, round(list_cosine_similarity(e, list_reverse(e)), 6) + 0 AS cos FROM (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings)")
def fn_vector(spark, sf_dir):
    e = read(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("e"))
    d = vectors.dot(F.col("e"), F.col("e"))
    return e.select("vec_id", F.round(d, 6).alias("dot"), F.round(vectors.norm(F.col("e")), 6).alias("norm"), (F.round(vectors.cosine(F.col("e"), F.reverse("e")), 6) + F.lit(0.0)).alias("cos"))


@add("SELECT event_id, round(ln(greatest(value, 1)), 6) AS y FROM events")
def sql_functions(spark, sf_dir):
    """Functions of the package called from SQL text."""
    vectors.register(spark)
    read(spark, sf_dir, "events").createOrReplaceTempView("hyperembed_events")
    return spark.sql("SELECT event_id, round(tlog(value), 6) AS y FROM hyperembed_events")


@add("SELECT l_suppkey, count(*) AS n FROM (SELECT DISTINCT l_suppkey, l_partkey FROM lineitem) GROUP BY 1 HAVING count(*) > 20")
def sql_pipe(spark, sf_dir):
    read(spark, sf_dir, "lineitem").createOrReplaceTempView("hyperembed_lineitem")
    return spark.sql("FROM hyperembed_lineitem |> SELECT DISTINCT l_suppkey, l_partkey |> AGGREGATE count(*) AS n GROUP BY l_suppkey |> WHERE n > 20")


# Stored layouts and table functions.


@add(f"WITH {SQL_BASKETS} SELECT eid, count(*) AS size, sum(gamma) AS delta FROM inc GROUP BY eid")
def roundtrip_bucketed(spark, sf_dir):
    """Hyperedge sizes from the copy that is bucketed by hyperedge: no exchange."""
    name = f"incidence_{uuid.uuid4().hex}"
    by_eid, _ = layout.write_bucketed(graphs.order_baskets(spark, sf_dir).graph, name, f"{work_folder(spark)}/{name}", 8)
    return by_eid.groupBy("eid").agg(F.count("*").alias("size"), F.sum("gamma").alias("delta"))


@add(f"WITH {SQL_BASKETS} SELECT eid, vid, gamma FROM inc WHERE {mix_sql('eid', '0', 23)} % 16 = 3")
def roundtrip_partitioned(spark, sf_dir):
    """One hash block of the incidence, read from its own folder."""
    path = f"{work_folder(spark)}/incidence-{uuid.uuid4().hex}"
    layout.write_partitioned(graphs.order_baskets(spark, sf_dir).graph.inc, path, 16)
    return layout.read_block(spark, path, 3)


@add("WITH p AS (SELECT DISTINCT l_orderkey AS eid, l_partkey AS v FROM lineitem) SELECT x.eid, x.v AS a, y.v AS b FROM p x JOIN p y ON x.eid = y.eid AND x.v < y.v")
def udtf_pairs(spark, sf_dir):
    """Members of every basket to pairs by a table function (baskets hold seven lines at most)."""
    tables.register(spark)
    view = f"baskets_{uuid.uuid4().hex}"
    read(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("eid")).agg(F.collect_list("l_partkey").alias("members")).createOrReplaceTempView(view)
    return spark.sql(f"SELECT * FROM hyperedge_pairs(TABLE({view}))")


@add("WITH s AS (SELECT l_orderkey AS eid, count(*) AS size FROM lineitem GROUP BY 1) SELECT eid, size AS members, size AS places, true AS in_range FROM s")
def udtf_members(spark, sf_dir):
    """As many distinct random places as each basket has lines."""
    tables.register(spark)
    view = f"sizes_{uuid.uuid4().hex}"
    read(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("eid")).agg(F.count("*").alias("size")).withColumns({"nodes": F.lit(2000).cast("long"), "seed": F.lit(41).cast("long")}).createOrReplaceTempView(view)
    drawn = spark.sql(f"SELECT * FROM random_members(TABLE({view}))")
    return drawn.groupBy("eid").agg(F.count("*").alias("members"), F.count_distinct("place").alias("places"), F.bool_and(F.col("place").between(0, 1999)).alias("in_range"))
