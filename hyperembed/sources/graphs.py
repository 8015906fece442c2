"""Hypergraphs, node attributes and labels of the experiment workloads, built from the given tables or generated."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions.vectors import mix
from ..operators.hypergraph import Hypergraph, hypergraph_from
from ..session import cut


@dataclass
class Workload:
    """A hypergraph with all its nodes (vid), sparse attributes (vid, dim, x) and labels (vid, y)."""

    name: str
    graph: Hypergraph
    nodes: DataFrame
    attrs: DataFrame
    labels: DataFrame


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def key_of(text) -> F.Column:
    """Non-negative id of a string: 60 bits of its MD5, the same in other SQL engines."""
    return F.conv(F.substring(F.md5(text.cast("binary") if hasattr(text, "cast") else F.col(text).cast("binary")), 1, 15), 16, 10).cast("long")


def part_attributes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One-hot brand, size and name words, and the price in thousands."""
    p = read(spark, sf_dir, "part").select(F.col("p_partkey").alias("vid"), "p_brand", "p_size", "p_name", "p_retailprice")
    hot = F.concat(F.array(F.concat(F.lit("brand="), "p_brand"), F.concat(F.lit("size="), F.col("p_size").cast("string"))), F.transform(F.split("p_name", " "), lambda w: F.concat(F.lit("name="), w)))
    one = p.select("vid", F.explode(F.array_distinct(hot)).alias("dim"), F.lit(1.0).alias("x"))
    return one.unionByName(p.select("vid", F.lit("price").alias("dim"), (F.col("p_retailprice") / 1000).alias("x")))


def part_labels(spark, sf_dir):
    return read(spark, sf_dir, "part").select(F.col("p_partkey").alias("vid"), F.col("p_type").alias("y"))


def part_nodes(spark, sf_dir):
    return read(spark, sf_dir, "part").select(F.col("p_partkey").alias("vid"))


def order_baskets(spark: SparkSession, sf_dir: str) -> Workload:
    """Hyperedge: an order; node: a part in it."""
    h = hypergraph_from(read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey"), "l_orderkey", "l_partkey")
    return Workload("order_baskets", h, part_nodes(spark, sf_dir), part_attributes(spark, sf_dir), part_labels(spark, sf_dir))


def customer_baskets(spark: SparkSession, sf_dir: str) -> Workload:
    """Hyperedge: a customer; node: a part bought."""
    rows = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").join(read(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey"), "l_orderkey")
    return Workload("customer_baskets", hypergraph_from(rows, "o_custkey", "l_partkey"), part_nodes(spark, sf_dir), part_attributes(spark, sf_dir), part_labels(spark, sf_dir))


def part_traits(spark: SparkSession, sf_dir: str) -> Workload:
    """Hyperedge: a value of brand, size or name word; node: a part."""
    traits = part_attributes(spark, sf_dir).where("dim != 'price'")
    h = hypergraph_from(traits.select(key_of(F.col("dim")).alias("e"), "vid"), "e", "vid")
    return Workload("part_traits", h, part_nodes(spark, sf_dir), traits, part_labels(spark, sf_dir))


def customer_traits(spark: SparkSession, sf_dir: str) -> Workload:
    """Hyperedge: a nation or a market segment; node: a customer; label: the region."""
    c = read(spark, sf_dir, "customer")
    rows = c.select(F.col("c_custkey").alias("vid"), F.explode(F.array(F.concat(F.lit("nation="), F.col("c_nationkey").cast("string")), F.concat(F.lit("segment="), "c_mktsegment"))).alias("t"))
    attrs = c.select(F.col("c_custkey").alias("vid"), F.explode(F.array(F.concat(F.lit("segment="), "c_mktsegment"), F.concat(F.lit("bin="), F.floor(F.col("c_acctbal") / 1000).cast("string")))).alias("dim"), F.lit(1.0).alias("x"))
    nation = read(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("c_nationkey"), F.col("n_regionkey").alias("y"))
    labels = c.join(F.broadcast(nation), "c_nationkey").select(F.col("c_custkey").alias("vid"), F.col("y").cast("string").alias("y"))
    return Workload("customer_traits", hypergraph_from(rows.select(key_of(F.col("t")).alias("e"), "vid"), "e", "vid"), c.select(F.col("c_custkey").alias("vid")), attrs, labels)


def words(text) -> F.Column:
    return F.regexp_extract_all(F.lower(text), F.lit(r"([a-z]{4,})"), 1)


def doc_terms(spark: SparkSession, sf_dir: str, least: int = 5, most: int = 200) -> Workload:
    """Hyperedge: a word of four letters or more in `least` to `most` documents; attributes: TF-IDF of those words."""
    d = read(spark, sf_dir, "documents").select(F.col("doc_id").alias("vid"), "text", "lang")
    tf = d.select("vid", F.explode(words(F.col("text"))).alias("term")).groupBy("vid", "term").agg(F.count("*").alias("tf"))
    df = tf.groupBy("term").agg(F.count("*").alias("df")).where((F.col("df") >= least) & (F.col("df") <= most))
    rows = tf.join(df, "term")
    n = d.agg(F.count("*").alias("n"))
    tfidf = rows.crossJoin(F.broadcast(n)).select("vid", F.col("term").alias("dim"), (F.col("tf") * (F.log((1 + F.col("n")) / (1 + F.col("df"))) + 1)).alias("x"))
    h = hypergraph_from(rows.select(key_of(F.col("term")).alias("e"), "vid"), "e", "vid")
    return Workload("doc_terms", h, d.select("vid"), tfidf, d.select("vid", F.col("lang").alias("y")))


def conv_terms(spark: SparkSession, sf_dir: str) -> Workload:
    """Hyperedge: a word in 2 to 50 conversations; label: whether a system turn occurs."""
    c = read(spark, sf_dir, "conversations").select(F.col("conv_id").alias("vid"), "role", "text")
    tf = c.select("vid", F.explode(words(F.col("text"))).alias("dim")).groupBy("vid", "dim").agg(F.count("*").cast("double").alias("x"))
    df = tf.groupBy("dim").agg(F.count("*").alias("df")).where("df between 2 and 50")
    rows = tf.join(df.select("dim"), "dim", "left_semi")
    labels = c.groupBy("vid").agg(F.max((F.col("role") == "system").cast("int")).cast("string").alias("y"))
    return Workload("conv_terms", hypergraph_from(rows.select(key_of(F.col("dim")).alias("e"), "vid"), "e", "vid"), c.select("vid").distinct(), rows, labels)


def page_hosts(spark: SparkSession, sf_dir: str) -> Workload:
    """Hyperedge: a host; node: a page. Hosts share no page, so the hypergraph falls into parts."""
    p = read(spark, sf_dir, "pages")
    host = F.regexp_extract("url", r"^[a-z]+://([^/?#]+)", 1)
    attrs = p.select(F.col("page_id").alias("vid"), F.explode(words(F.regexp_replace("html", "<[^>]*>", " "))).alias("dim")).groupBy("vid", "dim").agg(F.count("*").cast("double").alias("x"))
    labels = p.select(F.col("page_id").alias("vid"), F.regexp_extract("url", r"^[a-z]+://[^/]+/([a-z]{2})/", 1).alias("y"))
    return Workload("page_hosts", hypergraph_from(p.select(key_of(host).alias("e"), "page_id"), "e", "page_id"), p.select(F.col("page_id").alias("vid")), attrs, labels)


def _event_users(spark, sf_dir, unit: str, name: str) -> Workload:
    e = read(spark, sf_dir, "events")
    slot = F.concat("event_type", F.lit("|"), F.date_format(F.date_trunc(unit, "ts"), "yyyy-MM-dd HH"))
    share = e.groupBy(F.col("user_id").alias("vid"), F.col("event_type").alias("dim")).agg(F.count("*").alias("n"))
    total = e.groupBy(F.col("user_id").alias("vid")).agg(F.count("*").alias("t"), F.avg("value").alias("v"))
    attrs = share.join(total, "vid").select("vid", "dim", (F.col("n") / F.col("t")).alias("x")).unionByName(total.select("vid", F.lit("value").alias("dim"), (F.col("v") / 100).alias("x")))
    labels = share.groupBy("vid").agg(F.max_by("dim", F.struct("n", "dim")).alias("y"))
    return Workload(name, hypergraph_from(e.select(key_of(slot).alias("e"), "user_id"), "e", "user_id"), total.select("vid"), attrs, labels)


def user_days(spark: SparkSession, sf_dir: str) -> Workload:
    """Hyperedge: an event type on a day; node: a user with such an event."""
    return _event_users(spark, sf_dir, "day", "user_days")


def user_hours(spark: SparkSession, sf_dir: str) -> Workload:
    return _event_users(spark, sf_dir, "hour", "user_hours")


def vec_buckets(spark: SparkSession, sf_dir: str) -> Workload:
    """Hyperedge: a sign pattern of the first eight dimensions; attributes: the vector."""
    v = read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("vid"), "embedding", F.col("label").cast("string").alias("y"))
    pattern = sum(((F.col("embedding")[i] > 0).cast("long") * (1 << i) for i in range(8)), F.lit(0).cast("long"))
    attrs = v.select("vid", F.posexplode("embedding").alias("i", "v")).select("vid", F.col("i").cast("string").alias("dim"), F.col("v").cast("double").alias("x"))
    return Workload("vec_buckets", hypergraph_from(v.select(pattern.alias("e"), "vid"), "e", "vid"), v.select("vid"), attrs, v.select("vid", "y"))


def region_days(spark: SparkSession, sf_dir: str) -> Workload:
    """Classes planted in given tables. Hyperedge: the orders of a day from a region, or of a day with a priority, which are from all regions;
    node: a market segment of a nation; label: the region."""
    nation = read(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("c_nationkey"), F.col("n_regionkey").cast("string").alias("y"))
    part = F.array(F.concat(F.lit("nation="), F.col("c_nationkey").cast("string")), F.concat(F.lit("segment="), "c_mktsegment"))
    c = read(spark, sf_dir, "customer").join(F.broadcast(nation), "c_nationkey").select(F.col("c_custkey").alias("o_custkey"), key_of(F.array_join(part, "|")).alias("vid"), part.alias("dims"), "y")
    kinds = F.array(F.concat(F.lit("region="), "y"), F.concat(F.lit("priority="), "o_orderpriority"))
    rows = read(spark, sf_dir, "orders").select("o_custkey", "o_orderdate", "o_orderpriority").join(c, "o_custkey").select("vid", "o_orderdate", F.explode(kinds).alias("kind")).distinct()
    rows = cut(rows.select("vid", key_of(F.concat(F.col("o_orderdate").cast("string"), F.lit("|"), "kind")).alias("e")), "rows")
    attrs = c.select("vid", F.explode("dims").alias("dim"), F.lit(1.0).alias("x")).distinct()
    return Workload("region_days", hypergraph_from(rows, "e", "vid"), c.select("vid").distinct(), attrs, c.select("vid", "y").distinct())


def supplier_catalog(spark: SparkSession, sf_dir: str) -> Workload:
    """Hyperedge: a supplier; node: a part supplied."""
    h = hypergraph_from(read(spark, sf_dir, "lineitem").select("l_suppkey", "l_partkey"), "l_suppkey", "l_partkey")
    return Workload("supplier_catalog", h, part_nodes(spark, sf_dir), part_attributes(spark, sf_dir), part_labels(spark, sf_dir))


def shared_passages(spark: SparkSession, sf_dir: str) -> Workload:
    """Hyperedge: a run of five words that a document and a benchmark item share; node: either (items have negative ids)."""
    grams = lambda df: df.select("vid", "y", F.split(F.trim(F.regexp_replace(F.lower("text"), r"\s+", " ")), " ").alias("w")).where("size(w) >= 5").select(
        "vid", "y", F.explode(F.expr("array_distinct(transform(sequence(1, size(w) - 4), i -> array_join(slice(w, i, 5), ' ')))")).alias("g"))
    docs = grams(read(spark, sf_dir, "documents").select(F.col("doc_id").alias("vid"), "text", F.col("source").alias("y")))
    items = grams(read(spark, sf_dir, "benchmark").select((-1 - F.col("item_id")).alias("vid"), "text", F.lit("benchmark").alias("y")))
    rows = docs.join(items.select("g").distinct(), "g", "left_semi")
    rows = rows.unionByName(items.join(rows.select("g").distinct(), "g", "left_semi"))
    attrs = rows.select("vid", F.col("g").alias("dim"), F.lit(1.0).alias("x"))
    return Workload("shared_passages", hypergraph_from(rows.select(key_of(F.col("g")).alias("e"), "vid"), "e", "vid"), rows.select("vid").distinct(), attrs, rows.select("vid", "y").distinct())


def synthetic(spark: SparkSession, n: int, size: int = 3, q: int = 100, seed: int = 11) -> Workload:
    """n nodes, n hyperedges of `size` random nodes, q random binary attributes, all from the hash."""
    ids = spark.range(n).withColumnRenamed("id", "e")
    rows = ids.select("e", F.explode(F.array(*[F.pmod(mix(F.col("e"), j, seed), F.lit(n)) for j in range(size)])).alias("v"))
    nodes = spark.range(n).select(F.col("id").alias("vid"))
    bits = nodes.select("vid", F.explode(F.sequence(F.lit(0), F.lit(q - 1))).alias("i")).where(F.pmod(mix(F.col("vid"), F.col("i"), seed + 5), F.lit(2)) == 1)
    labels = nodes.select("vid", F.pmod(F.col("vid"), F.lit(4)).cast("string").alias("y"))
    return Workload("synthetic", hypergraph_from(rows, "e", "v"), nodes, bits.select("vid", F.col("i").cast("string").alias("dim"), F.lit(1.0).alias("x")), labels)


def planted(spark: SparkSession, n: int = 400, classes: int = 4, edges: int = 700, size: int = 4, q: int = 40, purity: int = 60, seed: int = 21) -> Workload:
    """Nodes of class vid mod `classes`; a member of a hyperedge is of the hyperedge's class with `purity` percent; attributes lean to the class."""
    e = spark.range(edges).select(F.col("id").alias("e"), F.explode(F.sequence(F.lit(0), F.lit(size - 1))).alias("j"))
    pure = F.pmod(mix(F.col("e"), F.col("j"), seed), F.lit(100)) < purity
    any_node = F.pmod(mix(F.col("e"), F.col("j"), seed + 2), F.lit(n))
    own = any_node - F.pmod(any_node, F.lit(classes)) + F.pmod(F.col("e"), F.lit(classes))
    rows = e.select("e", F.when(pure, F.pmod(own, F.lit(n))).otherwise(any_node).alias("v"))
    nodes = spark.range(n).select(F.col("id").alias("vid"))
    bit = nodes.select("vid", F.explode(F.sequence(F.lit(0), F.lit(q - 1))).alias("i"))
    home = F.pmod(F.col("i"), F.lit(classes)) == F.pmod(F.col("vid"), F.lit(classes))
    bit = bit.where(F.pmod(mix(F.col("vid"), F.col("i"), seed + 4), F.lit(100)) < F.when(home, 40).otherwise(15))
    labels = nodes.select("vid", F.pmod(F.col("vid"), F.lit(classes)).cast("string").alias("y"))
    return Workload("planted", hypergraph_from(rows, "e", "v"), nodes, bit.select("vid", F.col("i").cast("string").alias("dim"), F.lit(1.0).alias("x")), labels)


def toy(spark: SparkSession) -> Workload:
    """Six nodes, three hyperedges {1,2,3}, {3,4,5}, {3,5,6}."""
    inc = spark.createDataFrame([(e, v) for e, m in ((1, (1, 2, 3)), (2, (3, 4, 5)), (3, (3, 5, 6))) for v in m], "e long, v long")
    x = {1: (1, 0, 0), 2: (1, 1, 0), 3: (0, 1, 1), 4: (0, 1, 0), 5: (0, 1, 1), 6: (0, 0, 1)}
    attrs = spark.createDataFrame([(v, str(i), float(a)) for v, row in x.items() for i, a in enumerate(row) if a], "vid long, dim string, x double")
    nodes = spark.createDataFrame([(v,) for v in x], "vid long")
    return Workload("toy", hypergraph_from(inc, "e", "v"), nodes, attrs, spark.createDataFrame([(v, "a" if v < 4 else "b") for v in x], "vid long, y string"))


BUILDERS = {f.__name__: f for f in (order_baskets, customer_baskets, part_traits, customer_traits, doc_terms, conv_terms, page_hosts, user_days, user_hours, vec_buckets, supplier_catalog, shared_passages)}


def dense_attributes(w: Workload, most_dims: int = 4096) -> DataFrame:
    """(vid, attrs array<double>) of all nodes; dimensions in order of name. Refuses more than `most_dims` dimensions."""
    dims = [r["dim"] for r in w.attrs.select("dim").distinct().orderBy("dim").limit(most_dims + 1).collect()]
    if len(dims) > most_dims:
        raise ValueError("too many dimensions for dense vectors; use knn_sparse")
    place = {d: i for i, d in enumerate(dims)}
    entries = w.attrs.groupBy("vid").agg(F.map_from_entries(F.collect_list(F.struct("dim", "x"))).alias("m"))
    order = F.array(*[F.lit(d) for d in place]) if place else F.array().cast("array<string>")
    return w.nodes.join(entries, "vid", "left").select("vid", F.transform(order, lambda d: F.coalesce(F.element_at(F.col("m"), d), F.lit(0.0))).alias("attrs"))
