"""Evaluation tasks: splits, negatives, features, a linear learner, and the measures. Splits and negatives come from the hash."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.ml.classification import LinearSVC, LogisticRegression
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame, Window, functions as F
from pyspark.sql.types import DoubleType

from ..functions.vectors import dot, mix
from ..session import cut
from .blocks import gram
from .hypergraph import Hypergraph


def split(ids: DataFrame, train: int = 20, number: int = 0, seed: int = 31) -> DataFrame:
    """(id, split, is_train): `train` percent of the ids, by hash of (id, split number)."""
    return ids.select("id", F.lit(number).alias("split"), (F.pmod(mix(F.col("id"), number, seed), F.lit(100)) < train).alias("is_train"))


def edge_majority_label(h: Hypergraph, labels: DataFrame) -> DataFrame:
    """(eid, y): most frequent label of the members; ties go to the smallest label."""
    n = h.inc.join(labels, "vid").groupBy("eid", "y").agg(F.count("*").alias("n"))
    w = Window.partitionBy("eid").orderBy(F.desc("n"), "y")
    return n.withColumn("r", F.row_number().over(w)).where(F.col("r") == 1).select("eid", "y")


def _ranges(df: DataFrame, by: str, bins: int = 4096) -> DataFrame:
    """With a column `bin`: equal ranges of the column `by`, in its order; at most `bins` of them."""
    ends = df.agg(F.min(by).alias("_low"), F.max(by).alias("_high"))
    span = F.col("_high").cast("double") - F.col("_low").cast("double")
    place = F.when(span > 0, F.floor((F.col(by).cast("double") - F.col("_low").cast("double")) / span * bins)).otherwise(F.lit(0))
    return df.crossJoin(F.broadcast(ends)).withColumn("bin", F.least(F.lit(bins - 1), place).cast("int")).drop("_low", "_high")


def _before(binned: DataFrame, count) -> DataFrame:
    """(bin, before): sum of `count` in the bins before; one small row per bin."""
    sums = binned.groupBy("bin").agg(count.alias("n"))
    w = Window.orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)
    return F.broadcast(sums.select("bin", F.coalesce(F.sum("n").over(w), F.lit(0)).alias("before")))


def negatives(edges: DataFrame, nodes: DataFrame, seed: int = 41, tries: int = 4) -> DataFrame:
    """(eid, vid): for each (eid, size) as many distinct random nodes; the j-th pick takes the first of `tries` salts that no earlier slot took.

    Nodes are numbered in order, range by range, after the counts of the ranges before.
    """
    binned = _ranges(nodes.select("vid"), "vid")
    inside = F.row_number().over(Window.partitionBy("bin").orderBy("vid")) - 1
    ranked = binned.withColumn("inside", inside).join(_before(binned, F.count("*")), "bin").select("vid", (F.col("before") + F.col("inside")).cast("int").alias("place"))
    n = ranked.count()
    slots = edges.select("eid", "size", F.explode(F.sequence(F.lit(0), F.col("size") * tries - 1)).alias("slot"))
    picks = slots.select("eid", "size", "slot", F.pmod(mix(F.col("eid"), F.col("slot"), seed), F.lit(n)).alias("place"))
    first = picks.groupBy("eid", "size", "place").agg(F.min("slot").alias("slot"))
    w = Window.partitionBy("eid").orderBy("slot")
    return first.withColumn("r", F.row_number().over(w)).where("r <= size").join(ranked, "place").select("eid", "vid")


def group_features(members: DataFrame, vectors: DataFrame, width: int, how: str = "range") -> DataFrame:
    """(id, vec) per group (eid, vid): per dimension maximum minus minimum ('range'), or maxima followed by minima ('concat')."""
    rows = members.join(vectors.select(F.col("id").alias("vid"), "vec"), "vid")
    tops = [F.max(F.col("vec")[i]).alias(f"a{i}") for i in range(width)]
    lows = [F.min(F.col("vec")[i]).alias(f"b{i}") for i in range(width)]
    g = rows.groupBy("eid").agg(*tops, *lows)
    parts = [F.col(f"a{i}") - F.col(f"b{i}") for i in range(width)] if how == "range" else [F.col(f"{x}{i}") for x in "ab" for i in range(width)]
    return g.select(F.col("eid").alias("id"), F.array(*[p.cast("double") for p in parts]).alias("vec"))


def _ridge(rows: DataFrame, classes: list, w: int, penalty: float) -> np.ndarray:
    """Ridge regression on one-hot targets from one aggregated Gram matrix."""
    target = [F.when(F.col("y") == c, 1.0).otherwise(0.0) for c in classes]
    g = gram(rows.select("id", F.concat("x", F.array(*target)).alias("vec")), w + len(classes))
    scale = max(np.trace(g[:w, :w]) / w, 1e-12)
    return np.linalg.solve(g[:w, :w] + penalty * scale * np.eye(w), g[:w, w:])


def _fitted(rows: DataFrame, classes: list, w: int, penalty: float, learner: str) -> np.ndarray:
    """Weights of multinomial logistic regression, or of one linear support vector machine per class; the last row holds intercepts.

    A class without a training row scores below all others; with a single class in training everything goes to it.
    """
    beta = np.zeros((w, len(classes)))
    seen = sorted(r["y"] for r in rows.select("y").distinct().collect())
    beta[-1] = [0.0 if c in seen else -1e9 for c in classes]
    if len(seen) < 2:
        return beta
    place = F.array_position(F.array(*[F.lit(c) for c in seen]), F.col("y")) - 1
    data = cut(rows.select(array_to_vector(F.slice("x", 1, w - 1)).alias("features"), place.cast("double").alias("label")), "train")
    if learner == "logistic":
        model = LogisticRegression(regParam=penalty, family="multinomial", standardization=False).fit(data)
        for k, c in enumerate(seen):
            beta[:, classes.index(c)] = np.r_[model.coefficientMatrix.toArray()[k], model.interceptVector[k]]
        return beta
    for k, c in enumerate(seen):
        model = LinearSVC(regParam=penalty, standardization=False).fit(data.withColumn("label", (F.col("label") == k).cast("double")))
        beta[:, classes.index(c)] = np.r_[model.coefficients.toArray(), model.intercept]
    return beta


def classify(vectors: DataFrame, labels: DataFrame, parts: DataFrame, width: int, ridge: float = 1e-3, learner: str = "ridge") -> DataFrame:
    """(id, y, predicted, score) of the test rows, by a linear learner: 'ridge', 'logistic' or 'svc'; `ridge` is its penalty.

    `labels` (id, y string), `parts` (id, is_train). Rows are scaled to unit length; a constant is added. Rows of null label
    take no part. The score is that of the last class.
    """
    if learner not in ("ridge", "logistic", "svc"):
        raise ValueError(f"no learner {learner}")
    labels = labels.where("y is not null")
    classes = [r["y"] for r in labels.select("y").distinct().orderBy("y").collect()]
    length = F.sqrt(dot(F.col("vec"), F.col("vec")))
    unit = F.when(length > 0, F.transform("vec", lambda x: x.cast("double") / length)).otherwise(F.transform("vec", lambda x: x.cast("double")))
    rows = vectors.select("id", F.concat(unit, F.array(F.lit(1.0))).alias("x")).join(labels, "id").join(parts.select("id", "is_train"), "id")
    if not classes:
        return rows.where("false").select("id", "y", F.col("y").alias("predicted"), F.lit(None).cast("double").alias("score"))
    train = rows.where("is_train")
    beta = _ridge(train, classes, width + 1, ridge) if learner == "ridge" else _fitted(train, classes, width + 1, ridge, learner)
    scores = F.array(*[dot(F.col("x"), F.array(*[F.lit(float(b)) for b in beta[:, k]])) for k in range(len(classes))])
    out = rows.where("not is_train").withColumn("s", scores)
    best = F.array_position(F.col("s"), F.array_max("s")) - 1
    return out.select("id", "y", F.element_at(F.array(*[F.lit(c) for c in classes]), (best + 1).cast("int")).alias("predicted"), F.col("s")[len(classes) - 1].alias("score"))


# Measures.


def f1_scores(pred: DataFrame) -> DataFrame:
    """One row (micro_f1, macro_f1) of (y, predicted); a class without any counts as 0."""
    long = pred.select(F.explode(F.array(F.struct(F.col("y").alias("c"), F.lit(1).alias("t"), F.lit(0).alias("p"), (F.col("y") == F.col("predicted")).cast("int").alias("tp")),
                                         F.struct(F.col("predicted").alias("c"), F.lit(0).alias("t"), F.lit(1).alias("p"), F.lit(0).alias("tp")))).alias("z")).select("z.*")
    per = long.groupBy("c").agg(F.sum("t").alias("t"), F.sum("p").alias("p"), F.sum("tp").alias("tp"))
    f1 = F.when(F.col("t") + F.col("p") > 0, 2 * F.col("tp") / (F.col("t") + F.col("p"))).otherwise(0.0)
    return per.agg((2 * F.sum("tp") / F.sum(F.col("t") + F.col("p"))).alias("micro_f1"), F.avg(f1).alias("macro_f1"))


def accuracy(pred: DataFrame) -> DataFrame:
    return pred.agg(F.avg((F.col("y") == F.col("predicted")).cast("double")).alias("accuracy"))


def auc(scores: DataFrame) -> DataFrame:
    """One row (auc) of (y boolean, score): rank sum with mid-ranks for ties, from counts per score, range by range of the scores."""
    per = _ranges(scores.groupBy("score").agg(F.count("*").alias("n"), F.sum(F.col("y").cast("int")).alias("pos")), "score")
    w = Window.partitionBy("bin").orderBy("score").rowsBetween(Window.unboundedPreceding, -1)
    mid = F.col("before") + F.coalesce(F.sum("n").over(w), F.lit(0)) + (F.col("n") + 1) / 2
    per = per.join(_before(per, F.sum("n")), "bin").withColumn("ranks", F.col("pos") * mid)
    p, n = F.sum("pos"), F.sum(F.col("n") - F.col("pos"))
    return per.agg(((F.sum("ranks") - p * (p + 1) / 2) / (p * n)).alias("auc"))


@F.pandas_udf(DoubleType())
def auc_of_group(y: pd.Series, score: pd.Series) -> float:
    """AUC as a grouped aggregate, for many groups each of which fits in a worker; `auc` is the form for one large group."""
    pos = float(y.sum())
    neg = len(y) - pos
    return float((score.rank()[y.astype(bool)].sum() - pos * (pos + 1) / 2) / (pos * neg)) if pos and neg else float("nan")


def average_rank(results: DataFrame) -> DataFrame:
    """(method, avg_rank) of (method, dataset, metric, value): rank 1 is the best; a missing value ranks last of all."""
    methods = results.select("method").distinct().count()
    w = Window.partitionBy("dataset", "metric").orderBy(F.desc("value"))
    ranked = results.withColumn("rank", F.when(F.col("value").isNull(), F.lit(methods)).otherwise(F.rank().over(w)))
    return ranked.groupBy("method").agg(F.avg("rank").alias("avg_rank"))


def similarity_mae(sim: DataFrame, vectors: DataFrame, scale: str = "both") -> DataFrame:
    """One row (mae) over the pairs of (source, id, sim): both sides divided by the mean of their own diagonal ('both'), or by that of the similarity ('reference')."""
    a, b = (vectors.select(F.col("id").alias(i), F.col("vec").alias(v)) for i, v in (("source", "va"), ("id", "vb")))
    rows = sim.join(a, "source").join(b, "id").select("source", "id", "sim", dot(F.col("va"), F.col("vb")).alias("dot"))
    means = rows.where("source = id").agg(F.avg("sim").alias("ms"), F.avg("dot").alias("md"))
    md = "md" if scale == "both" else "ms"
    return rows.crossJoin(F.broadcast(means)).agg(F.avg(F.abs(F.col("sim") / F.col("ms") - F.col("dot") / F.col(md))).alias("mae"))


def link_examples(h: Hypergraph, nodes: DataFrame, test_share: int = 20, seed: int = 41) -> tuple[Hypergraph, DataFrame]:
    """(training hypergraph, examples): examples are (id, eid, vid, y, is_train) memberships of real and of random hyperedges.

    Real hyperedges keep an even id 2 * eid, their random mates the odd one. The training hypergraph has no test hyperedge.
    """
    edges = h.inc.groupBy("eid").agg(F.count("*").cast("int").alias("size")).join(split(h.edges.select(F.col("eid").alias("id")), 100 - test_share).withColumnRenamed("id", "eid"), "eid")
    train = edges.where("is_train").select("eid")
    graph = Hypergraph(h.inc.join(train, "eid", "left_semi"), h.edges.join(train, "eid", "left_semi"))
    real = h.inc.select("eid", "vid").join(edges.select("eid", "is_train"), "eid").select((F.col("eid") * 2).alias("id"), "eid", "vid", F.lit("real").alias("y"), "is_train")
    fake = negatives(edges.select("eid", "size"), nodes, seed).join(edges.select("eid", "is_train"), "eid").select((F.col("eid") * 2 + 1).alias("id"), "eid", "vid", F.lit("fake").alias("y"), "is_train")
    return graph, real.unionByName(fake)


def link_scores(examples: DataFrame, vectors: DataFrame, width: int, how: str = "range") -> DataFrame:
    """One row (accuracy, auc) of real against random hyperedges from node vectors."""
    features = group_features(examples.select(F.col("id").alias("eid"), "vid"), vectors, width, how)
    marks = examples.select("id", "y", "is_train").distinct()
    pred = classify(features, marks.select("id", "y"), marks.select("id", "is_train"), width if how == "range" else 2 * width)
    return accuracy(pred).crossJoin(auc(pred.select((F.col("y") == "real").alias("y"), F.round("score", 12).alias("score"))))
