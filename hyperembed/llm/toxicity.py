"""Toxicity by weak supervision: lexicon and pattern voters, a generative label model, a linear classifier.

1. A bounded sample of labelled rows (at most `SAMPLE_ROWS`, the first by hash; only rows whose crc32(doc_id) mod 3 is not
   1) is thinned of near copies: of the rows that share their smallest 5-word shingle hash, one stays.
2. Words and word beginnings whose presence goes with the label, in each of two folds, become lexicon voters (at most
   `VOTERS`); fixed patterns vote as well.
3. Voters whose votes nearly coincide merge. The label model estimates, by expectation-maximisation, each voter's accuracy
   and the votes of voters that depend on each other; the given label is one more voter, so wrong labels can be outvoted.
4. A logistic regression learns the posterior labels from presence of the lexicon's words; it scores every whole text.

Defined results: null and empty texts get the score of a text without any feature. Rows that repeat a doc_id are scored
alike. With no labelled rows the model has no features and every text has the prior score 0.5 * smoothing. Ties in
the choice of features go by name.
"""

from __future__ import annotations

import re
from collections import Counter

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from .common import bounded_batches, stash, tidy
from .label_model import LabelModel

SAMPLE_ROWS, VOTERS, LEAST_DOCS = 12_000, 512, 4
BEGINNINGS = (4, 5, 6)
_LETTERS = re.compile(r"[^\W\d_]+")
#: Votes for label 1 from the form of a text alone.
PATTERNS = {
    "~masked": re.compile(r"[^\W\d_]\*+[^\W\d_]"),
    "~second_person": re.compile(r"\byou(?:'re| are) (?:a|an|so|such)\b", re.IGNORECASE),
    "~shouting": re.compile(r"(?:\b[A-Z]{4,}\b[ ,!]+){3}"),
}


def held_out(ident: Column) -> Column:
    return F.pmod(F.crc32(ident.cast("string").cast("binary")), F.lit(3)) == 1


def words_of(text: str | None) -> set[str]:
    return set(_LETTERS.findall((text or "").lower()))


def features_of(words: set[str]) -> set[str]:
    """Words, and beginnings of longer words (marked by a star)."""
    out = set(words)
    for n in BEGINNINGS:
        out.update([f"{w[:n]}*" for w in words if len(w) > n])
    return out


def smallest_shingle(text: str | None) -> int:
    w = _LETTERS.findall((text or "").lower())
    grams = pd.Series([" ".join(w[i: i + 5]) for i in range(max(1, len(w) - 4))])
    return int(pd.util.hash_array(grams.to_numpy(object), categorize=False).min().astype(np.int64))


def training_sample(docs: DataFrame, labels: DataFrame, text: str, ident: str, label: str, rows: int) -> DataFrame:
    """(_text, _label, _fold) of at most `rows` labelled rows for learning, without near copies; the choice is by hash."""
    marks = labels.select(F.col(ident).alias("_id"), F.col(label).cast("int").alias("_label")).where("_label in (0, 1)")
    marks = marks.where(~held_out(F.col("_id"))).groupBy("_id").agg(F.max("_label").alias("_label"))
    chosen = F.broadcast(marks.orderBy(F.xxhash64("_id"), "_id").limit(rows))  # at most `rows` rows
    texts = docs.select(F.col(ident).alias("_id"), F.col(text).alias("_text")).join(chosen, "_id")

    @F.pandas_udf("long")
    def key(t: pd.Series) -> pd.Series:
        return t.map(smallest_shingle)

    one = texts.withColumn("_key", key("_text")).groupBy("_key").agg(F.min_by(F.struct("_text", "_label"), F.xxhash64("_id")).alias("_x"))
    return stash(one.select("_x.*", F.col("_key").alias("_order")), "toxic-sample")


def _count_features(batches):
    """(feature, fold, toxic, all) sums of a partition."""
    toxic, every = Counter(), Counter()
    for b in batches:
        for text, label, fold in zip(*(c.to_pylist() for c in b.columns)):
            f = [(x, fold) for x in features_of(words_of(text))]
            every.update(f)
            if label:
                toxic.update(f)
    keys = list(every)
    for i in range(0, len(keys), 100_000):
        part = keys[i: i + 100_000]
        columns = [pa.array([k[0] for k in part], pa.string()), pa.array([k[1] for k in part], pa.int32()), pa.array([toxic[k] for k in part], pa.int64()), pa.array([every[k] for k in part], pa.int64())]
        yield pa.RecordBatch.from_arrays(columns, ["f", "fold", "toxic", "docs"])


def mine_lexicon(sample: DataFrame, voters: int, least: int) -> list[tuple[str, int, int]]:
    """The features that go most with label 1: (feature, toxic documents, documents).

    The sample falls into two folds by hash; what is found over both must hold in each by itself, so that a few wrong labels
    of one fold make no voter.
    """
    folds = sample.select("_text", "_label", F.pmod(F.xxhash64("_order"), F.lit(2)).cast("int").alias("fold"))
    counts = folds.mapInArrow(tidy(_count_features), "f string, fold int, toxic long, docs long")
    in_fold = lambda c, k: F.sum(F.when(F.col("fold") == k, F.col(c)).otherwise(0))
    counts = counts.groupBy("f").agg(F.sum("toxic").alias("toxic"), F.sum("docs").alias("docs"), *[in_fold(c, k).alias(f"{c}{k}") for c in ("toxic", "docs") for k in (0, 1)])
    rate = sample.agg(F.avg("_label").alias("r")).first()["r"] or 0.0
    if not 0 < rate < 1:
        return []
    k, n = F.col("toxic"), F.col("docs")
    share = (k + 0.5) / (n + 1)
    # Twice the gain in log-likelihood over the base rate.
    gain = 2 * (k * F.log(share / rate) + (n - k) * F.log((1 - share) / (1 - rate)))
    # Among so many features some gain this much by chance alone.
    tried = counts.where(n >= least).count()
    holds = (F.col("toxic0") > 0.6 * F.col("docs0")) & (F.col("toxic1") > 0.6 * F.col("docs1"))
    best = counts.where((k >= least) & (share > 0.75) & holds).withColumn("gain", gain).where(F.col("gain") > 1.9 * float(np.log(max(2, tried))))
    return [(r.f, r.toxic, r.docs) for r in best.orderBy(F.desc("gain"), "f").limit(voters).collect()]


def merge_voters(fires: np.ndarray, least: float = 0.8) -> np.ndarray:
    """Group number of each column; columns whose firings overlap by `least` (Jaccard) share a group."""
    m = fires.shape[1]
    group = np.arange(m)
    both = fires.T.astype(np.float32) @ fires.astype(np.float32)
    n = np.diag(both)
    near = both >= least * (n[:, None] + n[None, :] - both)
    for j in range(m):
        for i in np.flatnonzero(near[j, :j]):
            a, b = group[i], group[j]
            if a != b:
                group[group == max(a, b)] = min(a, b)
    return np.unique(group, return_inverse=True)[1]


class ToxicityModel:
    """Weights by feature, and what was learned on the way (voter groups, accuracies)."""

    def __init__(self, weights: dict[str, float], bias: float, voters: list, label_model: LabelModel | None):
        self.weights, self.bias, self.voters, self.label_model = weights, bias, voters, label_model
        self.words = {f: w for f, w in weights.items() if not f.startswith("~")}
        self.patterns = {f: w for f, w in weights.items() if f.startswith("~")}

    def score(self, text: str | None) -> float:
        total, w = self.bias, self.words
        found = set()
        for word in words_of(text):
            if word in w:
                found.add(word)
            for n in BEGINNINGS:
                if len(word) > n and (b := word[:n] + "*") in w:
                    found.add(b)
        total += sum(w[f] for f in found)
        total += sum(v for f, v in self.patterns.items() if v and PATTERNS[f].search(text or ""))
        return float(1 / (1 + np.exp(-np.clip(total, -60, 60))))


def _logistic(x: np.ndarray, target: np.ndarray, l2: float = 1.0, steps: int = 30) -> np.ndarray:
    """Weights (last: bias) of a regression on soft labels, by Newton steps."""
    x = np.c_[x, np.ones(len(x))].astype(float)
    w = np.zeros(x.shape[1])
    penalty = np.r_[np.full(x.shape[1] - 1, l2), 1e-3]
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (p - target) + penalty * w
        h = (x * (p * (1 - p))[:, None]).T @ x + np.diag(penalty + 1e-6)
        step = np.linalg.solve(h, g)
        w -= step
        if np.abs(step).max() < 1e-6:
            break
    return w


def _firing(features: list[str]):
    index = {f: i for i, f in enumerate(features)}

    def run(batches):
        for b in batches:
            hits = []
            for text in b.column(0).to_pylist():
                h = [index[f] for f in features_of(words_of(text)) if f in index]
                h += [index[f] for f, p in PATTERNS.items() if f in index and p.search(text or "")]
                hits.append(sorted(h))
            yield pa.RecordBatch.from_arrays([pa.array(hits, pa.list_(pa.int32())), b.column(1)], ["hits", "label"])

    return run


def learn(docs: DataFrame, labels: DataFrame, text: str = "text", ident: str = "doc_id", label: str = "toxic",
          rows: int = SAMPLE_ROWS, voters: int = VOTERS, least: int = LEAST_DOCS) -> ToxicityModel:
    bounded_batches(docs.sparkSession)
    sample = training_sample(docs, labels, text, ident, label, rows)
    lexicon = mine_lexicon(sample, voters, least)
    features = [f for f, _, _ in lexicon] + list(PATTERNS)
    hits = sample.orderBy("_order").select("_text", "_label").mapInArrow(tidy(_firing(features)), "hits array<int>, label int").toPandas()  # at most `rows` rows
    fires = np.zeros((len(hits), len(features)), bool)
    for i, h in enumerate(hits["hits"]):
        fires[i, h] = True
    given = hits["label"].to_numpy(float)
    if not lexicon:
        rate = (given.sum() + 0.5) / (len(given) + 1) if len(given) else 0.5
        return ToxicityModel({}, float(np.log(rate / (1 - rate))), [], None)
    group = merge_voters(fires)
    votes = np.zeros((len(fires), group.max() + 3), np.int8)
    for j, g in enumerate(group):
        votes[fires[:, j], g] = 1
    votes[:, -2] = np.where(fires.any(1), 0, -1)  # no voter speaks up: a vote for label 0
    votes[:, -1] = np.where(given > 0, 1, -1)  # the given label
    pattern, inverse, counts = np.unique(votes, axis=0, return_inverse=True, return_counts=True)
    anchor = np.bincount(inverse.ravel(), weights=given, minlength=len(pattern)) / counts
    model = LabelModel(prior=float(given.mean())).fit(pattern, counts, np.clip(anchor, 0.02, 0.98))
    w = _logistic(fires, model.posterior(votes), l2=0.05)
    kept = {f: float(v) for f, v in zip(features, w) if abs(v) > 1e-9}
    return ToxicityModel(kept, float(w[-1]), [(f, int(g)) for f, g in zip(features, group)], model)


def score(docs: DataFrame, model: ToxicityModel, text: str = "text", ident: str = "doc_id", threshold: float = 0.7, carry: bool = False) -> DataFrame:
    """(ident, held_out, score, predicted) of every row; with `carry`, `_row` instead of ident. The model goes to executors with the task (bounded by `VOTERS`)."""

    @F.pandas_udf("double")
    def scored(t: pd.Series) -> pd.Series:
        return t.map(model.score, na_action=None).astype(float)

    first = F.struct("*").alias("_row") if carry else F.col(ident)
    out = docs.select(first, F.coalesce(held_out(F.col(ident)), F.lit(False)).alias("held_out"), scored(F.col(text)).alias("score"))
    return out.withColumn("predicted", (F.col("score") >= threshold).cast("int"))
