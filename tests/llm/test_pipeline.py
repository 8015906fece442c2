import random

import corpus_pipeline as cp
import pytest
from pyspark.sql import functions as F

from hyperembed.llm import toxicity

SF = "/root/testdata/sf0.001"
COLUMNS = "doc_id long, text string, lang string, source string, n_chars long, _id string, size long"


@pytest.fixture(scope="module")
def rows():
    rng = random.Random(6)
    words = [f"w{i}" for i in range(400)]
    make = lambda n: " ".join(rng.choice(words) for _ in range(n))
    texts = [make(rng.randint(5, 300)) for _ in range(40)]
    texts += [t + " tail" for t in texts[:8] if len(t.split()) > 60] + [t.upper() for t in texts[8:14]] + [texts[20]] * 5 + [None, "", "", " \n "]
    out = [(i, t, "en", "abc"[i % 3] if i % 7 else None, len(t or ""), "x", 3) for i, t in enumerate(texts)]
    return out + [(None, "no id here", "en", "a", 3, "x", 3), (3, texts[3], "en", "a", 3, "x", 3)]


def fold(text):
    return (text or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))


def shingles(text):
    w = (text or "").lower().split()
    return {tuple(w[i: i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def test_stages_against_brute_force(spark, rows):
    docs = spark.createDataFrame(rows, COLUMNS).repartition(3)
    stages = dict(cp.STAGES)
    assert list(stages) == ["toxicity", "exact dedup", "n-gram Jaccard join", "mixing sources to target weights", "SentencePiece encoding and decoding"]

    given = spark.read.parquet(f"{SF}/documents.parquet")
    clean = stages["toxicity"](spark, given, SF)
    model = toxicity.learn(given, spark.read.parquet(f"{SF}/labels.parquet"))
    want = sorted(r.doc_id for r in given.collect() if model.score(r.text) < 0.7)
    assert clean.columns == given.columns and sorted(r.doc_id for r in clean.collect()) == want

    once = stages["exact dedup"](spark, docs, SF)
    best = {}
    for r in rows:
        key = fold(r[1])
        best[key] = max(best.get(key, (-1,)), (-1 if r[0] is None else r[0],))
    assert once.columns == docs.columns
    assert sorted(-1 if r.doc_id is None else r.doc_id for r in once.collect()) == sorted(i for i, t in ((-1 if r[0] is None else r[0], r[1]) for r in rows) if i == best[fold(t)][0])

    kept = once.collect()
    one = stages["n-gram Jaccard join"](spark, once, SF)
    sets = {r.doc_id: shingles(r.text) for r in kept if r.doc_id is not None}
    root = {i: i for i in sets}
    for _ in sets:
        for a in sets:
            for b in sets:
                if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                    root[a] = root[b] = min(root[a], root[b])
    want = sorted(-1 if r.doc_id is None else r.doc_id for r in kept if r.doc_id is None or root[r.doc_id] == r.doc_id)
    assert one.columns == docs.columns and sorted(-1 if r.doc_id is None else r.doc_id for r in one.collect()) == want

    mixed = stages["mixing sources to target weights"](spark, one, SF)
    taken = {}
    for r in mixed.collect():
        taken[r.doc_id] = taken.get(r.doc_id, 0) + 1
    assert mixed.columns == docs.columns and all(n <= 3 * sum(r[0] == i for r in rows) for i, n in taken.items())
    total = sum(len((r.text or "").split()) for r in one.collect())
    assert abs(sum(len(r.text.split()) for r in mixed.collect()) - total) < 0.02 * total

    coded = stages["SentencePiece encoding and decoding"](spark, mixed, SF)
    text = {r.doc_id: r.text for r in mixed.collect()}
    from hyperembed.llm import sentence_pieces as sp

    lattice = sp.PieceLattice(cp.vocabulary("piece_bpe_32k.model"))
    got = coded.collect()
    assert len(got) == 2 * mixed.count()
    assert all(lattice.joined(list(r.ids)) == lattice.normal(text[r.doc_id]) for r in got)


def test_stages_on_an_empty_table(spark):
    docs = spark.createDataFrame([], COLUMNS)
    for _, stage in cp.STAGES:
        assert stage(spark, docs, SF).count() == 0


def test_driver_memory_is_given_back_between_stages(spark, monkeypatch):
    cp.give_back_driver(spark)
    calls = []
    monkeypatch.setattr(cp, "STAGES", [(str(k), lambda spark, docs, sf_dir: docs) for k in range(3)])
    monkeypatch.setattr(cp, "give_back_driver", calls.append)
    assert cp.run(spark, SF).count() == spark.read.parquet(f"{SF}/documents.parquet").count()
    assert len(calls) == 2


def test_workers_drop_what_other_stages_keep(monkeypatch):
    import functools

    from hyperembed.llm import common, sentence_pieces

    assert sentence_pieces.worker_lattice in common.HELD
    mine, other = functools.cache(lambda: [1]), functools.cache(lambda: [2])
    monkeypatch.setattr(common, "HELD", [mine, other])
    a, b = mine(), other()
    assert list(common.tidy(lambda batches: iter([1]), mine)([])) == [1]
    assert mine() is a and other() is not b


def test_executors_give_memory_back(spark):
    from hyperembed.llm import common

    beans = spark._jvm.java.lang.management.ManagementFactory.getGarbageCollectorMXBeans()
    count = lambda: sum(b.getCollectionCount() for b in beans)
    before = count()
    common.give_back_executors(spark)
    assert count() > before
