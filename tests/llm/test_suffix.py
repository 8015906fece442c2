import hashlib
import random

import numpy as np

from hyperembed.llm import suffix_dedup as sd


def brute(rows, length=50):
    """(n_bytes, n_removed, n_spans, sha) per row, string by string."""
    first = {}
    for i, text in rows:
        data = (text or "").encode()
        for k in range(len(data) - length + 1):
            if i is not None:
                w = data[k: k + length]
                first[w] = min(i, first.get(w, i))
    out = []
    for i, text in rows:
        data = (text or "").encode()
        gone = np.zeros(len(data) + 1, bool)
        for k in range(len(data) - length + 1):
            if i is not None and first[data[k: k + length]] < i:
                gone[k: k + length] = True
        kept = bytes(b for b, g in zip(data, gone) if not g)
        out.append((i, len(data), int(gone.sum()), int((gone[1:] & ~gone[:-1]).sum() + gone[0]), hashlib.sha256(kept).hexdigest()))
    return out


def texts(seed):
    rng = random.Random(seed)
    words = ["ab", "the", "naïve", "xx", "quick", "b", "aaaa", "longerword"]
    make = lambda n: " ".join(rng.choice(words) for _ in range(n))
    passages = [make(14) for _ in range(4)] + ["z" * 70, "ababab" * 20]
    rows = []
    for i in range(60):
        parts = [make(rng.randint(0, 40))]
        for _ in range(rng.randint(0, 3)):
            p = rng.choice(passages)
            cut = rng.randint(0, 20)
            parts += [p[cut:], make(rng.randint(0, 9))]
        rows.append((i, " ".join(parts)))
    rows += [(100, rows[3][1]), (101, rows[3][1]), (101, rows[5][1]), (102, None), (103, ""), (104, "short"), (None, rows[3][1]), (2, rows[9][1])]
    rng.shuffle(rows)
    return rows


def test_against_brute_force(spark):
    for seed in (1, 2):
        rows = texts(seed)
        df = spark.createDataFrame([(*r, "x") for r in rows], "doc_id long, text string, _copy string").repartition(3)
        got = sorted(map(repr, (tuple(r) for r in sd.remove_repeats(df).drop("kept").collect())))
        assert got == sorted(map(repr, brute(rows)))


def test_hot_anchors_take_the_other_way(spark, monkeypatch):
    monkeypatch.setattr(sd, "HOT", 3)
    rows = texts(3)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = sorted(map(repr, (tuple(r) for r in sd.remove_repeats(df).drop("kept").collect())))
    assert got == sorted(map(repr, brute(rows)))
    assert sd.remove_repeats(df.limit(0)).count() == 0


def test_deep_shallow_sort_orders_windows():
    rng = np.random.default_rng(5)
    text = rng.integers(97, 99, 600).astype(np.uint8)
    text[100:180] = text[300:380]
    text[400:470] = 97
    starts = np.arange(len(text) - 50 + 1)
    order, new = sd.deep_shallow_sort(text, starts, 50)
    data = text.tobytes()
    windows = [data[s: s + 50] for s in starts[order]]
    assert windows == sorted(windows)
    assert [True, *(a != b for a, b in zip(windows, windows[1:]))] == new.tolist()


def test_every_window_has_an_anchor_of_its_text():
    rng = np.random.default_rng(7)
    data = rng.integers(97, 100, 3000).astype(np.uint8)
    ends = np.array([700, 700, 749, 1500, 3000])
    at, _ = sd.anchors(data, ends)
    start = 0
    for e in ends:
        for k in range(start, e - 49):
            inside = at[(at >= k) & (at + sd.GRAM <= k + 50)]
            assert len(inside)
        start = e


def test_multikey_quicksort_in_buckets():
    rng = np.random.default_rng(4)
    text = rng.integers(97, 100, 4000).astype(np.uint8)
    text[1000:1060] = text[2000:2060] = text[3000:3060]
    starts = rng.integers(0, 3940, 1500)
    bucket = rng.integers(0, 7, 1500)
    order, new = sd.deep_shallow_sort(text, starts, 50, bucket=bucket)
    windows = [(int(bucket[i]), text[starts[i]: starts[i] + 50].tobytes()) for i in order]
    assert windows == sorted(windows) and sorted(order.tolist()) == list(range(1500))
    assert new.tolist() == [k == 0 or windows[k] != windows[k - 1] for k in range(1500)]


def test_packed_tokens_round_trip():
    for n in (0, 1, 5000):
        tokens = np.sort(np.random.default_rng(n).integers(0, 2**32, n).astype(np.uint32))
        assert (sd.unpack_sorted(sd.pack_sorted(tokens)) == tokens).all()


def test_empty_table_and_very_long_texts(spark):
    schema = "doc_id long, text string, kept string, _id string"
    assert sd.remove_repeats(spark.createDataFrame([], schema)).count() == 0
    long = " ".join(f"word{i * i % 9973}" for i in range(60_000))
    rows = [(1, long), (2, "other start " + long[1000:200_000]), (3, "q" * 300_000), (4, "q" * 60)]
    got = sorted(tuple(r) for r in sd.remove_repeats(spark.createDataFrame([(*r, "x", "y") for r in rows], schema)).drop("kept").collect())
    assert [r[:3] for r in got] == [(1, len(long), 0), (2, 12 + 199_000, 199_000), (3, 300_000, 0), (4, 60, 60)]
