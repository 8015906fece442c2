"""Quality rules by weak supervision: every rule votes or abstains, expectation-maximisation weighs the rules.

One pass over the texts counts what the rules need; the votes of a document are one number in base 3. The label model sees
the histogram of those numbers (at most 3 ** rules rows, whatever the corpus) and gives each a posterior probability of
good quality, which takes the place of a filter that every rule must pass.

The model starts from the guess that bad texts fail a rule now and then and good ones hardly ever; that start counts as a few
documents. How often each rule is right, and which rules see the same fault, comes from the corpus: an objection that no
other rule ever shares is weak, one that comes with others or whose rule the others bear out is strong.

Defined results: a null or empty text has no words, all counts are 0 and base_failed is true. Rows that repeat a doc_id
are documents of their own. On an empty table the model keeps its start values and the result is empty.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import bounded_batches, stash, tidy
from .label_model import LabelModel

SYMBOLS = b"#*$%&|<>"
BLANK = b" \t\n\x0b\x0c\r"
CAPITALS = bytes(range(65, 91))
SMALL = bytes(range(97, 123))
TAILS = bytes(range(128, 192))
DIGITS = b"0123456789"
#: A text of fewer words, or with a larger share of repeated words (in percent), fails without a vote.
LEAST_WORDS, MOST_REPEATED = 50, 50

#: name: (bad below, good from, good to, bad above) of a ratio; None: no such vote. Between them the rule abstains.
RULES = {
    "word_length": (2.5, 3.5, 7.0, 10.0),
    "symbols_per_word": (None, 0.0, 0.005, 0.1),
    "duplicate_lines": (None, 0.0, 0.05, 0.3),
    "repeated_words": (None, 0.0, 0.05, 0.25),
    "capital_share": (None, 0.005, 0.15, 0.4),
    "exclamations_per_word": (None, 0.0, 0.02, 0.2),
    "digit_share": (None, 0.0, 0.1, 0.3),
    "distinct_words": (0.1, 0.3, 1.0, None),
    "words_with_letters": (0.8, 0.95, 1.0, None),
    "words_without_symbols": (0.7, 0.97, 1.0, None),
    "commonest_word": (None, 0.0, 0.1, 0.25),
    "letter_share": (0.7, 0.8, 1.0, None),
}
#: Where the model starts: shares of votes against, abstentions and votes for, on bad (0) and on good texts (1).
START = {0: (0.3, 0.1, 0.6), 1: (0.01, 0.09, 0.9)}
#: Shapes of letters: a word is its letters, digits, symbols and other marks.
_SHAPES = bytes.maketrans(bytes(range(256)), bytes(
    b[0] if (b := bytes([k])) in (b" ", b"\t", b"\n", b"\x0b", b"\x0c", b"\r") else ord("a") if b.isalpha() or k > 127 else ord("0") if b.isdigit() else ord("#") if b in SYMBOLS else ord(".")
    for k in range(256)
))
STATS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def _count(data: bytes, which: bytes) -> int:
    return len(data) - len(data.translate(None, which))


def repeated_words(words: list) -> tuple[int, int, int]:
    """(words that lie in a 3-word window found twice or more, distinct words, occurrences of the commonest word)."""
    seen: dict = {}
    ids = np.array([seen.setdefault(w, len(seen)) for w in words], np.int64)
    n, k = len(ids), len(seen)
    top = int(np.bincount(ids).max()) if n else 0
    if n < 4 or k == n:
        return 0, k, top
    pair = ids[:-1] * k + ids[1:]
    if k > 1 << 20:  # three ids would not fit in 63 bits
        pair = np.unique(pair, return_inverse=True)[1].astype(np.int64)
        k = int(max(k, pair.max() + 1))
    window = pair[:-1] * k + ids[2:]
    order = np.argsort(window, kind="stable")
    same = window[order][1:] == window[order][:-1]
    again = np.zeros(n - 2, bool)
    again[order[1:][same]] = True
    again[order[:-1][same]] = True
    cover = np.zeros(n, bool)
    cover[:-2] |= again
    cover[1:-1] |= again
    cover[2:] |= again
    return int(cover.sum()), len(seen), top


def measure(text: str | None) -> tuple:
    """STATS, then lines with a word, capitals, small letters, exclamation marks, digits, distinct words, the commonest word's number,
    words with a letter, words without a symbol, bytes and bytes of letters in words."""
    data = (text or "").encode("utf-8", "surrogatepass")
    words = data.split()
    dense = data.translate(None, BLANK)
    lines, dups, seen = 0, 0, set()
    for line in data.split(b"\n"):
        if line.strip(BLANK):
            lines += 1
            if line in seen:
                dups += 1
            else:
                seen.add(line)
    repeats, distinct, top = repeated_words(words)
    skeleton = data.translate(_SHAPES)
    shapes = Counter(skeleton.split())
    lettered, clean = sum([n for s, n in shapes.items() if b"a" in s]), sum([n for s, n in shapes.items() if b"#" not in s])
    return (len(words), len(dense) - _count(dense, TAILS), _count(data, SYMBOLS), dups, repeats,
            lines, _count(data, CAPITALS), _count(data, SMALL), data.count(b"!"), _count(data, DIGITS), distinct, top, lettered, clean, len(dense), skeleton.count(b"a"))


def rule_votes(stats: np.ndarray) -> np.ndarray:
    """Votes of RULES, in order, for rows of `measure`."""
    words, chars, symbols, dups, repeats, lines, capitals, small, marks, digits, distinct, top, lettered, clean, size, letters = stats.T.astype(float)
    some = lambda x: np.maximum(x, 1)
    ratios = {
        "word_length": chars / some(words), "symbols_per_word": symbols / some(words), "duplicate_lines": dups / some(lines),
        "repeated_words": repeats / some(words), "capital_share": capitals / some(capitals + small),
        "exclamations_per_word": marks / some(words), "digit_share": digits / some(chars),
        # Distinct words thin out with length; the square root keeps the ratio comparable.
        "distinct_words": np.minimum(1, distinct / some(10 * np.sqrt(words))),
        "words_with_letters": lettered / some(words), "words_without_symbols": clean / some(words),
        # The commonest word of a short text is common by chance.
        "commonest_word": np.where(words < 20, 0.15, top / some(words)), "letter_share": letters / some(size),
    }
    out = np.zeros((len(stats), len(RULES)), np.int8)
    for k, (name, (low, good, to, high)) in enumerate(RULES.items()):
        x = ratios[name]
        out[(x >= good) & (x <= to), k] = 1
        out[((x < low) if low is not None else False) | ((x > high) if high is not None else False), k] = -1
    out[words == 0] = 0
    return out


def _measured(batches):
    base = 3 ** np.arange(len(RULES), dtype=np.int64)
    for b in batches:
        stats = np.array([measure(t) for t in b.column(1).to_pylist()], np.int64).reshape(b.num_rows, -1)
        pattern = ((rule_votes(stats) + 1) * base).sum(1).astype(np.int32)
        columns = [b.column(0), *(pa.array(stats[:, k]) for k in range(len(STATS))), pa.array(pattern)]
        yield pa.RecordBatch.from_arrays(columns, ["_id", *STATS, "pattern"])


def votes_of(patterns: np.ndarray) -> np.ndarray:
    return np.stack([np.asarray(patterns) // 3**k % 3 - 1 for k in range(len(RULES))], 1) if len(patterns) else np.zeros((0, len(RULES)), int)


def measure_documents(df: DataFrame, text: str = "text", ident: str = "doc_id") -> DataFrame:
    """(_id, STATS, pattern), written to the shared folder."""
    bounded_batches(df.sparkSession)
    kind = df.schema[ident].dataType.simpleString()
    schema = f"_id {kind}, {', '.join(f'{s} long' for s in STATS)}, pattern int"
    return stash(df.select(F.col(ident).alias("_id"), F.col(text).alias("_text")).mapInArrow(tidy(_measured), schema), "quality")


def fit_rules(measured: DataFrame) -> tuple[LabelModel, dict[int, float]]:
    """The label model over all documents with words, and the posterior of every vote pattern that occurs."""
    rows = measured.groupBy("pattern").agg(F.sum(F.expr("cast(n_words > 0 as long)")).alias("n")).orderBy("pattern").collect()
    patterns, counts = np.array([r.pattern for r in rows], int), np.array([r.n for r in rows], float)
    votes = votes_of(patterns)
    model = fit_votes(votes, counts)
    return model, dict(zip(patterns.tolist(), model.posterior(votes).tolist()))


def fit_votes(votes: np.ndarray, counts: np.ndarray) -> LabelModel:
    """The label model of vote patterns."""
    return LabelModel(prior=0.9, start=START).fit(votes, counts)


def judge(df: DataFrame, text: str = "text", ident: str = "doc_id", threshold: float = 0.5) -> DataFrame:
    """(ident, STATS, base_failed, quality, kept): quality is the posterior probability, kept its verdict at `threshold`."""
    measured = measure_documents(df, text, ident)
    _, posterior = fit_rules(measured)
    spark = df.sparkSession
    lookup = F.broadcast(spark.createDataFrame(list(posterior.items()), "pattern int, quality double"))  # at most 3 ** rules rows
    failed = (F.col("n_words") < LEAST_WORDS) | (100 * F.col("n_repeat_words") > MOST_REPEATED * F.col("n_words"))
    return measured.join(lookup, "pattern").select(
        F.col("_id").alias(ident), *STATS, failed.alias("base_failed"), "quality", (~failed & (F.col("quality") >= threshold)).alias("kept")
    )
