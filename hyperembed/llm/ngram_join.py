"""Jaccard self-join on word shingles by token-combination prefixes, and the classes that its links form.

Texts with equal shingle sets collapse to one node first. Tokens (shingles) have two classes. A token is frequent if at
least `level` sets hold it (kept in a bitmap of fixed size; a false hit there only makes a rare token frequent), else
rare. In the global order rare tokens come first. Two sets with similarity t share all but floor(n (1 - t)) of n tokens,
so with d = floor(n (1 - t)) + 1:

* a set with d rare tokens is indexed under the first d of them, one by one;
* any other set is indexed under all its rare tokens, and its prefix is extended over frequent tokens, which are dealt
  into sub-classes, until rare tokens plus, per sub-class, tokens beyond the first reach d. Every pair of prefix tokens of a
  sub-class is indexed. Losing n - overlap tokens lowers that sum by no more, so a similar pair shares a token or a pair.

The number of sub-classes must be the same for both sets of a pair, so it belongs to a band of sizes; similar sets lie in
one band or in neighbouring ones, and each set is indexed for its own band and the next.

Buckets of rare tokens are small by definition and give all their pairs. Buckets of token pairs can hold a third of the
corpus: partitions reduce them to stars first, and only members of different classes of a bucket meet afterwards, until
none are left untried. Each candidate is verified on the whole sets.

Defined results: null, empty and blank texts have no shingles and link with nothing; a null doc_id links with nothing and
its class is null; rows that repeat a doc_id with other texts are nodes of their own; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F

from .common import bounded_batches, maybe_broadcast, stash, tidy

WORDS = 5
#: Bits of the bitmap of frequent tokens.
MAP_BITS = 26
#: A token is frequent from so many sets on: the least of these that fills at most a quarter of the bitmap, else the last.
LEVELS = (16, 64, 256)
SUBCLASS_SHARE = 0.15
FLUSH = 600_000
#: Sizes of candidates are compared in steps of this logarithm: five steps cover a ratio of 4/3.
STEP = np.log(1.07)
#: Members of a tile in which classes of open buckets are compared.
TILE = 512
U = np.uint64
_MIX1, _MIX2, _STEP = U(0xBF58476D1CE4E5B9), U(0x94D049BB133111EB), U(0x9E3779B97F4A7C15)


def mix64(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> U(30))) * _MIX1
    x = (x ^ (x >> U(27))) * _MIX2
    return x ^ (x >> U(31))


def size_bands() -> np.ndarray:
    """Lower ends of the bands; each is at least 4/3 of the one before."""
    ends = [1]
    while ends[-1] < 1 << 40:
        ends.append(max(ends[-1] + 1, -(-ends[-1] * 4 // 3)))
    return np.array(ends, np.int64)


BANDS = size_bands()


class Shingler(dict):
    """Sorted 64-bit hashes of a text's distinct shingles; remembers the hashes of words."""

    def __init__(self, words: int = WORDS, entries: int = 100_000):
        super().__init__()
        self.words, self.entries = words, entries

    def __missing__(self, word: bytes) -> int:
        if len(self) > self.entries:
            self.clear()
        h = self[word] = xxhash.xxh3_64_intdigest(word)
        return h

    def __call__(self, text: str | None) -> np.ndarray:
        words = (text or "").encode("utf-8", "surrogatepass").lower().split()
        n = len(words)
        if not n:
            return np.zeros(0, U)
        h = np.fromiter(map(self.__getitem__, words), U, n)
        k = min(n, self.words)
        s = np.full(n - k + 1, k, U)
        for i in range(k):
            s = s * _STEP + h[i: n - k + 1 + i]
        return np.unique(mix64(s))


def set_key(s: np.ndarray) -> bytes:
    return xxhash.xxh3_128_digest(s.tobytes())


def band_of(n: int) -> int:
    return int(np.searchsorted(BANDS, n, "right")) - 1


def handle_of(key: bytes, n: int, rare: int) -> int:
    """Share of rare tokens (8 bits), 48 bits of the key, a step of the size (8 bits).

    The least handle of a bucket is its most central set: edits make tokens rare, so an original stands before its
    copies and links with them where copies do not link with each other. Handles need not be unique, since candidates
    are verified by key.
    """
    return (min(255, rare * 256 // n) << 56 | int.from_bytes(key[:6], "little") << 8 | min(255, int(np.log(n) / STEP))) - (1 << 63)


def profile_of(s: np.ndarray) -> bytes:
    """Tokens of the set by upper bits of a hash, in as many classes (a power of two) as it has tokens, or up to twice that.

    The sum of the lesser counts of two profiles bounds the overlap of their sets from above. Counts stop at 255, which
    no real class reaches: there are as many classes as tokens.
    """
    bits = max(3, int(len(s) - 1).bit_length())
    return np.minimum(255, np.bincount((mix64(s) >> U(64 - bits)).astype(np.int64), minlength=1 << bits)).astype(np.uint8).tobytes()


def overlap_bound(a: bytes, b: bytes) -> int:
    """Upper bound of the overlap of two sets, from their profiles."""
    x, y = (np.frombuffer(p, np.uint8).astype(np.int32) for p in (a, b))
    while len(x) > len(y):
        x = x[::2] + x[1::2]
    while len(y) > len(x):
        y = y[::2] + y[1::2]
    full = (x >= 255) | (y >= 255)
    return int(np.minimum(x, y).sum()) + (1 << 40) * bool(full.any())


def prefix_signatures(s: np.ndarray, frequent: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(tokens indexed one by one, hashes of indexed token pairs) of a set; `frequent` marks its tokens. Similarity 3/4."""
    n = len(s)
    need = n // 4 + 1
    rare = s[~frequent]
    if len(rare) >= need:
        return rare[:need], np.zeros(0, U)
    often, need = s[frequent], need - len(rare)
    out = []
    band = band_of(n)
    for scheme in (band, band + 1):
        parts = max(1, int(SUBCLASS_SHARE * BANDS[scheme]))
        sub = (mix64(often ^ U(0xA5A5A5A5)) % U(parts)).astype(np.int64)
        order = np.argsort(sub, kind="stable")
        beyond = np.ones(len(often), np.int64)  # 0 for the first token of each sub-class
        beyond[order[np.r_[True, sub[order][1:] != sub[order][:-1]]] if len(order) else order] = 0
        end = int(np.searchsorted(np.cumsum(beyond), need)) + 1
        order = order[order < end]
        token, sub = often[order], sub[order]
        for lag in range(1, len(token)):
            same = sub[lag:] == sub[:-lag]
            if not same.any():
                break
            out.append(mix64(token[:-lag][same] * _STEP + token[lag:][same] + U(scheme + 1)))
    return rare, np.unique(np.concatenate(out)) if out else np.zeros(0, U)


def _fresh_sets(batches, shingler, named: bool = False):
    """(id, set, key) of the rows; the set is None where this partition has had it before. With `named`, only rows with an id have sets."""
    seen: set[bytes] = set()
    for b in batches:
        for ident, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
            s = shingler(text)
            if not len(s):
                yield ident, None, None, 0
                continue
            key = set_key(s)
            new = key not in seen and not (named and ident is None)
            if new:
                if len(seen) > 500_000:
                    seen.clear()
                seen.add(key)
            yield ident, s if new else None, key, len(s)


def _blocks(values: np.ndarray, bits: int, *more: np.ndarray):
    """Cut sorted uint64 values by their upper bits: (block, low 32 bits of the rest, ...)."""
    block = (values >> U(64 - bits)).astype(np.int64)
    cut = np.r_[np.flatnonzero(np.r_[True, block[1:] != block[:-1]]), len(values)]
    low = ((values >> U(32 - bits)) & U(0xFFFFFFFF)).astype("<u4")
    for i, j in zip(cut[:-1], cut[1:]):
        yield int(block[i]), low[i:j].tobytes(), *(m[i:j].tobytes() for m in more)


def _token_pieces(bits: int, words: int):
    def flush(sets):
        rows = list(_blocks(np.sort(np.concatenate(sets)), bits))
        return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary())], ["block", "tokens"])

    def run(batches):
        sets, n = [], 0
        for _, s, _, _ in _fresh_sets(batches, Shingler(words)):
            if s is not None:
                sets.append(s)
                n += len(s)
                if n >= FLUSH:
                    yield flush(sets)
                    sets, n = [], 0
        if n:
            yield flush(sets)

    return run


def _frequent_segments(bits: int, levels):
    """Of one block, for each level the bitmap segment of its tokens held by so many sets, and their number."""
    width = MAP_BITS - bits  # bits of a place within the segment

    def run(key, t):
        tokens = np.sort(np.concatenate([np.frombuffer(x, "<u4") for x in t.column("tokens").to_pylist()]))
        first = np.flatnonzero(np.r_[True, tokens[1:] != tokens[:-1]])
        count = np.diff(np.r_[first, len(tokens)])
        place = tokens[first] >> np.uint32(32 - width)
        out = {"block": [key[0].as_py()]}
        for k, level in enumerate(levels):
            bitmap = np.zeros(1 << width, bool)
            bitmap[place[count >= level]] = True
            out[f"n{k}"] = [int(bitmap.sum())]
            out[f"map{k}"] = [np.packbits(bitmap).tobytes() if bitmap.any() else None]
        kinds = {"block": pa.int32()} | {f"n{k}": pa.int64() for k in range(len(levels))} | {f"map{k}": pa.binary() for k in range(len(levels))}
        return pa.table({c: pa.array(out[c], kinds[c]) for c in kinds})

    return run


def frequent_tokens(docs: DataFrame, bits: int, words: int = WORDS, levels=LEVELS) -> tuple[np.ndarray, np.ndarray, int]:
    """(bitmap of shared tokens, of frequent tokens, level) over all texts, 2 ** MAP_BITS bits each; the driver holds no more.

    Shared tokens are those that two sets or more hold; others cannot lead to a partner.
    """
    levels = (2, *levels)
    pieces = docs.mapInArrow(tidy(_token_pieces(bits, words)), "block int, tokens binary")
    columns = ["block int", *(f"n{k} long" for k in range(len(levels))), *(f"map{k} binary" for k in range(len(levels)))]
    segments = stash(pieces.groupBy("block").applyInArrow(_frequent_segments(bits, levels), ", ".join(columns)), "frequent")
    sums = segments.agg(*[F.sum(f"n{k}").alias(f"n{k}") for k in range(len(levels))]).first()
    k = next((k for k in range(1, len(levels)) if (sums[k] or 0) <= 1 << (MAP_BITS - 2)), len(levels) - 1)
    maps = [np.zeros(1 << (MAP_BITS - 3), np.uint8) for _ in range(2)]
    size = 1 << (MAP_BITS - 3 - bits)
    for r in segments.where("map0 is not null").select("block", "map0", f"map{k}").toLocalIterator():
        for bitmap, x in zip(maps, r[1:]):
            if x is not None:
                bitmap[r[0] * size: (r[0] + 1) * size] = np.frombuffer(x, np.uint8)
    return maps[0], maps[1], levels[k]


def is_marked(s: np.ndarray, bitmap: np.ndarray) -> np.ndarray:
    place = (s >> U(64 - MAP_BITS)).astype(np.int64)
    return (bitmap[place >> 3] >> (7 - (place & 7)).astype(np.uint8) & 1).astype(bool)


#: Rows of documents (block is null), and pieces of the index by block; block -1 holds stars.
INDEX = "key binary, handle long, n long, pairs array<long>, profile binary, block int, sigs binary, singles int, handles binary"


def _index_rows(shared, frequent, bits: int, kind: pa.DataType, words: int):
    """One pass over the texts of a partition: a row per document, and its index entries by block.

    Signatures of token pairs and the profile stand at the first document of a set. Buckets of token pairs keep their first
    member of the partition, the others give a star; buckets of single tokens keep all.
    """
    names = ["_id", "key", "handle", "n", "pairs", "profile", "block", "sigs", "singles", "handles"]
    types = [kind, pa.binary(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.binary(), pa.int32(), pa.binary(), pa.int32(), pa.binary()]

    def batch(rows):
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), types)], names)

    def flush(parts):
        out = []
        blocks: dict[int, list] = {}
        for which in (0, 1):
            sig = np.concatenate([p[which] for p in parts])
            handle = np.repeat(np.array([p[2] for p in parts], np.int64), [len(p[which]) for p in parts])
            order = np.lexsort((handle, sig))
            sig, handle = sig[order], handle[order]
            if which and len(sig):
                first = np.r_[True, sig[1:] != sig[:-1]]
                head = handle[np.maximum.accumulate(np.where(first, np.arange(len(sig)), 0))]
                star = ~first & (handle != head)
                if star.any():
                    edges = np.unique(np.stack([head[star], handle[star]]), axis=1)
                    out.append((*[None] * 6, -1, None, None, edges.astype("<i8").tobytes()))
                sig, handle = sig[first], handle[first]
            for block, low, own in _blocks(sig, bits, handle.astype("<i8")) if len(sig) else ():
                blocks.setdefault(block, [b"", b"", b"", b""])[2 * which: 2 * which + 2] = [low, own]
        for block, (low, own, low2, own2) in blocks.items():
            out.append((*[None] * 6, block, low + low2, len(low) // 4, own + own2))
        return batch(out) if out else None

    def run(batches):
        rows, parts, n = [], [], 0
        for ident, s, key, size in _fresh_sets(batches, Shingler(words), named=True):
            handle = pairs = profile = None
            if s is not None:
                often = is_marked(s, frequent.value)
                handle = handle_of(key, size, size - int(np.count_nonzero(often)))
                singles, combos = prefix_signatures(s, often)
                singles = singles[is_marked(singles, shared.value)]
                if len(singles) or len(combos):
                    parts.append((np.sort(mix64(singles + U(77))), combos, handle))
                    n += len(singles) + len(combos)
                    profile = profile_of(s)
                pairs = combos.view(np.int64) if len(combos) else None
            rows.append((ident, key, handle, size, pairs, profile, None, None, None, None))
            if len(rows) >= 2000:
                yield batch(rows)
                rows = []
            if n >= FLUSH:
                if (b := flush(parts)) is not None:
                    yield b
                parts, n = [], 0
        if rows:
            yield batch(rows)
        if n and (b := flush(parts)) is not None:
            yield b

    return run


def _star_rows(batches):
    for b in batches:
        for handles in b.column(0).to_pylist():
            e = np.frombuffer(handles, "<i8").reshape(2, -1)
            meet = _sizes_meet(e[0], e[1])
            yield pa.RecordBatch.from_arrays([pa.array(e[0][meet]), pa.array(e[1][meet])], ["a", "b"])


def _sizes_meet(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.abs((a & 255) - (b & 255)) <= 5


def _bucket_pairs(key, t):
    """Candidates of one block: all pairs of a rare token's bucket, a star for a token pair's bucket."""
    sig = np.concatenate([np.frombuffer(x, "<u4") for x in t.column("sigs").to_pylist()]).astype(U)
    handle = np.concatenate([np.frombuffer(x, "<i8") for x in t.column("handles").to_pylist()])
    combo = np.concatenate([np.arange(len(x) // 4) >= k for x, k in zip(t.column("sigs").to_pylist(), t.column("singles").to_pylist())])
    sig = sig << U(1) | combo.astype(U)
    order = np.lexsort((handle, sig))
    sig, handle, combo = sig[order], handle[order], combo[order]
    new = np.r_[True, (sig[1:] != sig[:-1]) | (handle[1:] != handle[:-1])]
    sig, handle, combo = sig[new], handle[new], combo[new]
    first = np.r_[True, sig[1:] != sig[:-1]]
    head = handle[np.maximum.accumulate(np.where(first, np.arange(len(sig)), 0))]
    star = combo & ~first
    star[star] = _sizes_meet(head[star], handle[star])
    found = [np.stack([head[star], handle[star]])]
    size = np.diff(np.r_[np.flatnonzero(first), len(sig)])
    alone = np.repeat((size > 1), size) & ~combo
    s, h = sig[alone], handle[alone]
    for lag in range(1, int(size.max(initial=1))):
        same = s[lag:] == s[:-lag]
        if not same.any():
            break
        a, b = h[:-lag][same], h[lag:][same]
        meet = _sizes_meet(a, b)
        found.append(np.unique(np.stack([a[meet], b[meet]]), axis=1))
    e = np.unique(np.concatenate(found, axis=1), axis=1)
    return pa.table({"a": e[0], "b": e[1]})


def _bound_filter(batches):
    """Keys of pairs whose profiles leave room for the similarity."""
    for b in batches:
        keep = []
        for na, nb, pa_, pb in zip(*(b.column(c).to_pylist() for c in ("na", "nb", "pa", "pb"))):
            same = min(overlap_bound(pa_, pb), na, nb)
            keep.append(100 * same >= 75 * (na + nb - same))
        yield b.filter(pa.array(keep, pa.bool_())).select(["a", "b", "ha"])


def _tile_pairs(key, t):
    """Pairs of one tile with another (or itself) that differ in label and whose profiles leave room for the similarity."""
    lo, hi = key[1].as_py(), key[2].as_py()
    keys, tile, n = t.column("key").to_pylist(), t.column("tile").to_numpy(), t.column("n").to_numpy()
    label = np.unique(np.array([x.hex() for x in t.column("label").to_pylist()]), return_inverse=True)[1]
    raw = t.column("profile").to_pylist()
    width = np.array([len(x) for x in raw])
    found: set = set()
    for w in np.unique(width).tolist():
        rows = {v: np.flatnonzero(width == v) for v in (w, 2 * w)}
        flat = {v: np.frombuffer(b"".join(raw[i] for i in r), np.uint8).reshape(-1, v) for v, r in rows.items() if len(r)}
        x = flat[w]
        for v, y in flat.items():
            if v != w:  # fold neighbouring classes of the longer profiles; full counts stay full
                y = np.minimum(255, y[:, ::2].astype(np.uint16) + y[:, 1::2]).astype(np.uint8)
            i_all, j_all = rows[w], rows[v]
            for s in range(0, len(i_all), 32):
                i = i_all[s: s + 32]
                na, nb = n[i][:, None], n[j_all][None, :]
                ok = (label[i][:, None] != label[j_all][None, :]) & (4 * na >= 3 * nb) & (4 * nb >= 3 * na)
                if lo != hi:
                    ok &= tile[i][:, None] != tile[j_all][None, :]
                if not ok.any():
                    continue
                least = np.minimum(x[s: s + 32, None, :], y[None, :, :])
                same = np.minimum(least.sum(axis=2, dtype=np.int32) + (1 << 20) * (least == 255).any(axis=2), np.minimum(na, nb))
                for p, q in np.argwhere(ok & (100 * same >= 75 * (na + nb - same))).tolist():
                    a, b = keys[i[p]], keys[j_all[q]]
                    if a != b:
                        found.add((min(a, b), max(a, b)))
    pairs = sorted(found)
    return pa.table({"a": pa.array([a for a, _ in pairs], pa.binary()), "b": pa.array([b for _, b in pairs], pa.binary())})


def _set_rows(words: int):
    def run(batches):
        shingler = Shingler(words)
        for b in batches:
            for at in range(0, b.num_rows, 64):
                sets = [s for s in map(shingler, b.column(1).slice(at, 64).to_pylist()) if len(s)]
                yield pa.RecordBatch.from_arrays(
                    [pa.array([set_key(s) for s in sets], pa.binary()), pa.array([s.view(np.int64) for s in sets], pa.list_(pa.int64()))], ["key", "tokens"])

    return run


def components(edges: DataFrame) -> DataFrame:
    """(node, root) for every node of (a, b): root is the least node of its component. Large-star and small-star rounds."""

    def mark(e):
        return tuple(e.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())

    # Always a > b: b is the smaller node.
    e = stash(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a != b").distinct(), "edges")
    now = mark(e)
    while now[0]:
        both = e.select(F.col("a").alias("u"), F.col("b").alias("v")).union(e.select("b", "a"))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("a"), F.col("m").alias("b")).where("a != b").distinct()
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a").select(F.explode(F.array(F.struct("a", F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b")))).alias("x")).select("x.*")
        e = stash(small.where("a != b").distinct(), "edges")
        was, now = now, mark(e)
        if was == now:
            break
    # Every node now points at its root.
    return e.select(F.col("a").alias("node"), F.col("b").alias("root")).union(e.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())


class ShingleJoin:
    """State of one join over (_id, _text): nodes, candidates, links."""

    def __init__(self, df: DataFrame, text: str, ident: str, words: int = WORDS):
        self.spark = df.sparkSession
        bounded_batches(self.spark)
        self.words = words
        self.kind = df.schema[ident].dataType
        self.docs = df.select(F.col(ident).alias("_id"), F.col(text).alias("_text"))
        self.bits = max(6, min(18, int(self.spark.conf.get("spark.sql.shuffle.partitions")).bit_length() + 1))
        shared, frequent, self.level = frequent_tokens(self.docs, self.bits, words)
        shared, frequent = (self.spark.sparkContext.broadcast(m) for m in (shared, frequent))
        arrow = pa.string() if self.kind.simpleString() == "string" else pa.int32() if self.kind.simpleString() == "int" else pa.int64()
        self.index = stash(self.docs.mapInArrow(tidy(_index_rows(shared, frequent, self.bits, arrow, words)), f"_id {self.kind.simpleString()}, {INDEX}"), "index")
        self.rows = self.index.where("block is null").select("_id", "key", "handle", "n")

    def candidates(self) -> DataFrame:
        """Distinct (a, b) handles, a < b, from the buckets."""
        stars = self.index.where("block = -1").select("handles").mapInArrow(_star_rows, "a long, b long")
        pieces = self.index.where("block >= 0").select("block", "sigs", "singles", "handles")
        pairs = pieces.groupBy("block").applyInArrow(_bucket_pairs, "a long, b long")
        return stash(pairs.union(stars).where("a != b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "candidates")

    def plausible(self, pairs: DataFrame) -> DataFrame:
        """(a, b, ha): keys of the pairs of handles that their profiles do not rule out; a has the lesser handle, ha."""
        profiles = self.index.where("profile is not null").select("handle", "key", "n", "profile")
        wanted = pairs.select(F.explode(F.array("a", "b")).alias("handle")).distinct()
        profiles = stash(profiles.join(wanted, "handle", "left_semi").dropDuplicates(["key"]), "profiles")
        side = lambda x: profiles.select(F.col("handle").alias(f"h{x}"), F.col("key").alias(x), F.col("n").alias(f"n{x}"), F.col("profile").alias(f"p{x}"))
        both = pairs.withColumnsRenamed({"a": "ha", "b": "hb"}).join(side("b"), "hb").join(side("a"), "ha").where("4 * na >= 3 * nb and 4 * nb >= 3 * na and a != b")
        left = both.select("a", "b", "ha", "na", "nb", "pa", "pb").mapInArrow(tidy(_bound_filter), "a binary, b binary, ha long")
        return stash(left.distinct(), "plausible")

    def verify(self, pairs: DataFrame) -> DataFrame:
        """Of pairs of keys those that link, on whole sets."""
        wanted = pairs.select(F.explode(F.array("a", "b")).alias("key")).distinct()
        ids = self.rows.where("_id is not null").select("_id", "key").join(wanted, "key", "left_semi").groupBy("key").agg(F.min("_id").alias("_id"))
        ids = maybe_broadcast(stash(ids.select("_id").distinct(), "wanted"), 32)
        sets = self.docs.join(ids, "_id", "left_semi").select("_id", "_text").mapInArrow(tidy(_set_rows(self.words)), "key binary, tokens array<long>")
        sets = stash(sets.join(wanted, "key", "left_semi"), "sets")
        a, b = (sets.select(F.col("key").alias(x), F.col("tokens").alias(f"t{x}")) for x in "ab")
        both = pairs.join(b, "b").join(a, "a").withColumn("same", F.size(F.array_intersect("ta", "tb")))
        return both.where("100 * same >= 75 * (size(ta) + size(tb) - same)").select("a", "b").distinct()

    def _apart(self, pairs: DataFrame, links: DataFrame) -> DataFrame:
        """Pairs whose members the links so far do not join."""
        roots = stash(components(links), "roots")
        a, b = (roots.select(F.col("node").alias(x), F.col("root").alias(f"r{x}")) for x in "ab")
        return pairs.join(a, "a", "left").join(b, "b", "left").where("ra is null or rb is null or ra != rb").select("a", "b")

    def links(self) -> DataFrame:
        """(a, b) keys: links enough to give every class; a link between members of one class may be left out."""
        tried = self.candidates()
        pairs = self.plausible(tried)
        # First each node with its most central neighbour: most classes are whole after that.
        near = pairs.groupBy("b").agg(F.min_by("a", F.struct("ha", "a")).alias("a")).select("a", "b")
        links = stash(self.verify(near), "links")
        rest = stash(self._apart(pairs, links).join(near, ["a", "b"], "left_anti"), "rest")
        links = stash(links.union(self.verify(rest)), "links")
        # Buckets of token pairs were tried as stars; members of different classes meet now.
        members = self.index.where("pairs is not null").select("handle", "key", F.explode("pairs").alias("sig"))
        if not members.limit(1).count():
            return links
        roots = stash(components(links), "roots")
        named = members.join(roots, members["key"] == roots["node"], "left").select("handle", "sig", F.coalesce("root", "key").alias("label")).distinct()
        open_ = named.groupBy("sig").agg(F.min("label").alias("lo"), F.max("label").alias("hi")).where("lo != hi").select("sig")
        left = stash(named.join(open_, "sig", "left_semi"), "open")
        survivors = self._across(left).join(pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")), ["a", "b"], "left_anti")
        return stash(links.union(self.verify(stash(survivors, "across"))), "links")

    def _across(self, left: DataFrame) -> DataFrame:
        """(a, b) keys of plausible pairs of different labels within the clusters that open buckets form.

        A cluster is cut into tiles of about TILE members; a task compares the profiles of two tiles and gives out only
        the pairs that these leave open.
        """
        centre = left.groupBy("sig").agg(F.min("handle").alias("centre"))
        edges = left.select("sig", "handle").join(centre, "sig").where("handle != centre").select(F.col("centre").alias("a"), F.col("handle").alias("b")).distinct()
        clusters = components(edges).withColumnsRenamed({"node": "handle", "root": "cluster"})
        profiles = self.index.where("profile is not null").select("handle", "key", "n", "profile")
        members = stash(left.select("handle", "label").distinct().join(clusters, "handle").join(profiles, "handle").dropDuplicates(["key"]), "members")
        tiles = members.groupBy("cluster").agg(F.ceil(F.count("*") / TILE).cast("int").alias("tiles"))
        placed = members.join(tiles, "cluster").withColumn("tile", F.pmod(F.xxhash64("key"), F.col("tiles")).cast("int"))
        placed = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)))
        placed = placed.select("cluster", F.least("tile", "other").alias("lo"), F.greatest("tile", "other").alias("hi"), "tile", "key", "label", "n", "profile")
        return placed.groupBy("cluster", "lo", "hi").applyInArrow(_tile_pairs, "a binary, b binary").distinct()


def near_duplicate_classes(df: DataFrame, text: str = "text", ident: str = "doc_id", carry: bool = False, words: int = WORDS) -> DataFrame:
    """(ident, n_shingles, component_id) of every row: the least id reachable by links. With `carry`, `_row` beside them."""
    join = ShingleJoin(df, text, ident, words)
    roots = components(join.links())
    named = join.rows.where("key is not null and _id is not null").groupBy("key").agg(F.min("_id").alias("_least"), F.count("*").alias("_size"))
    named = named.join(roots, named["key"] == roots["node"], "left").select("key", "_least", "_size", F.coalesce("root", "key").alias("root"), F.col("root").isNotNull().alias("linked"))
    classes = named.groupBy("root").agg(F.min("_least").alias("_class"))
    # Only sets of several documents, and linked ones, have a class beyond themselves.
    table = stash(named.where("linked or _size > 1").join(classes, "root").select("key", "_class"), "classes")
    rows = join.rows.drop("handle").join(maybe_broadcast(table, 64), "key", "left")
    rows = rows.select("_id", "key", "n", F.when(F.col("_id").isNotNull(), F.coalesce("_class", "_id")).alias("_class"))
    if not carry:
        return rows.select(F.col("_id").alias(ident), F.col("n").alias("n_shingles"), F.col("_class").alias("component_id"))
    goes = maybe_broadcast(stash(rows.where("_class != _id").select("_id", "_class").distinct(), "goes"), 48)
    packed = df.select(F.struct("*").alias("_row"), F.col(ident).alias("_id"))
    named = lambda found: found.select("_row", F.coalesce("_class", "_id").alias("component_id"))
    # An id that repeats with other texts may have rows of several classes; only there the class goes by the row's set.
    several = rows.join(goes.select("_id").distinct(), "_id", "left_semi").groupBy("_id").agg(F.min("_class").alias("lo"), F.max("_class").alias("hi")).where("lo != hi")
    several = stash(several.select("_id"), "several")
    if not several.limit(1).count():
        return named(packed.join(goes, "_id", "left"))
    several = maybe_broadcast(several, 16)

    @F.pandas_udf("binary")
    def key_of(texts: pd.Series) -> pd.Series:
        sets = map(Shingler(words), (t if isinstance(t, str) else None for t in texts))
        return pd.Series([set_key(s) if len(s) else None for s in sets], dtype=object)

    classes = stash(rows.join(several, "_id", "left_semi").where("key is not null").select("_id", "key", "_class").distinct(), "classes")
    own = packed.join(several, "_id", "left_semi").withColumn("key", key_of(F.col("_row")[text])).join(classes, ["_id", "key"], "left")
    return named(packed.join(several, "_id", "left_anti").join(goes, "_id", "left")).union(named(own))


def one_of_each_class(df: DataFrame, text: str = "text", ident: str = "doc_id") -> DataFrame:
    """The rows of `df` whose id is the least of their class, with all their columns; rows of null id stay."""
    return near_duplicate_classes(df, text, ident, carry=True).where(F.col("_row")[ident].eqNullSafe(F.col("component_id"))).select("_row.*")
