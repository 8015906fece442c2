"""Exact duplicates by counting quotient filters.

Every partition packs the 64-bit fingerprints of its texts into counting quotient filters, one per fingerprint
block; the filters of a block merge without loss because both sides list (quotient, remainder) in sorted order.
Only texts whose fingerprint was counted twice or more go on to a comparison of their bytes.

Defined results: a null text counts as empty, so nulls and empty texts form one group. Rows that repeat a doc_id
count separately in `group_size` and share the verdict. Where every doc_id of a group is null, `keep_id` is null and
all its rows are kept; a null doc_id beside others is never the one that stays. An empty table gives an empty result.
"""

from __future__ import annotations

import struct

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import fold_case, maybe_broadcast, packed, stash

#: Fingerprints that one partition gathers before it writes out its filters.
FLUSH = 2_000_000


class CountingQuotientFilter:
    """Sorted fingerprints with counts, stored as quotient bitmaps, remainder slots and counter slots.

    A fingerprint of `bits` bits splits into a quotient (upper part) and a remainder. Bitmap `used` marks quotients that
    have a run, `ends` marks the last slot of each run, `counter` marks slots that hold a count (minus one) instead of a
    remainder. A remainder with count one takes a single slot.
    """

    def __init__(self, keys: np.ndarray, counts: np.ndarray, bits: int):
        self.keys, self.counts, self.bits = keys, counts, bits

    @classmethod
    def build(cls, fingerprints: np.ndarray, bits: int) -> CountingQuotientFilter:
        keys, counts = np.unique(fingerprints, return_counts=True)
        return cls(keys, counts.astype(np.uint64), bits)

    def merge(self, *others: CountingQuotientFilter) -> CountingQuotientFilter:
        """Merge by order of (quotient, remainder); counts of equal entries add up, nothing is lost."""
        keys = np.concatenate([self.keys, *(o.keys for o in others)])
        counts = np.concatenate([self.counts, *(o.counts for o in others)])
        order = np.argsort(keys, kind="stable")
        keys, counts = keys[order], counts[order]
        first = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]]) if len(keys) else np.zeros(0, np.int64)
        return CountingQuotientFilter(keys[first], np.add.reduceat(counts, first) if len(first) else counts, self.bits)

    def to_bytes(self) -> bytes:
        n = len(self.keys)
        q = max(0, min(self.bits - 8, int(np.ceil(np.log2(max(1, n / 0.95))))))
        r = self.bits - q
        quotient = (self.keys >> np.uint64(r)).astype(np.int64) if r < 64 else np.zeros(n, np.int64)
        remainder = self.keys & np.uint64((1 << r) - 1)
        many = self.counts > 1
        width = 1 + many.astype(np.int64)
        start = np.cumsum(width) - width
        slots = np.zeros(int(width.sum()), np.uint64)
        slots[start] = remainder
        slots[start[many] + 1] = self.counts[many] - np.uint64(1)
        counter = np.zeros(len(slots), bool)
        counter[start[many] + 1] = True
        last = np.r_[quotient[1:] != quotient[:-1], True] if n else np.zeros(0, bool)
        ends = np.zeros(len(slots), bool)
        ends[(start + width - 1)[last]] = True
        used = np.zeros(1 << q, bool)
        used[quotient] = True
        size = max(1, (max(r, int(slots.max()).bit_length() if len(slots) else 1) + 7) // 8)
        body = slots.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :size].tobytes()
        maps = b"".join(np.packbits(m).tobytes() for m in (used, ends, counter))
        return struct.pack("<BBBI", self.bits, q, size, len(slots)) + maps + body

    @classmethod
    def from_bytes(cls, data: bytes) -> CountingQuotientFilter:
        bits, q, size, n = struct.unpack_from("<BBBI", data)
        at, maps = 7, []
        for length in (1 << q, n, n):
            width = (length + 7) // 8
            maps.append(np.unpackbits(np.frombuffer(data, np.uint8, width, at), count=length).astype(bool))
            at += width
        used, ends, counter = maps
        slots = np.zeros((n, 8), np.uint8)
        slots[:, :size] = np.frombuffer(data, np.uint8, n * size, at).reshape(n, size)
        slots = slots.reshape(-1).view("<u8")
        run = np.cumsum(ends) - ends
        quotient = np.flatnonzero(used).astype(np.uint64)[run]
        r = bits - q
        keys = slots | (quotient << np.uint64(r) if r < 64 else np.uint64(0))
        at_count = np.flatnonzero(counter)
        counts = np.ones(n, np.uint64)
        counts[at_count - 1] += slots[at_count]
        return cls(keys[~counter], counts[~counter], bits)


def _filters(blocks: int, bits: int):
    """Fingerprints of a partition to (block, filter) rows; a block is a range of the upper fingerprint bits."""

    def flush(parts):
        fp = np.sort(np.concatenate(parts))
        block = (fp >> np.uint64(bits)).astype(np.int64)
        cut = np.flatnonzero(np.r_[True, block[1:] != block[:-1]])
        pieces = np.split(fp & np.uint64((1 << bits) - 1), cut[1:])
        rows = [CountingQuotientFilter.build(p, bits).to_bytes() for p in pieces]
        return pa.RecordBatch.from_arrays([pa.array(block[cut].astype(np.int32)), pa.array(rows, pa.binary())], ["block", "cqf"])

    def run(batches):
        parts, n = [], 0
        for b in batches:
            parts.append(b.column(0).to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64))
            n += len(parts[-1])
            if n >= FLUSH:
                yield flush(parts)
                parts, n = [], 0
        if n:
            yield flush(parts)

    return run


def _merge_block(bits: int):
    def run(key, t):
        first, *rest = [CountingQuotientFilter.from_bytes(x) for x in t.column("cqf").to_pylist()]
        whole = first.merge(*rest)
        again = whole.counts > 1
        fp = whole.keys[again] | (np.uint64(key[0].as_py()) << np.uint64(bits))
        return pa.table({"fp": fp.view(np.int64), "n": whole.counts[again].astype(np.int64)})

    return run


def repeated_fingerprints(fingerprints: DataFrame, block_bits: int | None = None) -> DataFrame:
    """(fp, n) for every 64-bit value of the one column that occurs at least twice.

    `block_bits` sets the number of merge tasks' groups (2 ** block_bits); each holds an equal share of the distinct
    fingerprints however often one of them occurs, since repeats collapse to counters in their own partition first.
    """
    spark = fingerprints.sparkSession
    if block_bits is None:
        block_bits = max(4, min(20, int(spark.conf.get("spark.sql.shuffle.partitions")).bit_length() + 1))
    bits = 64 - block_bits
    packs = fingerprints.mapInArrow(_filters(1 << block_bits, bits), "block int, cqf binary")
    return packs.groupBy("block").applyInArrow(_merge_block(bits), "fp long, n long")


def exact_dedup(df: DataFrame, text: str = "text", ident: str = "doc_id", carry: bool = False, block_bits: int | None = None) -> DataFrame:
    """One row per input row: (ident, keep_id, group_size, kept, text_sha256); with `carry`, the whole input row as `_row` instead of ident."""
    norm = fold_case(F.col("_text"))
    rows = packed(df, text, ident).withColumns({"_norm": norm, "_fp": F.xxhash64(norm)})
    again = stash(repeated_fingerprints(rows.select("_fp"), block_bits), "repeated").withColumnRenamed("fp", "_fp").select("_fp")
    again = maybe_broadcast(again, 16)
    suspects = rows.select("_id", "_norm", "_fp").join(again, "_fp", "left_semi")
    # Grouping on the text itself compares bytes, and sums within each partition before anything moves.
    equal = suspects.groupBy("_fp", F.sha2("_norm", 256).alias("_sha"), "_norm").agg(F.max("_id").alias("_keep"), F.count("*").alias("_size"))
    equal = equal.withColumn("_len", F.octet_length("_norm"))
    classes = stash(
        equal.groupBy("_fp", "_sha").agg(F.max("_keep").alias("_keep"), F.max("_size").alias("_size"), F.count("*").alias("_texts")).where("_size > 1 or _texts > 1"),
        "classes",
    )
    rows = rows.withColumn("_sha", F.sha2("_norm", 256))
    keys = ["_fp", "_sha"]
    if classes.where("_texts > 1").limit(1).count():  # two texts with one fingerprint and one digest: join on the bytes
        classes, keys = equal.select("_fp", "_sha", "_norm", "_keep", "_size"), ["_fp", "_sha", "_norm"]
    else:
        classes = maybe_broadcast(classes.drop("_texts"), 120)
    first = F.col("_row") if carry else F.col("_id").alias(ident)
    slim = rows.drop("_text") if len(keys) == 3 else rows.drop("_text", "_norm")
    slim = slim if carry else slim.drop("_row")
    keep = F.when(F.col("_size").isNull(), F.col("_id")).otherwise(F.col("_keep"))
    return slim.join(classes, keys, "left").select(
        first,
        keep.alias("keep_id"),
        F.coalesce("_size", F.lit(1)).cast("long").alias("group_size"),
        F.when(keep.isNull(), True).otherwise(F.coalesce(F.col("_id") == keep, F.lit(False))).alias("kept"),
        F.col("_sha").alias("text_sha256"),
    )


def keep_one(df: DataFrame, text: str = "text", ident: str = "doc_id") -> DataFrame:
    """The rows of `df` that stay, with all their columns."""
    return exact_dedup(df, text, ident, carry=True).where("kept").select("_row.*")
