"""Table functions on Arrow batches, for SQL: members to pairs, hyperedges to random members."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.functions import arrow_udtf
from pyspark.sql.types import StructType

from .vectors import PRIME

#: Rows of an output batch.
BATCH = 1 << 16


@arrow_udtf(returnType=StructType().add("eid", "long").add("a", "long").add("b", "long"))
class HyperedgePairs:
    """Of a table (eid, members): pairs a < b of each row's distinct members. Null members and null arrays give nothing; quadratic in the array's length."""

    def eval(self, rows: pa.RecordBatch) -> Iterator[pa.Table]:
        for eid, members in zip(rows.column(0).to_pylist(), rows.column(1)):
            ids = np.unique(np.array([x for x in members.as_py() or () if x is not None], np.int64))
            step = max(1, BATCH // max(1, len(ids)))
            for at in range(0, len(ids) - 1, step):
                heads = np.arange(at, min(at + step, len(ids) - 1))
                count = len(ids) - 1 - heads
                left = np.repeat(heads, count)
                right = np.arange(len(left)) - np.repeat(np.cumsum(count) - count, count) + left + 1
                yield pa.table({"eid": pa.array([eid] * len(left), pa.int64()), "a": ids[left], "b": ids[right]})


@arrow_udtf(returnType=StructType().add("eid", "long").add("place", "long"))
class RandomMembers:
    """Of a table (eid, size, nodes, seed): `size` distinct places below `nodes` for each row, or all where there are no more; from the hash of (eid, slot, seed). Rows with a null give nothing."""

    def eval(self, rows: pa.RecordBatch) -> Iterator[pa.Table]:
        for e, s, n, k in zip(*(c.to_pylist() for c in rows.columns[:4])):
            if None in (e, s, n, k):
                continue
            want, seen, slot = min(s, n), {}, 0
            while len(seen) < want:
                # After many draws that hit taken places, the next free ones follow in order.
                place = _draw(e, slot, k) % n if slot < 8 * want else slot % n
                seen.setdefault(place)
                slot += 1
            yield pa.table({"eid": pa.array([e] * len(seen), pa.int64()), "place": pa.array(list(seen), pa.int64())})


def _draw(a: int, b: int, seed: int) -> int:
    """`vectors.mix` on integers."""
    a, b = a % PRIME, b % PRIME

    def affine(t, k):
        return (t * 48271 + b * 69621 + k * 16807 + 12345) % PRIME

    t = affine(a, seed)
    return affine((t * t + 12345) % PRIME, seed + 1)


def register(spark: SparkSession) -> None:
    """SQL names: hyperedge_pairs(TABLE(..)), random_members(TABLE(..)); Spark allows no lateral join with such functions."""
    spark.udtf.register("hyperedge_pairs", HyperedgePairs)
    spark.udtf.register("random_members", RandomMembers)
