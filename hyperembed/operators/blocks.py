"""Tables of vectors (id, vec): products with incidence tables and with small matrices. The only numpy on executors besides sketches."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

VEC = "id long, vec array<double>"


def rows_of(batch, column: str = "vec") -> np.ndarray:
    c = batch.column(column)
    flat = c.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(c), -1) if len(c) else np.zeros((0, 0))


def vec_batch(ids, x: np.ndarray) -> pa.RecordBatch:
    n, w = x.shape
    offsets = pa.array(np.arange(n + 1, dtype=np.int32) * w)
    return pa.RecordBatch.from_arrays([ids, pa.ListArray.from_arrays(offsets, pa.array(np.ascontiguousarray(x, np.float64).ravel()))], ["id", "vec"])


def half_step(ell: DataFrame, vecs: DataFrame, width: int, source: str, target: str, merge: bool = False) -> DataFrame:
    """Per `target` id the sum of ell * vec over its `source` ids: `width` codegen sums, partial before the exchange.

    With `merge` neither side is broadcast: files of rates and of vectors that are mostly zero are far smaller than their rows, and
    Spark would hold these on the driver.
    """
    rows = ell.select(F.col(source).alias("id"), F.col(target).alias("out"), "ell").join(vecs.hint("merge") if merge else vecs, "id")
    sums = rows.groupBy("out").agg(*[F.sum(F.col("ell") * F.col("vec")[i]).alias(f"s{i}") for i in range(width)])
    return sums.select(F.col("out").alias("id"), F.array(*[F.col(f"s{i}") for i in range(width)]).alias("vec"))


#: Wider Gram matrices add up in numpy, in two steps of this fan-in; narrower ones in codegen sums.
WIDE, FAN = 128, 64


def _add_rows(key, table):
    x = table.column("vec").combine_chunks()
    total = x.flatten().to_numpy(zero_copy_only=False).reshape(len(x), -1).sum(axis=0)
    return pa.table({"id": pa.array([key[0].as_py()], pa.int64()), "vec": pa.array([total.tolist()], pa.list_(pa.float64()))})


def gram_rows(vecs: DataFrame, width: int) -> DataFrame:
    """Sum of vec vec^T as `width` rows (id, vec). Partitions form their own; rows of these add up on executors."""

    def run(batches):
        g = np.zeros((width, width))
        for b in batches:
            x = rows_of(b)
            if len(x):
                g += x.T @ x
        yield vec_batch(pa.array(np.arange(width, dtype=np.int64)), g)

    parts = vecs.select("id", "vec").mapInArrow(run, VEC)
    if width <= WIDE:
        sums = parts.groupBy("id").agg(*[F.sum(F.col("vec")[i]).alias(f"s{i}") for i in range(width)])
        return sums.select("id", F.array(*[f"s{i}" for i in range(width)]).alias("vec"))
    # No task holds more than a FAN-th of the partitions' rows, nor more than FAN sums.
    some = parts.withColumn("turn", F.pmod(F.spark_partition_id(), F.lit(FAN))).groupBy("id", "turn").applyInArrow(_add_rows, VEC)
    return some.groupBy("id").applyInArrow(_add_rows, VEC)


def gram(vecs: DataFrame, width: int) -> np.ndarray:
    """Sum of vec vec^T; the driver gets `width` rows, however many partitions there are."""
    out = np.zeros((width, width))
    for r in gram_rows(vecs, width).collect():
        out[r[0]] = r[1]
    return (out + out.T) / 2


def times(vecs: DataFrame, matrix: np.ndarray) -> DataFrame:
    """vec times a small matrix, in the same partitions."""

    def run(batches):
        for b in batches:
            x = rows_of(b)
            yield vec_batch(b.column("id"), x @ matrix if len(x) else np.zeros((0, matrix.shape[1])))

    return vecs.select("id", "vec").mapInArrow(run, VEC)
