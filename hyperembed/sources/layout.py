"""Stored layouts of incidence tables: partitioned by hash block, or bucketed so that later joins move no incidence row."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions.vectors import mix
from ..operators.hypergraph import Hypergraph


def write_partitioned(inc: DataFrame, path: str, blocks: int = 64, by: str = "eid") -> None:
    """Parquet in `blocks` folders by hash of `by`; a reader that names a block reads that folder only."""
    rows = inc.withColumn("block", F.pmod(mix(F.col(by), 0, 23), F.lit(blocks)).cast("int"))
    # A second, random key deals a hub's block out over several tasks.
    rows.repartition("block", F.pmod(mix(F.col("eid"), F.col("vid"), 29), F.lit(8))).write.partitionBy("block").mode("overwrite").parquet(path)


def read_block(spark: SparkSession, path: str, block: int | None = None) -> DataFrame:
    """Incidence rows of one block, or of all."""
    df = spark.read.parquet(path)
    return (df if block is None else df.where(F.col("block") == block)).drop("block")


def write_bucketed(h: Hypergraph, name: str, path: str, buckets: int = 64) -> tuple[DataFrame, DataFrame]:
    """Two copies of the incidence, tables <name>_by_eid and <name>_by_vid, in sorted buckets; a table of vectors in as many buckets joins either without an exchange.

    Rows are dealt by bucket first, so that there is one file a bucket.
    """
    spark, out = h.inc.sparkSession, []
    for by in ("eid", "vid"):
        rows = h.inc.repartition(buckets, by)
        rows.write.bucketBy(buckets, by).sortBy(by).mode("overwrite").option("path", f"{path}/by_{by}").saveAsTable(f"{name}_by_{by}")
        out.append(spark.table(f"{name}_by_{by}"))
    return out[0], out[1]
