"""Sharding by jump consistent hashing: a stable key and the shard count decide, without a ring table.

Cases: a null key counts as key 0; a null text has size 8 and CRC 0; repeated rows get slots of their own; an empty
table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

from .common import partitions

#: Slot blocks of each shard: a fixed number, so that the table of their sizes is bounded by shards x blocks.
BLOCKS = 1024


def jump_hash(keys: np.ndarray, shards: int) -> np.ndarray:
    """Shard of each 64-bit key; with one more shard a key stays or goes to the new one."""
    state = keys.astype(np.int64).view(np.uint64).copy()
    at = np.zeros(len(state), np.int64)
    ahead = np.zeros(len(state), np.int64)
    live = np.arange(len(state))
    with np.errstate(over="ignore"):
        while len(live):
            at[live] = ahead[live]
            state[live] = state[live] * np.uint64(2862933555777941757) + np.uint64(1)
            draw = (state[live] >> np.uint64(33)).astype(np.float64) + 1.0
            ahead[live] = np.floor((at[live] + 1) * (float(1 << 31) / draw)).astype(np.int64)
            live = live[ahead[live] < shards]
    return at


def shard_of(key, shards: int):
    """Column: the shard of an integer key column."""

    @pandas_udf("int")
    def udf(keys: pd.Series) -> pd.Series:
        return pd.Series(jump_hash(keys.fillna(0).to_numpy(np.int64), shards).astype(np.int32))

    return udf(F.coalesce(key.cast("bigint"), F.lit(0)))


def shard(docs: DataFrame, shards: int, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard for every row.

    Slots are gapless within a shard without one task per shard: rows are numbered inside (shard, block), and a table of
    at most shards x BLOCKS block sizes gives each block its offset.
    """
    body = F.coalesce(F.col(text), F.lit(""))
    rows = docs.select(
        F.col(key).alias("doc_id"),
        (F.octet_length(body).cast("bigint") + 8).alias("size"),
        F.crc32(body).alias("text_crc32"),
        shard_of(F.col(key), shards).alias("shard"),
        shard_of(F.col(key), shards + 1).alias("grown_shard"),
    ).withColumn("block", F.pmod(F.coalesce("doc_id", F.lit(0)) + F.col("text_crc32") % 4096, F.lit(BLOCKS)).cast("int"))
    dealt = rows.repartition(partitions(docs.sparkSession), "shard", "block")
    sizes = dealt.groupBy("shard", "block").agg(F.count("*").alias("n"))
    before = Window.partitionBy("shard").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sizes.select("shard", "block", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("offset"))
    inside = Window.partitionBy("shard", "block").orderBy("doc_id", "text_crc32", "size")
    numbered = dealt.withColumn("rn", F.row_number().over(inside))
    return numbered.join(F.broadcast(offsets), ["shard", "block"]).select(
        "doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard",
        (F.col("offset") + F.col("rn") - 1).cast("bigint").alias("slot"), "grown_shard",
    )


def write_shards(docs: DataFrame, path: str, shards: int, key: str = "doc_id") -> None:
    """Write the rows themselves, one folder per shard; files of a shard are written by many tasks."""
    n = partitions(docs.sparkSession)
    docs.withColumn("shard", shard_of(F.col(key), shards)).repartition(n, "shard", F.pmod(F.xxhash64(key), F.lit(max(1, n // shards)))).write.partitionBy("shard").parquet(path)


def op4_jump_shards(spark, sf_dir: str) -> DataFrame:
    return shard(spark.read.parquet(f"{sf_dir}/documents.parquet"), 24)
