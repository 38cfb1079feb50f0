"""The lower level: groups in Z order, as linked blocks; and the upper one: a chained hash directory of the keys."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import universal_hash
from ..operators.joins import positions

PRIME, A, B = 2_147_483_629, 48_271, 11


def build_blocks(keyed: DataFrame, rows_per_block: int = 256, distributed: bool = True) -> DataFrame:
    """(z, g, ..., pos, block, prev_block, next_block) in order of (z, g)."""
    if distributed:
        placed = positions(keyed, ["z", "g"])
    else:
        placed = keyed.withColumn("pos", (F.row_number().over(Window.orderBy("z", "g")) - 1).cast("long"))
    block = F.floor(F.col("pos") / rows_per_block)
    last = F.broadcast(keyed.agg(F.floor((F.count("*") - 1) / rows_per_block).alias("last_block")))
    placed = placed.withColumn("block", block).join(last)
    return placed.select(*keyed.columns, "pos", "block", F.when(F.col("block") > 0, F.col("block") - 1).alias("prev_block"), F.when(F.col("block") < F.col("last_block"), F.col("block") + 1).alias("next_block"))


def build_directory(blocks: DataFrame, buckets: int, a: int = A, b: int = B, p: int = PRIME) -> DataFrame:
    """(bucket, key, pos, n, chain_no, next_key): every distinct key with its first place, chained within its bucket."""
    keys = blocks.groupBy(F.col("z").alias("key")).agg(F.min("pos").alias("pos"), F.count("*").alias("n"))
    keys = keys.withColumn("bucket", universal_hash(F.col("key"), a, b, p, buckets))
    chain = Window.partitionBy("bucket").orderBy("key")
    return keys.select("bucket", "key", "pos", "n", F.row_number().over(chain).alias("chain_no"), F.lead("key").over(chain).alias("next_key"))


def directory_stats(directory: DataFrame, buckets: int) -> DataFrame:
    """(keys, used_buckets, load, mean_chain, longest_chain, longest_run)."""
    per = directory.groupBy("bucket").agg(F.count("*").alias("chain"), F.max("n").alias("run"))
    return per.agg(
        F.sum("chain").alias("keys"),
        F.count("*").alias("used_buckets"),
        F.round(F.sum("chain") / buckets, 6).alias("load"),
        F.round(F.avg("chain"), 6).alias("mean_chain"),
        F.max("chain").alias("longest_chain"),
        F.max("run").alias("longest_run"),
    )


def upsert(keyed: DataFrame, changed: DataFrame) -> DataFrame:
    """keyed rows with those of changed groups replaced or added; blocks are laid out anew from it where keys moved."""
    return keyed.join(changed.select("g"), "g", "left_anti").unionByName(changed)
