"""Latent vectors: items from the given embeddings, users from what they bought, groups as hyperedges over members."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.linalg import vec_mean, vec_sum
from ..sources.tables import Tables

DIM = 8


def item_vectors(tables: Tables, d: int = DIM) -> DataFrame:
    """(v, vec): the first d components of the embedding that the item's key points to."""
    vectors = tables.embeddings.select("vec_id", F.transform(F.slice("embedding", 1, d), lambda x: x.cast("double")).alias("vec"))
    n = tables.embeddings.agg(F.count("*").alias("n_vec"))
    keyed = tables.part.select(F.col("p_partkey").alias("v")).join(F.broadcast(n)).withColumn("vec_id", F.pmod(F.col("v"), F.col("n_vec")))
    return keyed.join(vectors, "vec_id").select("v", "vec")


def user_vectors(lines: DataFrame, items: DataFrame, d: int = DIM) -> DataFrame:
    """(u, vec): the mean of the vectors of what a user bought, line by line."""
    return lines.select("u", "v").join(items, "v").groupBy("u").agg(vec_mean(F.col("vec"), d).alias("vec"))


def hyperedge_aggregate(members: DataFrame, users: DataFrame, mode: str = "mean", d: int = DIM) -> DataFrame:
    """(g, vec): a group as a hyperedge over its members' preferences.

    mean: the plain mean. degree_norm: each member weighs 1 / sqrt(its number of groups), and the sum is divided by the
    square root of the group's size.
    """
    rows = members.select("g", "u").join(users, "u")
    if mode == "mean":
        return rows.groupBy("g").agg(vec_mean(F.col("vec"), d).alias("vec"))
    if mode == "degree_norm":
        degree = members.groupBy("u").agg(F.count("*").alias("k"))
        weighed = rows.join(degree, "u").select("g", F.transform("vec", lambda x: x / F.sqrt(F.col("k").cast("double"))).alias("vec"))
        summed = weighed.groupBy("g").agg(vec_sum(F.col("vec"), d).alias("vec"), F.count("*").alias("size"))
        return summed.select("g", F.transform("vec", lambda x: x / F.sqrt(F.col("size").cast("double"))).alias("vec"))
    raise ValueError("mode is mean or degree_norm")
