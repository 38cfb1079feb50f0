"""Interest over time: training quadruples per slice, long- and short-term profiles, and their sequence."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..encoder.relevance import history_vectors
from ..functions.linalg import vec_mean, zeros


def quadruples(sliced: DataFrame, edges: DataFrame, slices: int) -> DataFrame:
    """(slice, interactions, items, groups, edges): the sizes of each slice's cumulative training data."""
    rows = sliced.where("slice is not null").select("g", "v", "slice")
    upto = rows.select("g", "v", F.explode(F.sequence(F.col("slice"), F.lit(slices - 1))).alias("slice"))
    sizes = upto.groupBy("slice").agg(F.count("*").alias("interactions"), F.countDistinct("v").alias("items"), F.countDistinct("g").alias("groups"))
    active = upto.select("slice", "g").distinct()
    ends = edges.join(active.withColumnRenamed("g", "src"), "src").join(active.select(F.col("slice").alias("s2"), F.col("g").alias("dst")), "dst").where("slice = s2")
    return sizes.join(ends.groupBy("slice").agg(F.count("*").alias("edges")), "slice", "left").select("slice", "interactions", "items", "groups", F.coalesce("edges", F.lit(0)).cast("long").alias("edges"))


def long_term(sliced: DataFrame, items: DataFrame, slices: int, d: int) -> DataFrame:
    """(g, slice, long): the history vector of all interactions up to each slice.

    The closed-form profile: what the encoder adds to a group from its items. The trained encoders of each cumulative
    slice put theirs in the same columns.
    """
    rows = sliced.where("slice is not null").select("g", "v", F.explode(F.sequence(F.col("slice"), F.lit(slices - 1))).alias("slice"))
    keyed = rows.select(F.struct("g", "slice").alias("g"), "v")
    return history_vectors(keyed, items, d).select(F.col("g.g").alias("g"), F.col("g.slice").alias("slice"), F.col("hist").alias("long"))


def short_term(sliced: DataFrame, items: DataFrame, d: int) -> DataFrame:
    """(g, slice, short): the mean vector of the new interactions of each slice."""
    rows = sliced.where("slice is not null").select("g", "slice", "v").join(items, "v")
    return rows.groupBy("g", "slice").agg(vec_mean(F.col("vec"), d).alias("short"))


def profiles(long: DataFrame, short: DataFrame, d: int) -> DataFrame:
    """(g, slice, profile): long-term and short-term side by side; nothing new counts as zeros."""
    return long.join(short, ["g", "slice"], "left").select("g", "slice", F.concat("long", F.coalesce("short", zeros(d))).alias("profile"))


def sequences(rows: DataFrame) -> DataFrame:
    """(g, seq): each group's profiles in order of time."""
    return rows.groupBy("g").agg(F.sort_array(F.collect_list(F.struct("slice", "profile"))).alias("seq"))
