"""Strata of the relation graph, the edge sets between them, and the sample size of each set."""

from __future__ import annotations

from pyspark.ml.clustering import KMeans
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def cluster_nodes(vectors: DataFrame, k: int = 8, seed: int = 1, mode: str = "k-means||") -> DataFrame:
    """(g, cluster) by k-means; the parallel start is the scalable relative of k-means++."""
    features = vectors.select("g", array_to_vector("vec").alias("features"))
    return KMeans(k=k, seed=seed, initMode=mode, featuresCol="features", predictionCol="cluster").fit(features).transform(features).select("g", F.col("cluster").cast("long").alias("cluster"))


def cluster_by_column(groups: DataFrame, column) -> DataFrame:
    """(g, cluster): repeatable strata from an expression over the group."""
    return groups.select("g", column.cast("long").alias("cluster")).distinct()


def edge_sets(edges: DataFrame, clusters: DataFrame) -> DataFrame:
    """Undirected edges (a, b, ...) with the unordered pair of strata (ci, cj) that they join."""
    ca, cb = (clusters.select(F.col("g").alias(k), F.col("cluster").alias(f"c_{k}")) for k in "ab")
    both = edges.join(ca, "a").join(cb, "b")
    return both.select(*edges.columns, F.least("c_a", "c_b").alias("ci"), F.greatest("c_a", "c_b").alias("cj"))


def allocate(sets: DataFrame, share: float) -> DataFrame:
    """(ci, cj, n_edges, num): the same share of every set, rounded by largest remainder so that the sum is exact.

    One row per set: as many as pairs of strata.
    """
    per = sets.groupBy("ci", "cj").agg(F.count("*").alias("n_edges"))
    want = F.col("n_edges") * F.lit(share)
    per = per.withColumns({"base": F.floor(want), "left": want - F.floor(want)})
    everything = Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    extra = F.round(F.sum("n_edges").over(everything) * F.lit(share)) - F.sum("base").over(everything)
    place = F.row_number().over(Window.orderBy(F.desc("left"), "ci", "cj"))
    per = per.withColumns({"extra": extra, "place": place})
    return per.select("ci", "cj", "n_edges", (F.col("base") + (F.col("place") <= F.col("extra")).cast("long")).alias("num"))
