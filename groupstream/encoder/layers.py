"""The group graph encoder: a dense first layer, propagation over the relation graph, and refreshed item vectors."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.linalg import blend, dense, vec_mean, vec_sum, zeros
from ..sources.storage import settle


def weights(rows: int, columns: int, seed: int = 0) -> list[list[float]]:
    """Small repeatable weights from a rule, for checks: multiples of 1/20 between -1/4 and 1/4."""
    return [[((i * 7 + j * 3 + seed * 5) % 11 - 5) / 20 for j in range(columns)] for i in range(rows)]


def bias(rows: int, seed: int = 0) -> list[float]:
    return [((i * 5 + seed * 3) % 7 - 3) / 20 for i in range(rows)]


def initial_layer(latent: DataFrame, attributes: DataFrame, key: str, matrix: Sequence, b: Sequence, d_attributes: int, act: str = "sigmoid") -> DataFrame:
    """(key, vec): act(W [latent ; attributes] + b). Missing attributes count as zeros."""
    attrs = attributes.select(key, F.col("vec").alias("attrs"))
    both = latent.join(attrs, key, "left").select(key, F.concat("vec", F.coalesce("attrs", zeros(d_attributes))).alias("x"))
    return both.select(key, dense(matrix, F.col("x"), b, act).alias("vec"))


def aggregate_neighbours(edges: DataFrame, vectors: DataFrame, d: int) -> DataFrame:
    """(g, agg): the sum of neighbours' vectors times the edge's weight lap; zeros for isolated groups."""
    sent = edges.select("src", F.col("dst").alias("g"), "lap").join(vectors.select(F.col("g").alias("src"), "vec"), "src")
    got = sent.select("g", F.transform("vec", lambda x: x * F.col("lap")).alias("vec")).groupBy("g").agg(vec_sum(F.col("vec"), d).alias("agg"))
    return vectors.select("g").join(got, "g", "left").select("g", F.coalesce("agg", zeros(d)).alias("agg"))


def propagate(edges: DataFrame, vectors: DataFrame, matrix: Sequence, b: Sequence, d: int, act: str = "sigmoid") -> DataFrame:
    """One layer: act(W [self ; neighbours] + b)."""
    both = vectors.join(aggregate_neighbours(edges, vectors, d), "g")
    return both.select("g", dense(matrix, F.concat("vec", "agg"), b, act).alias("vec"))


def encode_groups(edges: DataFrame, vectors: DataFrame, layers: Sequence[tuple], d: int, act: str = "sigmoid", cut: bool = True) -> DataFrame:
    """The vectors after all layers; with none, the first layer alone. Each layer is written out, which ends its lineage."""
    for matrix, b in layers:
        vectors = propagate(edges, vectors, matrix, b, d, act)
        vectors = settle(vectors, "layer") if cut else vectors
    return vectors


def refresh_items(items: DataFrame, fresh: DataFrame, groups: DataFrame, alpha: float, d: int, empty: str = "keep") -> DataFrame:
    """(v, vec): alpha * own + (1 - alpha) * mean of the groups that just touched the item.

    Without such a group the vector stays (empty='keep') or is scaled by alpha (empty='shrink').
    """
    if not 0 <= alpha <= 1:
        raise ValueError("alpha lies in [0, 1]")
    mean = fresh.select("g", "v").distinct().join(groups, "g").groupBy("v").agg(vec_mean(F.col("vec"), d).alias("new"))
    alone = F.col("vec") if empty == "keep" else F.transform("vec", lambda x: x * alpha)
    return items.join(mean, "v", "left").select("v", F.when(F.col("new").isNull(), alone).otherwise(blend(alpha, F.col("vec"), F.col("new"))).alias("vec"))
