"""Accuracy and cost measures."""

from __future__ import annotations

import statistics
import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def hit_ratio(recs: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """(k, hits, truths, hr): the share of true pairs (v, g) that are among the first k recommendations (v, rank, g)."""
    pairs = truth.select("v", "g").distinct()
    hit = recs.where(F.col("rank") <= k).select("v", "g").distinct().withColumn("hit", F.lit(1))
    return pairs.join(hit, ["v", "g"], "left").agg(F.lit(k).alias("k"), F.coalesce(F.sum("hit"), F.lit(0)).alias("hits"), F.count("*").alias("truths"), F.round(F.coalesce(F.sum("hit"), F.lit(0)) / F.count("*"), 6).alias("hr"))


def ndcg(recs: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """(k, queries, ndcg): discounted gain over the best possible for each item with true groups, averaged."""
    pairs = truth.select("v", "g").distinct()
    gain = recs.where(F.col("rank") <= k).join(pairs, ["v", "g"]).groupBy("v").agg(F.sum(1 / F.log2(F.col("rank") + 1.0)).alias("dcg"))
    size = pairs.groupBy("v").agg(F.least(F.count("*"), F.lit(k)).alias("m"))
    ideal = F.aggregate(F.sequence(F.lit(1).cast("long"), F.col("m")), F.lit(0.0), lambda s, i: s + 1 / F.log2(i + 1.0))
    return size.join(gain, "v", "left").agg(F.lit(k).alias("k"), F.count("*").alias("queries"), F.round(F.avg(F.coalesce("dcg", F.lit(0.0)) / ideal), 6).alias("ndcg"))


def sigma_inf(spreads: DataFrame) -> DataFrame:
    """(sets, sigma_inf): the mean share of groups that recommended lists activate."""
    return spreads.agg(F.count("*").alias("sets"), F.round(F.avg("influence"), 6).alias("sigma_inf"))


def recall_at_k(found: DataFrame, exact: DataFrame, k: int) -> DataFrame:
    """(k, found, wanted, recall): how much of the exact first k another search finds."""
    want = exact.where(F.col("rank") <= k).select("v", "g")
    got = found.where(F.col("rank") <= k).select("v", "g").withColumn("hit", F.lit(1))
    return want.join(got, ["v", "g"], "left").agg(F.lit(k).alias("k"), F.coalesce(F.sum("hit"), F.lit(0)).alias("found"), F.count("*").alias("wanted"), F.round(F.coalesce(F.sum("hit"), F.lit(0)) / F.count("*"), 6).alias("recall"))


def relative_change(variant: float, full: float) -> float:
    """In percent."""
    return 100 * (variant - full) / full


def timed(action: Callable[[], object], repeats: int = 5, warm: int = 1) -> float:
    """The median of wall times in seconds, after warm-up."""
    for _ in range(warm):
        action()
    taken = []
    for _ in range(repeats):
        began = time.perf_counter()
        action()
        taken.append(time.perf_counter() - began)
    return statistics.median(taken)
