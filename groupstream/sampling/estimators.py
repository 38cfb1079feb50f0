"""Estimators over sampled edges, their variance in closed form, the best inclusion probabilities, and the error bounds of
the topology-only ones.

An edge's score vector is c = lap * (sum over layers of x_a + x_b), with x the projected vectors of its ends.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.linalg import add, norm, vec_sum


def edge_scores(edges: DataFrame, vectors: list[DataFrame], d: int) -> DataFrame:
    """(a, b, ..., c, score): c for the given layers' projected vectors (g, vec), and its length."""
    rows = edges
    for i, layer in enumerate(vectors):
        xa, xb = (layer.select(F.col("g").alias(k), F.col("vec").alias(f"x_{k}{i}")) for k in "ab")
        rows = rows.join(xa, "a").join(xb, "b")
    total = None
    for i in range(len(vectors)):
        pair = add(F.col(f"x_a{i}"), F.col(f"x_b{i}"))
        total = pair if total is None else add(total, pair)
    rows = rows.withColumn("c", F.transform(total, lambda x: x * F.col("lap")))
    return rows.select(*edges.columns, "c", norm(F.col("c"), d).alias("score"))


def node_inclusion(included: DataFrame) -> DataFrame:
    """(g, p_v): the probability that any of a node's edges is drawn, for independent draws with probabilities p."""
    ends = included.select(F.col("a").alias("g"), "p").unionByName(included.select(F.col("b").alias("g"), "p"))
    sure = F.max((F.col("p") >= 1).cast("int")) == 1
    none = F.exp(F.sum(F.when(F.col("p") < 1, F.log1p(-F.col("p"))).otherwise(0.0)))
    return ends.groupBy("g").agg(F.when(sure, 1.0).otherwise(1 - none).alias("p_v"))


def node_estimate(sampled: DataFrame, inclusion: DataFrame, vectors: DataFrame, d: int) -> DataFrame:
    """(g, est): the neighbour sum of each sampled node, its edges weighed by lap * p_v / p."""
    both = sampled.select("a", "b", "lap", "p").unionByName(sampled.select(F.col("b").alias("a"), F.col("a").alias("b"), "lap", "p"))
    rows = both.join(inclusion.withColumnRenamed("g", "b"), "b").join(vectors.select(F.col("g").alias("a"), "vec"), "a")
    return rows.select(F.col("b").alias("g"), F.transform("vec", lambda x: x * F.col("lap") * F.col("p_v") / F.col("p")).alias("vec")).groupBy("g").agg(vec_sum(F.col("vec"), d).alias("est"))


def graph_estimate(sampled: DataFrame, d: int) -> DataFrame:
    """(est): the sum of c / p over sampled edges, an unbiased estimate of the sum of c over all."""
    return sampled.select(F.transform("c", lambda x: x / F.col("p")).alias("vec")).agg(vec_sum(F.col("vec"), d).alias("est"))


def variance(scored: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(variance): the sum of score**2 / p - score**2 for independent draws, over all edges or by a column such as origin."""
    square = F.col("score") * F.col("score")
    return scored.groupBy(*by).agg((F.sum(square / F.col("p")) - F.sum(square)).alias("variance"))


def least_variance(scored: DataFrame, num: int) -> DataFrame:
    """(bound): what no inclusion probabilities that sum to num can beat."""
    return scored.agg((F.pow(F.sum("score"), F.lit(2.0)) / num - F.sum(F.col("score") * F.col("score"))).alias("bound"))


def approx_bounds(scored: DataFrame, layers: int, d: float, norm_cap: str = "d") -> DataFrame:
    """Per edge: the best draw probability, the topology-only one, the interval around the first and the error bounds.

    norm_cap 'sqrt_d' uses the sharper bound of a sigmoid vector's length.
    """
    cap = F.lit(float(d) if norm_cap == "d" else float(d) ** 0.5)
    rows = scored.withColumn("m", F.col("score") / F.col("lap") / (2 * layers))
    sums = rows.agg(F.sum("lap").alias("q_sum"), F.sum(F.col("lap") * F.col("m")).alias("m_sum"))
    rows = rows.join(F.broadcast(sums))
    best, plain = F.col("lap") * F.col("m") / F.col("m_sum"), F.col("lap") / F.col("q_sum")
    lower, upper = F.col("lap") * F.col("m") / (F.col("q_sum") * cap), F.col("lap") * cap / F.col("m_sum")
    low_side, high_side = plain * (1 - F.col("m") / cap), F.col("lap") * F.abs(cap / F.col("m_sum") - 1 / F.col("q_sum"))
    rows = rows.select("a", "b", best.alias("best"), plain.alias("plain"), lower.alias("lower"), upper.alias("upper"), low_side.alias("low_side"), high_side.alias("high_side"))
    error = F.abs(F.col("plain") - F.col("best"))
    holds = F.col("best").between(F.col("lower") - 1e-12, F.col("upper") + 1e-12) & (error <= F.greatest("low_side", "high_side") + 1e-12)
    return rows.withColumns({"error": error, "holds": holds})
