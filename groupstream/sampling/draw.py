"""Draw and inclusion probabilities of edges, and the ways to sample by them.

Edges are undirected rows (a, b, lap, deg_a, deg_b, ci, cj). q sums to one in each set (ci, cj); p = min(1, num * q), with
the excess of capped edges spread over the others, sums to num.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import uniform

_SET = ("ci", "cj")


def draw_probability(edges: DataFrame, kind: str = "laplacian", scores: DataFrame | None = None) -> DataFrame:
    """edges with q, by kind: 'laplacian' (topology alone), 'degree_sum', 'uniform' or 'optimal' (scores: (a, b, score))."""
    if kind == "optimal":
        weighed = edges.join(scores.select("a", "b", F.col("score").alias("weight")), ["a", "b"])
    else:
        weight = {"laplacian": F.col("lap"), "degree_sum": (F.col("deg_a") + F.col("deg_b")).cast("double"), "uniform": F.lit(1.0)}[kind]
        weighed = edges.withColumn("weight", weight)
    total = F.sum("weight").over(Window.partitionBy(*_SET))
    return weighed.select(*edges.columns, (F.col("weight") / total).alias("q"))


def inclusion(drawn: DataFrame, quotas: DataFrame) -> DataFrame:
    """drawn with num, p and capped. In order of falling q an edge is capped if its share of what the ones before leave
    reaches one, and the capped ones are a prefix, so no rounds are needed."""
    order = Window.partitionBy(*_SET).orderBy(F.desc("q"), "a", "b")
    whole = Window.partitionBy(*_SET)
    rows = drawn.join(quotas.select(*_SET, "num"), list(_SET))
    rows = rows.withColumns({"place": F.row_number().over(order) - 1, "rest": F.sum("q").over(whole) - F.coalesce(F.sum("q").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))})
    rows = rows.withColumn("capped", ((F.col("num") - F.col("place")) * F.col("q") >= F.col("rest") - 1e-12) & (F.col("place") < F.col("num")))
    free = F.when(~F.col("capped"), F.col("q"))
    rows = rows.withColumns({"k": F.sum(F.col("capped").cast("long")).over(whole), "free": F.sum(free).over(whole)})
    p = F.when(F.col("capped"), 1.0).otherwise((F.col("num") - F.col("k")) * F.col("q") / F.col("free"))
    return rows.select(*drawn.columns, "num", p.alias("p"), "capped")


def sample_poisson(included: DataFrame, salt: str = "edge") -> DataFrame:
    """Each edge on its own with probability p: one narrow pass."""
    return included.where(uniform(salt, "a", "b") < F.col("p"))


def race_key(salt: str):
    """An exponential race: the smallest keys are a sample without replacement with draw probabilities q."""
    return -F.log(uniform(salt, "a", "b") + F.lit(2.0**-33)) / F.col("q")


def sample_fixed(included: DataFrame, salt: str = "edge", num: str = "num") -> DataFrame:
    """Exactly num edges of each set (all, if it has fewer)."""
    order = Window.partitionBy(*_SET).orderBy(F.round(race_key(salt), 9), "a", "b")
    return included.withColumn("__n", F.row_number().over(order)).where(F.col("__n") <= F.col(num)).drop("__n")


def sample_top_degree(edges: DataFrame, num: str = "num") -> DataFrame:
    """The num edges of each set with the highest degrees."""
    order = Window.partitionBy(*_SET).orderBy(F.desc(F.col("deg_a") + F.col("deg_b")), "a", "b")
    return edges.withColumn("__n", F.row_number().over(order)).where(F.col("__n") <= F.col(num)).drop("__n")


def layer_sample(edges: DataFrame, seeds: DataFrame, fanout: int, layers: int, salt: str = "layer") -> DataFrame:
    """(layer, src, dst): neighbour sampling per layer, up to `fanout` hashed picks for each node that the layer above holds."""
    out, need = None, seeds.select("g").distinct()
    for layer in range(layers, 0, -1):
        order = Window.partitionBy("dst").orderBy(uniform(f"{salt}{layer}", "src", "dst"), "src")
        hop = edges.select("src", "dst").join(need.withColumnRenamed("g", "dst"), "dst", "left_semi")
        hop = hop.withColumn("n", F.row_number().over(order)).where(F.col("n") <= fanout).select(F.lit(layer).alias("layer"), "src", "dst")
        out = hop if out is None else out.unionByName(hop)
        need = need.unionByName(hop.select(F.col("src").alias("g"))).distinct()
    return out


def subgraph_sample(edges: DataFrame, num: int, salt: str = "subgraph") -> DataFrame:
    """One draw of num edges of the whole graph, without strata or overlap."""
    return edges.withColumn("__u", uniform(salt, "a", "b")).orderBy("__u", "a", "b").limit(num).drop("__u")
