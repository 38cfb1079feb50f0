"""The propagation graph of an item: directed, weighted, and refreshed where new interactions arrive."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .factors import weight

COLUMNS = ["v", "src", "dst", "a_src", "w_src", "w_dst", "sim", "p"]


def build(sims: DataFrame, active: DataFrame, will: DataFrame, **kw) -> DataFrame:
    """(v, src, dst, a_src, w_src, w_dst, sim, p) from similarity per edge, activeness per group and willingness per item."""
    a = active.select(F.col("g").alias("src"), "act")
    w1, w2 = (will.select("v", F.col("g").alias(k), F.col("will").alias(f"w_{k}")) for k in ("src", "dst"))
    rows = sims.join(a, "src", "left").join(w1, "src").join(w2, ["v", "dst"])
    rows = rows.withColumn("a_src", F.coalesce("act", F.lit(0.0)))
    return rows.withColumn("p", weight(**kw)).select(*COLUMNS)


def by_in_degree(graph: DataFrame) -> DataFrame:
    """The graph with each weight divided by the number of edges that enter its target, as in the weighted cascade model: a
    group with many neighbours then does not accept from nearly every one, and cascades end before all are active."""
    return graph.withColumn("p", F.col("p") / F.count("*").over(Window.partitionBy("v", "dst")))


def apply_updates(graph: DataFrame, fresh: DataFrame, active: DataFrame, **kw) -> DataFrame:
    """The graph after new interactions (v, g): those groups get willingness 1 for that item and their current activeness,
    and the edges at them new weights. Similarities stay."""
    hit = fresh.select("v", "g").distinct()
    src = hit.join(active.select("g", F.col("act").alias("new_a")), "g", "left").select("v", F.col("g").alias("src"), F.coalesce("new_a", F.lit(0.0)).alias("new_a"), F.lit(True).alias("hit_src"))
    dst = hit.select("v", F.col("g").alias("dst"), F.lit(True).alias("hit_dst"))
    rows = graph.join(src, ["v", "src"], "left").join(dst, ["v", "dst"], "left")
    rows = rows.withColumns(
        {
            "a_src": F.coalesce("new_a", "a_src"),
            "w_src": F.when(F.col("hit_src"), 1.0).otherwise(F.col("w_src")),
            "w_dst": F.when(F.col("hit_dst"), 1.0).otherwise(F.col("w_dst")),
        }
    )
    touched = F.coalesce("hit_src", "hit_dst", F.lit(False))
    return rows.withColumn("p", F.when(touched, weight(**kw)).otherwise(F.col("p"))).select(*COLUMNS)
