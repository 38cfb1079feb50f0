"""The snapshot edge sampler: subgraphs of consecutive slices that share the edges where interests drift."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.storage import settle
from .clusters import allocate
from .draw import draw_probability, race_key, sample_fixed

_SET = ["ci", "cj"]


def slice_graph(edges: DataFrame, counts: DataFrame, t: int) -> DataFrame:
    """The edges that exist in slice t: both groups have interacted by then. counts: (g, slice, n)."""
    active = counts.where(F.col("slice") <= t).select("g").distinct()
    return edges.join(active.withColumnRenamed("g", "a"), "a", "left_semi").join(active.withColumnRenamed("g", "b"), "b", "left_semi")


def overlap_edges(previous: DataFrame, current: DataFrame) -> DataFrame:
    """The edges of the current graph that the previous one has too."""
    return current.join(previous.select("a", "b"), ["a", "b"], "left_semi")


def drifting(counts: DataFrame, t: int) -> DataFrame:
    """(g): groups whose number of new interactions differs between slices t - 1 and t."""
    now, before = (counts.where(F.col("slice") == s).select("g", F.col("n").alias(k)) for s, k in ((t, "n1"), (t - 1, "n0")))
    both = now.join(before, "g", "full_outer")
    return both.where(F.coalesce("n1", F.lit(0)) != F.coalesce("n0", F.lit(0))).select("g")


def changed_edges(edges: DataFrame, drift: DataFrame) -> DataFrame:
    """edges with changed: whether either end drifts."""
    a, b = (drift.select(F.col("g").alias(k), F.lit(True).alias(f"d_{k}")) for k in "ab")
    both = edges.join(a, "a", "left").join(b, "b", "left")
    return both.select(*edges.columns, (F.coalesce("d_a", F.lit(False)) | F.coalesce("d_b", F.lit(False))).alias("changed"))


def sample_overlap(previous: DataFrame, current: DataFrame, drift: DataFrame, quotas: DataFrame, overlap: float) -> DataFrame:
    """round(overlap * num) edges of each set from those shared with the previous sample: drifting ones first, then by degree."""
    shared = changed_edges(overlap_edges(previous, current), drift).join(quotas.select(*_SET, "num"), _SET)
    order = Window.partitionBy(*_SET).orderBy(F.desc("changed"), F.desc(F.col("deg_a") + F.col("deg_b")), "a", "b")
    kept = shared.withColumn("__n", F.row_number().over(order)).where(F.col("__n") <= F.round(F.col("num") * overlap))
    return kept.select(*current.columns, F.lit("overlap").alias("origin"))


def sample_fresh(previous: DataFrame, current: DataFrame, reused: DataFrame, quotas: DataFrame, kind: str, salt: str) -> DataFrame:
    """What is missing of each set's num, drawn from edges outside the previous sample."""
    taken = reused.groupBy(*_SET).agg(F.count("*").alias("taken"))
    rest = quotas.join(taken, _SET, "left").select(*_SET, (F.col("num") - F.coalesce("taken", F.lit(0))).alias("missing"))
    unused = current.join(previous.select("a", "b"), ["a", "b"], "left_anti")
    drawn = draw_probability(unused, kind).join(rest, _SET)
    return sample_fixed(drawn, salt, "missing").select(*current.columns, F.lit("fresh").alias("origin"))


def snapshot_sequence(edges: DataFrame, counts: DataFrame, slices: int, share: float = 0.3, overlap: float = 0.5, kind: str = "laplacian", salt: str = "slice", quotas: DataFrame | None = None) -> DataFrame:
    """(slice, origin, a, b, ...): the sampled subgraph of every slice. edges hold their set (ci, cj), degrees and lap.

    Quotas are the same share of each slice's graph, unless given for all slices.
    """
    previous, out = None, None
    for t in range(slices):
        current = slice_graph(edges, counts, t)
        num = settle(allocate(current, share), "quotas") if quotas is None else quotas
        if previous is None:
            drawn = draw_probability(current, kind).join(num.select(*_SET, "num"), _SET)
            now = sample_fixed(drawn, f"{salt}{t}").select(*current.columns, F.lit("fresh").alias("origin"))
        else:
            reused = sample_overlap(previous, current, drifting(counts, t), num, overlap)
            now = reused.unionByName(sample_fresh(previous, current, reused, num, kind, f"{salt}{t}"))
        previous = settle(now, "slice")
        labelled = previous.select(F.lit(t).alias("slice"), "origin", *edges.columns)
        out = labelled if out is None else out.unionByName(labelled)
    return out


def generate_subgraph(sample: DataFrame, sliced: DataFrame) -> DataFrame:
    """The interactions of the groups that a sample of edges touches."""
    nodes = sample.select(F.col("a").alias("g")).unionByName(sample.select(F.col("b").alias("g"))).distinct()
    return sliced.join(nodes, "g", "left_semi")


def redundancy(sequence: DataFrame) -> DataFrame:
    """(slice, n_edges, shared): how many of a slice's edges the slice before it has too."""
    before = sequence.select((F.col("slice") + 1).alias("slice"), "a", "b", F.lit(1).alias("was"))
    both = sequence.select("slice", "a", "b").join(before, ["slice", "a", "b"], "left")
    return both.groupBy("slice").agg(F.count("*").alias("n_edges"), F.sum(F.coalesce("was", F.lit(0))).alias("shared"))


def stratum_drift(edges: DataFrame, sample: DataFrame) -> DataFrame:
    """(ci, cj, share_all, share_sample, gap): how far a sample's shares of the sets are from the graph's."""
    whole = edges.groupBy(*_SET).agg(F.count("*").alias("n")).withColumn("share_all", F.col("n") / F.sum("n").over(Window.partitionBy())).drop("n")
    part = sample.groupBy(*_SET).agg(F.count("*").alias("n")).withColumn("share_sample", F.col("n") / F.sum("n").over(Window.partitionBy())).drop("n")
    both = whole.join(part, _SET, "full_outer").na.fill(0.0, ["share_all", "share_sample"])
    return both.withColumn("gap", F.abs(F.col("share_all") - F.col("share_sample")))


def drift_coverage(sequence: DataFrame, counts: DataFrame, t: int) -> DataFrame:
    """(drifting, covered): drifting groups of slice t, and those that its sample touches."""
    rows = sequence.where(F.col("slice") == t)
    nodes = rows.select(F.col("a").alias("g")).unionByName(rows.select(F.col("b").alias("g"))).distinct().withColumn("hit", F.lit(1))
    return drifting(counts, t).join(nodes, "g", "left").agg(F.count("*").alias("drifting"), F.coalesce(F.sum("hit"), F.lit(0)).cast("long").alias("covered"))
