"""The undirected graph of groups: ties by common users and by friendship, pruned to a bounded number per group."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


#: How many times the days of a friendship a window of the interval join is long.
WINDOW = 6


def common_user_edges(members: DataFrame, min_common: int = 1, max_degree: int | None = None) -> DataFrame:
    """(a, b, common), a < b: a self-join on the user, counted in partial sums.

    A user in k groups makes k * (k - 1) / 2 pairs. max_degree leaves users in more groups out; it is off by default,
    since a skewed user's rows are split by the adaptive join.
    """
    rows = members.select("u", "g")
    if max_degree is not None:
        few = rows.groupBy("u").agg(F.count("*").alias("k")).where(F.col("k") <= max_degree)
        rows = rows.join(few.select("u"), "u", "left_semi")
    left, right = rows.withColumnRenamed("g", "a"), rows.withColumnRenamed("g", "b")
    pairs = left.join(right, "u").where("a < b").groupBy("a", "b").agg(F.count("*").alias("common"))
    return pairs.where(F.col("common") >= min_common)


def friendship_edges(lines: DataFrame, days: int = 30) -> DataFrame:
    """(a, b, items), a < b: users who bought a common item within so many days of each other.

    An interval join: the left side lies in windows of several times `days`, the right one in each window that its days reach
    into, which is mostly one. A pair meets in the left row's window alone.
    """
    width = max(1, WINDOW * days)
    bought = lines.select("v", "u", "day").distinct()
    left = bought.select("v", F.floor(F.col("day") / width).alias("window"), F.col("u").alias("a"), F.col("day").alias("day_a"))
    reached = F.explode(F.sequence(F.floor((F.col("day") - days) / width), F.floor((F.col("day") + days) / width)))
    right = bought.select("v", reached.alias("window"), F.col("u").alias("b"), F.col("day").alias("day_b"))
    close = left.join(right, ["v", "window"]).where((F.col("a") < F.col("b")) & (F.abs(F.col("day_a") - F.col("day_b")) <= days))
    return close.select("a", "b", "v").distinct().groupBy("a", "b").agg(F.count("*").alias("items"))


def lift_to_groups(friends: DataFrame, members: DataFrame) -> DataFrame:
    """(a, b, friends), a < b: friend pairs between the members of two groups."""
    m1, m2 = (members.select(F.col("u").alias(u), F.col("g").alias(g)) for u, g in (("a", "ga"), ("b", "gb")))
    both = friends.select("a", "b").join(m1, "a").join(m2, "b").where("ga <> gb")
    return both.groupBy(F.least("ga", "gb").alias("a"), F.greatest("ga", "gb").alias("b")).agg(F.count("*").alias("friends"))


def ties(common: DataFrame, friends: DataFrame) -> DataFrame:
    """(a, b, common, friends, w): the union of both kinds of ties."""
    both = common.join(friends, ["a", "b"], "full_outer")
    c, f = F.coalesce("common", F.lit(0)).cast("long"), F.coalesce("friends", F.lit(0)).cast("long")
    return both.select("a", "b", c.alias("common"), f.alias("friends"), (c + f).alias("w"))


def symmetric(edges: DataFrame, *more: str) -> DataFrame:
    """(src, dst, ...) in both directions."""
    one = edges.select(F.col("a").alias("src"), F.col("b").alias("dst"), *more)
    return one.unionByName(edges.select(F.col("b").alias("src"), F.col("a").alias("dst"), *more))


def prune(edges: DataFrame, rule: str, value: float, sizes: DataFrame | None = None) -> DataFrame:
    """Edges (a, b, w) that a rule keeps: 'min_common', 'min_jaccard' (with group sizes g, size) or 'top_neighbours'."""
    if rule == "min_common":
        return edges.where(F.col("w") >= value)
    if rule == "min_jaccard":
        a, b = (sizes.select(F.col("g").alias(k), F.col("size").alias(f"size_{k}")) for k in "ab")
        union = F.col("size_a") + F.col("size_b") - F.col("w")
        return edges.join(a, "a").join(b, "b").where(F.col("w") / union >= value).select(*edges.columns)
    if rule == "top_neighbours":
        best = Window.partitionBy("src").orderBy(F.desc("w"), "dst")
        kept = symmetric(edges, "w").withColumn("n", F.row_number().over(best)).where(F.col("n") <= value)
        return kept.groupBy(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).agg(F.max("w").alias("w"))
    raise ValueError("rule is min_common, min_jaccard or top_neighbours")


def laplacian_weights(edges: DataFrame) -> DataFrame:
    """(src, dst) -> with deg_src, deg_dst and lap = 1 / sqrt(deg_src * deg_dst)."""
    degree = edges.groupBy(F.col("src").alias("k")).agg(F.count("*").alias("deg"))
    src = degree.select(F.col("k").alias("src"), F.col("deg").alias("deg_src"))
    dst = degree.select(F.col("k").alias("dst"), F.col("deg").alias("deg_dst"))
    return edges.join(src, "src").join(dst, "dst").select(*edges.columns, "deg_src", "deg_dst", (1 / F.sqrt((F.col("deg_src") * F.col("deg_dst")).cast("double"))).alias("lap"))
