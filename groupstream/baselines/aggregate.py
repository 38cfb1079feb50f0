"""Baselines without influence: aggregated scores and preferences, attention over members, light and multi-view
convolution, item neighbours and popularity."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.linalg import dot, vec_mean, vec_sum, zeros
from ..operators.joins import bounded
from ..sources.storage import settle


def user_scores(users: DataFrame, items: DataFrame, d: int) -> DataFrame:
    """(u, v, score) for a bounded window of items."""
    pairs = users.select("u", F.col("vec").alias("uv")).join(bounded(items.select("v", F.col("vec").alias("iv"))))
    return pairs.select("u", "v", dot(F.col("uv"), F.col("iv"), d).alias("score"))


def score_aggregate(scores: DataFrame, members: DataFrame, how: str = "average") -> DataFrame:
    """(g, v, score): the members' scores by average, least misery (minimum) or most pleasure (maximum)."""
    pick = {"average": F.avg, "least_misery": F.min, "most_pleasure": F.max}[how]
    return members.select("g", "u").join(scores, "u").groupBy("g", "v").agg(pick("score").alias("score"))


def preference_aggregate(members: DataFrame, users: DataFrame, d: int) -> DataFrame:
    """(g, vec): the mean of the members' vectors."""
    return members.select("g", "u").join(users, "u").groupBy("g").agg(vec_mean(F.col("vec"), d).alias("vec"))


def _weighed(rows: DataFrame, d: int) -> DataFrame:
    """(g, vec) from (g, vec, e): the mean with weights e."""
    summed = rows.select("g", F.transform("vec", lambda x: x * F.col("e")).alias("vec"), "e").groupBy("g").agg(vec_sum(F.col("vec"), d).alias("vec"), F.sum("e").alias("all"))
    return summed.select("g", F.transform("vec", lambda x: x / F.col("all")).alias("vec"))


def member_attention(members: DataFrame, users: DataFrame, d: int) -> DataFrame:
    """(g, vec): members weigh by the softmax of how well they agree with the group's mean preference."""
    rows = members.select("g", "u").join(users, "u")
    mean = preference_aggregate(members, users, d).withColumnRenamed("vec", "mean")
    return _weighed(rows.join(mean, "g").select("g", "vec", F.exp(dot(F.col("vec"), F.col("mean"), d)).alias("e")), d)


def static_attention(members: DataFrame, users: DataFrame, d: int) -> DataFrame:
    """(g, vec): members weigh by the number of their groups, a fixed sign of their influence."""
    degree = members.groupBy("u").agg(F.count("*").cast("double").alias("e"))
    return _weighed(members.select("g", "u").join(users, "u").join(degree, "u").select("g", "vec", "e"), d)


def light_conv(interactions: DataFrame, groups: DataFrame, items: DataFrame, layers: int, d: int) -> tuple[DataFrame, DataFrame]:
    """(g, vec) and (v, vec): vectors smoothed over the bipartite graph without weights or non-linearity, averaged over layers."""
    edges = interactions.select("g", "v").distinct()
    dg, dv = edges.groupBy("g").agg(F.count("*").alias("dg")), edges.groupBy("v").agg(F.count("*").alias("dv"))
    edges = edges.join(dg, "g").join(dv, "v").select("g", "v", (1 / F.sqrt((F.col("dg") * F.col("dv")).cast("double"))).alias("w"))

    def hop(vectors: DataFrame, have: str, want: str) -> DataFrame:
        sent = edges.join(vectors, have).select(want, F.transform("vec", lambda x: x * F.col("w")).alias("vec"))
        return sent.groupBy(want).agg(vec_sum(F.col("vec"), d).alias("vec"))

    def joined(base: DataFrame, new: DataFrame, key: str) -> DataFrame:
        return base.select(key).join(new, key, "left").select(key, F.coalesce("vec", zeros(d)).alias("vec"))

    gs, vs = [groups.select("g", "vec")], [items.select("v", "vec")]
    for _ in range(layers):
        g, v = joined(groups, hop(vs[-1], "v", "g"), "g"), joined(items, hop(gs[-1], "g", "v"), "v")
        gs.append(g)
        vs.append(v)

    def mean(parts: list[DataFrame], key: str) -> DataFrame:
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out.groupBy(key).agg(vec_mean(F.col("vec"), d).alias("vec"))

    return mean(gs, "g"), mean(vs, "v")


def multi_view(members: DataFrame, users: DataFrame, interactions: DataFrame, items: DataFrame, edges: DataFrame, d: int) -> DataFrame:
    """(g, vec): member view, item view and overlap view, fused by a softmax gate over how each agrees with their mean."""
    member = preference_aggregate(members, users, d)
    item = interactions.select("g", "v").distinct().join(items, "v").groupBy("g").agg(vec_mean(F.col("vec"), d).alias("b"))
    near = edges.select("src", F.col("dst").alias("g")).join(member.withColumnRenamed("g", "src"), "src").groupBy("g").agg(vec_mean(F.col("vec"), d).alias("c"))
    rows = member.withColumnRenamed("vec", "a").join(item, "g", "left").join(near, "g", "left")
    rows = rows.select("g", "a", F.coalesce("b", zeros(d)).alias("b"), F.coalesce("c", zeros(d)).alias("c"))
    mean = F.transform(F.zip_with(F.zip_with("a", "b", lambda x, y: x + y), F.col("c"), lambda x, y: x + y), lambda x: x / 3)
    rows = rows.withColumn("mean", mean)
    rows = rows.withColumns({f"e_{k}": F.exp(dot(F.col(k), F.col("mean"), d)) for k in "abc"})
    total = F.col("e_a") + F.col("e_b") + F.col("e_c")
    fused = F.array(*[(F.col("e_a") * F.get("a", F.lit(i)) + F.col("e_b") * F.get("b", F.lit(i)) + F.col("e_c") * F.get("c", F.lit(i))) / total for i in range(d)])
    return rows.select("g", fused.alias("vec"))


def item_neighbours(lines: DataFrame, k: int = 10, max_items: int | None = None) -> DataFrame:
    """(v, rank, other, n): the items most often bought by the same users. max_items leaves users with more items out; off
    by default. All pairs of a user's items are counted, in as many passes over parts of the items as bound what a pass moves."""
    rows = lines.select("u", "v").distinct()
    if max_items is not None:
        rows = rows.join(rows.groupBy("u").agg(F.count("*").alias("k")).where(F.col("k") <= max_items).select("u"), "u", "left_semi")
    baskets = settle(rows.groupBy("u").agg(F.collect_set("v").alias("vs")), "baskets")
    n_pairs = baskets.agg(F.sum(F.size("vs").cast("double") * F.size("vs"))).first()[0] or 0.0
    passes, parts = max(1, math.ceil(n_pairs / PAIRS)), max(1, math.ceil(min(n_pairs, PAIRS) / TOGETHER))
    place = lambda v: F.pmod(F.xxhash64(v), F.lit(passes * parts))
    out = None
    for number in range(passes):
        own = F.filter("vs", lambda v: place(v) % passes == number)
        sent = baskets.select(F.explode(own).alias("v"), "vs").withColumn("part", place(F.col("v")))
        found = sent.groupBy("part").applyInPandas(lambda r: _neighbours(r, k), "v long, rank int, other long, n long")
        if passes > 1:
            found = settle(found, "neighbours")
            lines.sparkSession._jvm.System.gc()  # lets Spark remove the shuffle files of this pass
        out = found if out is None else out.unionByName(found)
    return out


#: Pairs of a user's items that are on their way at once, and that are counted together.
PAIRS, TOGETHER = 1 << 28, 1 << 22


def _neighbours(rows: pd.DataFrame, k: int) -> pd.DataFrame:
    """The first k others of each item, from its buyers' baskets: baskets travel to their items and are opened here."""
    sizes = rows["vs"].map(len).to_numpy()
    v, other = np.repeat(rows["v"].to_numpy(np.int64), sizes), np.concatenate(rows["vs"].to_list())
    v, other = v[v != other], other[v != other]
    order = np.lexsort((other, v))
    v, other = v[order], other[order]
    first = np.flatnonzero(np.append(True, (v[1:] != v[:-1]) | (other[1:] != other[:-1]))) if len(v) else np.zeros(0, np.int64)
    n = np.diff(np.append(first, len(v)))
    v, other = v[first], other[first]
    order = np.lexsort((other, -n, v))
    v, other, n = v[order], other[order], n[order]
    start = np.flatnonzero(np.append(True, v[1:] != v[:-1])) if len(v) else first
    rank = np.arange(len(v)) - np.repeat(start, np.diff(np.append(start, len(v)))) + 1
    return pd.DataFrame({"v": v, "rank": rank, "other": other, "n": n})[rank <= k]


def popularity(interactions: DataFrame, by: str = "v", k: int = 20) -> DataFrame:
    """(by, n, rank): the k most interacting items or groups."""
    counted = interactions.groupBy(by).agg(F.count("*").alias("n")).orderBy(F.desc("n"), by).limit(k)
    return counted.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("n"), by)))
