"""What drives the spread of an item: activeness, similarity and willingness, and the weights they give to edges."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import uniform
from ..functions.linalg import cosine, dot, sigmoid
from ..operators.joins import bounded

GAMMA1, GAMMA2 = 0.1, 0.7


def activeness(activity: DataFrame, now: int, horizon: int = 7) -> DataFrame:
    """(g, recent, total, act): the share of a group's activities until `now` that fall into the last `horizon` days."""
    rows = activity.where(F.col("day") <= now)
    recent = F.count(F.when(F.col("day") > now - horizon, 1))
    counted = rows.groupBy("g").agg(recent.alias("recent"), F.count("*").alias("total"))
    return counted.withColumn("act", F.col("recent") / F.col("total"))


def similarity(edges: DataFrame, groups: DataFrame, d: int) -> DataFrame:
    """(src, dst, sim): the cosine of the groups at both ends. It belongs to a version of the vectors, not to an item."""
    a, b = (groups.select(F.col("g").alias(k), F.col("vec").alias(f"{k}_vec")) for k in ("src", "dst"))
    return edges.select("src", "dst").join(a, "src").join(b, "dst").select("src", "dst", cosine(F.col("src_vec"), F.col("dst_vec"), d).alias("sim"))


def willingness(items: DataFrame, groups: DataFrame, d: int, normalise: str = "sigmoid") -> DataFrame:
    """(v, g, will) for a window of items, a bounded set that every task holds: the inner product, brought to [0, 1]."""
    pairs = groups.select("g", F.col("vec").alias("gv")).join(bounded(items.select("v", F.col("vec").alias("iv"))))
    raw = dot(F.col("iv"), F.col("gv"), d)
    if normalise == "minmax":
        rows = pairs.select("v", "g", raw.alias("raw"))
        ends = rows.groupBy("v").agg(F.min("raw").alias("lo"), F.max("raw").alias("hi"))
        spread = F.nullif(F.col("hi") - F.col("lo"), F.lit(0.0))
        return rows.join(F.broadcast(ends), "v").select("v", "g", F.coalesce((F.col("raw") - F.col("lo")) / spread, F.lit(0.0)).alias("will"))
    value = {"none": raw, "sigmoid": sigmoid(raw), "clip": F.least(F.greatest(raw, F.lit(0.0)), F.lit(1.0))}[normalise]
    return pairs.select("v", "g", value.alias("will"))


def weight(g1: float = GAMMA1, g2: float = GAMMA2, drop: str | None = None, renorm: bool = False):
    """The weight of a propagation edge from its columns a_src, w_src, sim and w_dst.

    drop leaves out 'similarity', 'willingness' (the sender's activeness stays) or 'activeness'; renorm scales what is
    left of the three coefficients back to a sum of one.
    """
    if g1 < 0 or g2 < 0 or g1 + g2 > 1:
        raise ValueError("need g1, g2 >= 0 and g1 + g2 <= 1")
    a, s, r = g1, g2, 1 - g1 - g2
    send, like, take = F.col("a_src") * F.col("w_src"), F.col("sim"), F.col("w_dst")
    if drop == "similarity":
        s = 0.0
    elif drop == "willingness":
        send, r = F.col("a_src"), 0.0
    elif drop == "activeness":
        send = F.col("w_src")
    elif drop is not None:
        raise ValueError("drop is similarity, willingness, activeness or None")
    scale = 1 / (a + s + r) if renorm and a + s + r > 0 else 1.0
    return scale * a * send + scale * s * like + scale * r * take


def random_weights(edges: DataFrame, salt: str = "random") -> DataFrame:
    """Baseline: a hashed number as probability."""
    return edges.select("src", "dst", uniform(salt, "src", "dst").alias("p"))


def static_weights(edges: DataFrame, active: DataFrame, sims: DataFrame) -> DataFrame:
    """Baseline: the mean of the sender's activeness and the similarity, the same for all items and times."""
    a = active.select(F.col("g").alias("src"), "act")
    rows = edges.select("src", "dst").join(a, "src", "left").join(sims, ["src", "dst"])
    return rows.select("src", "dst", ((F.coalesce("act", F.lit(0.0)) + F.col("sim")) / 2).alias("p"))
