"""Relevance of items to groups, ranking loss and training triples."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import uniform
from ..functions.linalg import add, dot, vec_sum, zeros
from ..operators.joins import bounded, positions


def history_vectors(interactions: DataFrame, items: DataFrame, d: int) -> DataFrame:
    """(g, hist): the sum of the vectors of a group's distinct items over the square root of their number."""
    seen = interactions.select("g", "v").distinct().join(items, "v")
    summed = seen.groupBy("g").agg(vec_sum(F.col("vec"), d).alias("total"), F.count("*").alias("n_items"))
    return summed.select("g", F.transform("total", lambda x: x / F.sqrt(F.col("n_items").cast("double"))).alias("hist"), "n_items")


def group_side(groups: DataFrame, history: DataFrame, d: int) -> DataFrame:
    """(g, vec): a group's vector with its history added, so that relevance is one inner product."""
    both = groups.join(history.select("g", "hist"), "g", "left")
    return both.select("g", add(F.col("vec"), F.coalesce("hist", zeros(d))).alias("vec"))


def augment(groups: DataFrame, items: DataFrame, influence: DataFrame, alpha_r: float) -> tuple[DataFrame, DataFrame]:
    """Vectors of one more dimension whose inner product is the whole relevance:
    [(1 - alpha_r) item ; alpha_r] and [group ; influence]."""
    g = groups.join(influence, "g", "left").select("g", F.concat("vec", F.array(F.coalesce("influence", F.lit(0.0)))).alias("vec"))
    v = items.select("v", F.concat(F.transform("vec", lambda x: x * (1 - alpha_r)), F.array(F.lit(float(alpha_r)))).alias("vec"))
    return g, v


def relevance(groups: DataFrame, items: DataFrame, d: int) -> DataFrame:
    """(v, g, score) of every item of a bounded set against all groups: the exhaustive way."""
    pairs = groups.select("g", F.col("vec").alias("gv")).join(bounded(items.select("v", F.col("vec").alias("iv"))))
    return pairs.select("v", "g", dot(F.col("iv"), F.col("gv"), d).alias("score"))


#: Digits that decide a rank, so that engines which add in another order agree, and digits that are shown. The first have to
#: show an influence of one group in many, times its small share of the score.
RANK_DIGITS, DIGITS = 12, 6


def top_k(scored: DataFrame, k: int, by: str = "v", other: str = "g") -> DataFrame:
    """(by, rank, other, score): the k best by score, ties to the smaller id."""
    rows = scored.withColumn("raw", F.round("score", RANK_DIGITS) + F.lit(0.0))
    rank = F.row_number().over(Window.partitionBy(by).orderBy(F.desc("raw"), other))
    return rows.withColumn("rank", rank).where(F.col("rank") <= k).select(by, "rank", other, (F.round("raw", DIGITS) + F.lit(0.0)).alias("score"))


def training_triples(interactions: DataFrame, items: DataFrame, negatives: int = 1, salt: str = "negative", keep: tuple[str, ...] = ()) -> DataFrame:
    """(g, pos, draw, neg): for every positive pair so many hashed draws of items; draws that the group touched are left out.

    keep: further columns of interactions, such as their slice; a pair then counts once for each of their values.
    """
    numbered = positions(items.select("v"), ["v"], "place")
    n = F.broadcast(items.agg(F.count("*").alias("n_items")))
    pairs = interactions.select("g", F.col("v").alias("pos"), *keep).distinct().join(n).withColumn("draw", F.explode(F.array(*[F.lit(i) for i in range(negatives)])))
    drawn = pairs.withColumn("place", F.floor(uniform(salt, "g", "pos", "draw") * F.col("n_items")))
    drawn = drawn.join(numbered.withColumnRenamed("v", "neg"), "place")
    touched = interactions.select(F.col("g").alias("g2"), F.col("v").alias("v2")).distinct()
    return drawn.join(touched, (F.col("g") == F.col("g2")) & (F.col("neg") == F.col("v2")), "left_anti").select("g", "pos", "draw", "neg", *keep)


def pairwise_loss(triples: DataFrame, groups: DataFrame, items: DataFrame, d: int, penalty: float = 0.0, squares: float = 0.0) -> DataFrame:
    """(n, loss): the sum of -ln sigmoid(score of the positive - score of the negative), plus penalty * squares."""
    g = groups.select("g", F.col("vec").alias("gv"))
    p, q = (items.select(F.col("v").alias(k), F.col("vec").alias(f"{k}_vec")) for k in ("pos", "neg"))
    rows = triples.join(g, "g").join(p, "pos").join(q, "neg")
    gap = dot(F.col("gv"), F.col("pos_vec"), d) - dot(F.col("gv"), F.col("neg_vec"), d)
    return rows.agg(F.count("*").alias("n"), (F.sum(F.log1p(F.exp(-gap))) + F.lit(penalty * squares)).alias("loss"))
