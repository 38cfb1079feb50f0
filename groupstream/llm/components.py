"""Connected components of a table of links, by alternating large-star and small-star rounds.

Both steps need only the least neighbour of each node, an aggregate that Spark combines before its shuffle, and a join of
links with it, which it can split where a node has very many links. No node's neighbours are ever gathered in one row.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, drop_cut


def _rooted(pairs: DataFrame) -> DataFrame:
    """(a, b) with a > b, each once."""
    return pairs.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()


def _large_star(links: DataFrame) -> DataFrame:
    both = links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
    return _rooted(both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")))


def _small_star(links: DataFrame) -> DataFrame:
    least = links.groupBy("a").agg(F.min("b").alias("m"))
    moved = links.join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return _rooted(moved.unionByName(least.select("a", F.col("m").alias("b"))))


def _mark(links: DataFrame) -> tuple:
    return tuple(links.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b") % (1 << 40))).first())


def connected_components(links: DataFrame) -> DataFrame:
    """(a long, b long) -> (node, root): every node of a link with the smallest node that it reaches, itself left out if it is that."""
    now = cut(_rooted(links), "links")
    mark = _mark(now)
    while mark[0]:
        after = cut(_small_star(_large_star(now)), "links")
        seen = _mark(after)
        drop_cut(now)
        now = after
        if seen == mark:
            break
        mark = seen
    return now.select(F.col("a").alias("node"), F.col("b").alias("root"))
