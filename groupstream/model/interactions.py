"""Group-item interactions over time: cumulative or new, split by time and cut into slices."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.tables import Tables
from .groups import home_groups, memberships

SLICES, TRAIN = 4, 0.8


def group_lines(tables: Tables, family: str = "market") -> DataFrame:
    """(g, v, day, price): a member's purchase counts for the group."""
    lines = tables.lines()
    if family == "market":
        return lines.select((F.col("s") * 25 + F.col("nk")).alias("g"), "v", "day", "price")
    owner = home_groups(tables) if family == "home" else memberships(tables, family).select("g", "u")
    return lines.join(owner, "u").select("g", "v", "day", "price")


def group_interactions(lines: DataFrame) -> DataFrame:
    """(g, v, n, first_day, last_day)."""
    return lines.groupBy("g", "v").agg(F.count("*").alias("n"), F.min("day").alias("first_day"), F.max("day").alias("last_day"))


def upto(lines: DataFrame, at: int) -> DataFrame:
    return lines.where(F.col("day") <= at)


def fresh(lines: DataFrame, after: int, until: int) -> DataFrame:
    return lines.where((F.col("day") > after) & (F.col("day") <= until))


def chrono_split(lines: DataFrame, share: float = TRAIN, slices: int = SLICES, approximate: bool = False) -> DataFrame:
    """lines with split ('train' or 'test', by a quantile of time) and slice (equal intervals of the training part).

    The quantile is one row that joins back; at scale an approximate one keeps the sort out of the plan.
    """
    at = F.percentile_approx("day", share, 100_000).cast("double") if approximate else F.percentile("day", F.lit(share))
    cut = F.broadcast(lines.agg(at.alias("cut"), F.min("day").alias("t0")))
    step = (F.col("cut") - F.col("t0")) / slices
    number = F.least(F.lit(slices - 1), F.floor((F.col("day") - F.col("t0")) / step)).cast("int")
    train = F.col("day") <= F.col("cut")
    split = lines.join(cut)
    return split.select(*lines.columns, F.when(train, "train").otherwise("test").alias("split"), F.when(train, number).alias("slice"))


def item_attributes(sliced: DataFrame) -> DataFrame:
    """(v, slice, bought, popularity so far, average price so far) for each slice in which an item was bought."""
    per = sliced.where("slice is not null").groupBy("v", "slice").agg(F.count("*").alias("bought"), F.sum(F.col("price").cast("decimal(18,2)")).alias("paid"))
    so_far = Window.partitionBy("v").orderBy("slice").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    popularity = F.sum("bought").over(so_far)
    return per.select("v", "slice", "bought", popularity.alias("popularity"), F.round((F.sum("paid").over(so_far).cast("double") / popularity), 8).alias("avg_price"))


def slice_counts(sliced: DataFrame) -> DataFrame:
    """(g, slice, n): new interactions of each group in each slice."""
    return sliced.where("slice is not null").groupBy("g", "slice").agg(F.count("*").alias("n"))
