"""Groups of users. A family says what makes a group; memberships hold who belongs, since when and until when.

home: customers of one nation and market segment (disjoint). taste: buyers of at least `min_lines` lines of one brand and
type. market: customers of one nation who buy from one supplier.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.tables import Tables

FAMILIES = ("home", "taste", "market")


def home_groups(tables: Tables) -> DataFrame:
    """(u, g): every customer's group."""
    segments = tables.customer.select("c_mktsegment").distinct().withColumn("k", F.dense_rank().over(Window.orderBy("c_mktsegment")) - 1)  # a handful of segments
    users = tables.customer.join(F.broadcast(segments), "c_mktsegment")
    return users.select(F.col("c_custkey").alias("u"), (F.col("c_nationkey") * 5 + F.col("k")).cast("long").alias("g"))


def memberships(tables: Tables, family: str = "market", min_lines: int = 2) -> DataFrame:
    """(g, u, first_day, last_day, n), one row for each member."""
    lines = tables.lines()
    span = (F.min("day").alias("first_day"), F.max("day").alias("last_day"))
    if family == "home":
        active = lines.groupBy("u").agg(*span, F.count("*").alias("n"))
        return home_groups(tables).join(active, "u", "left").select("g", "u", "first_day", "last_day", F.coalesce("n", F.lit(0)).cast("long").alias("n"))
    if family == "market":
        return lines.groupBy((F.col("s") * 25 + F.col("nk")).alias("g"), "u").agg(*span, F.count("*").alias("n"))
    if family == "taste":
        kinds = tables.part.select("p_brand", "p_type").distinct().withColumn("g", (F.dense_rank().over(Window.orderBy("p_brand", "p_type")) - 1).cast("long"))  # brands times types
        items = tables.part.join(F.broadcast(kinds), ["p_brand", "p_type"]).select(F.col("p_partkey").alias("v"), "g")
        return lines.join(items, "v").groupBy("g", "u").agg(*span, F.count("*").alias("n")).where(F.col("n") >= min_lines)
    raise ValueError(f"family is one of {FAMILIES}")


def members_at(members: DataFrame, at: int, idle: int | None = None) -> DataFrame:
    """Who belongs on a day: joined by then and, with `idle`, seen in the so many days before it."""
    rows = members.where(F.col("first_day") <= at)
    return rows if idle is None else rows.where(F.col("last_day") >= at - idle)
