"""As-of, interval and salted joins, and positions in a total order without a window over everything."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.storage import settle


#: The most rows that a side of a join may be sent to every task with: a window of items, not a table.
WINDOW_ROWS = 1 << 16


def bounded(rows: DataFrame, most: int = WINDOW_ROWS) -> DataFrame:
    """rows, marked for a broadcast if they are few enough; else unmarked, and Spark chooses the join."""
    return F.broadcast(rows) if rows.limit(most + 1).count() <= most else rows


def asof(left: DataFrame, right: DataFrame, left_key: str, right_key: str, width: int, nearest: bool = False) -> DataFrame:
    """left with the right row at or before its key (with `nearest`: else the first one after it), as a struct column 'at'.

    Keys are cut into ranges of `width`. Each range's last right row is carried to the next ranges over one row per
    range, SPANS ranges in a task and then one row for each such span, so rows of different ranges are worked on apart and no
    task sees all ranges. Equal right keys: the smallest row counts.
    """
    cell = lambda k: F.floor(F.col(k) / width)
    value = F.struct(F.col(right_key), *[F.col(c) for c in right.columns if c != right_key])
    known = right.groupBy(right_key).agg(F.min(value).alias("at")).select(F.col(right_key).alias("k"), "at").withColumn("cell", cell("k"))
    asked = left.withColumn("cell", cell(left_key))
    ends = known.groupBy("cell").agg(F.max_by("at", "k").alias("last"), F.min_by("at", "k").alias("first"))
    cells = ends.join(asked.select("cell").distinct(), "cell", "full_outer")
    cells = cells.withColumn("span", F.floor(F.col("cell") / SPANS))
    spans = cells.groupBy("span").agg(F.max_by("last", F.when(F.col("last").isNotNull(), F.col("cell"))).alias("last"), F.min_by("first", F.when(F.col("first").isNotNull(), F.col("cell"))).alias("first"))
    far = _around(spans, Window.orderBy("span"))  # one row for SPANS ranges
    far = far.withColumnsRenamed({"carry": "far_carry", "next": "far_next"})
    near = _around(cells, Window.partitionBy("span").orderBy("cell")).join(far.select("span", "far_carry", "far_next"), "span")
    carried = near.select("cell", F.coalesce("carry", "far_carry").alias("carry"), F.coalesce("next", "far_next").alias("next"))
    marks = known.select("cell", F.col("k").alias("__k"), F.lit(0).alias("__side"), "at", *[F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns])
    rows = asked.select("cell", F.col(left_key).alias("__k"), F.lit(1).alias("__side"), F.lit(None).cast(known.schema["at"].dataType).alias("at"), *left.columns)
    order = Window.partitionBy("cell").orderBy("__k", "__side")
    both = marks.unionByName(rows).withColumns({"prev": F.last("at", True).over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow)), "succ": F.first("at", True).over(order.rowsBetween(0, Window.unboundedFollowing))})
    out = both.where("__side = 1").join(carried, "cell")
    found = F.coalesce("prev", "carry", "succ", "next") if nearest else F.coalesce("prev", "carry")
    return out.select(*left.columns, found.alias("at"))


SPANS = 4096


def _around(rows: DataFrame, order) -> DataFrame:
    """rows with carry, the last known `last` before each, and next, the first known `first` after it."""
    before, after = order.rowsBetween(Window.unboundedPreceding, -1), order.rowsBetween(1, Window.unboundedFollowing)
    return rows.withColumns({"carry": F.last("last", True).over(before), "next": F.first("first", True).over(after)})


def salted_join(left: DataFrame, right: DataFrame, keys: list[str], n: int, how: str = "inner") -> DataFrame:
    """A join whose left keys are dealt over n salts, and whose right rows are repeated for each: for hot keys that the
    adaptive join cannot split."""
    salted = left.withColumn("__salt", F.pmod(F.xxhash64(*left.columns), F.lit(n)).cast("int"))
    spread = right.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(n - 1))))
    return salted.join(spread, [*keys, "__salt"], how).drop("__salt")


def interval_join(left: DataFrame, right: DataFrame, key: str, left_at: str, right_at: str, low: int, high: int) -> DataFrame:
    """Pairs of one key whose right time lies in [left time + low, left time + high]: equal time windows, then the rest."""
    width = max(1, high - low)
    first, last = F.floor((F.col(left_at) + low) / width), F.floor((F.col(left_at) + high) / width)
    spread = left.withColumn("__w", F.explode(F.sequence(first, last)))
    near = right.withColumn("__w", F.floor(F.col(right_at) / width))
    return spread.join(near, [key, "__w"]).where((F.col(right_at) - F.col(left_at)).between(low, high)).drop("__w")


def positions(rows: DataFrame, order: list[str], name: str = "pos") -> DataFrame:
    """rows with their place in a total order: range partitions, a count for each, and numbers inside them.

    The ranges are written out first, since a second sampling could draw them differently. Only one count per partition
    reaches the driver.
    """
    ranged = settle(rows.repartitionByRange(*order).withColumn("__part", F.spark_partition_id()), "ranged")
    counts = sorted((r["__part"], r["count"]) for r in ranged.groupBy("__part").count().collect())
    starts, at = [], 0
    for part, n in counts:
        starts.append((part, at))
        at += n
    offsets = F.broadcast(rows.sparkSession.createDataFrame(starts, "__part int, __start long"))
    inside = F.row_number().over(Window.partitionBy("__part").orderBy(*order)) - 1
    return ranged.withColumn("__n", inside).join(offsets, "__part").select(*rows.columns, (F.col("__start") + F.col("__n")).alias(name))


def top_n(rows: DataFrame, by: list[str], order: list[Column], n: int) -> DataFrame:
    """The first n rows of each key; Spark limits each group before the shuffle."""
    return rows.withColumn("__n", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col("__n") <= n).drop("__n")
