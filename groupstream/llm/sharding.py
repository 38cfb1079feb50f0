"""Sharding by sampled splitters (DataFrame operators only).

A size-weighted sample of keys gives quantile boundaries; the rows are range-partitioned by them, and ranges that turn out
overfull are sampled again and subdivided. Exact sums per range then give every range the place of its first byte and row
in the order of keys, so each row's place follows from its range alone: shard = floor(bytes before it * shards / all bytes).
The sample decides how evenly the work is dealt, never the result.

A key is (hash of the text, hash of the id). Equal texts stand side by side and mostly share a shard, but a group that
holds a large part of all rows is split by the id's hash like any other range.

Cases: a null text counts as empty; null ids hash as the empty string; rows equal in text and id are interchangeable;
an empty table gives an empty result; other columns are kept, and columns named like the results are replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, md5_bits

#: Sampled keys for each range, bytes that a range should hold, and bounds of the number of ranges.
SAMPLES, RANGE_BYTES, RANGES = 16, 128 << 20, (256, 8192)
OVERFULL, SPLITS = 4, 3


def _range_of(bounds: list[tuple[int, int]]) -> Column:
    """How many of the sorted bounds are at or below the row's key, by bisection."""
    if not bounds:
        return F.lit(0)
    first, second = (F.array(*[F.lit(b[i]).cast("long") for b in bounds]) for i in (0, 1))
    step, steps = 1, []
    while step <= len(bounds):
        steps, step = [step, *steps], step * 2

    def go(at: Column, by: Column) -> Column:
        x, y = F.get(first, at + by - 1), F.get(second, at + by - 1)
        below = (x < F.col("__k1")) | ((x == F.col("__k1")) & (y <= F.col("__k2")))
        return F.when((at + by <= len(bounds)) & below, at + by).otherwise(at)

    return F.aggregate(F.array(*[F.lit(s) for s in steps]), F.lit(0), go)


def _splitters(keyed: DataFrame, rate: float, every: int) -> list[tuple[int, int]]:
    """Every so many-th key of a sample that takes a byte with probability rate."""
    u = md5_bits(F.concat_ws("|", F.lit("sample"), "__k1", "__k2"), 13) / F.lit(float(1 << 52))
    sample = keyed.where(u < F.col("__size") * F.lit(rate)).select("__k1", "__k2")
    ranked = sample.withColumn("n", F.row_number().over(Window.orderBy("__k1", "__k2")))
    return sorted({(r[0], r[1]) for r in ranked.where(F.col("n") % every == 0).select("__k1", "__k2").collect()})


def _loads(keyed: DataFrame, bounds: list[tuple[int, int]]) -> list[tuple[int, int, int]]:
    """(range, bytes, rows): as many as there are ranges, whatever the number of rows."""
    return sorted(tuple(r) for r in keyed.select(_range_of(bounds).alias("r"), "__size").groupBy("r").agg(F.sum("__size"), F.count(F.lit(1))).collect())


def place(df: DataFrame, size: Column, text: str = "text", id_column: str = "doc_id", n_shards: int = 16, ranges: tuple[int, int] = RANGES) -> DataFrame:
    """df with size, shard (0 to n_shards - 1, near equal in bytes) and slot (0, 1, ... inside its shard)."""
    hashed = {"__k1": md5_bits(F.coalesce(F.col(text), F.lit(""))), "__k2": md5_bits(F.coalesce(F.col(id_column).cast("string"), F.lit(""))), "__size": size.cast("long")}
    return place_keyed(df.withColumns(hashed), n_shards, ranges)


def place_keyed(keyed: DataFrame, n_shards: int, ranges: tuple[int, int] = RANGES) -> DataFrame:
    """The same for rows that have __k1, __k2 and __size (positive) already."""
    spark = keyed.sparkSession
    keep = [c for c in keyed.columns if c not in ("__k1", "__k2", "__size", "size", "shard", "slot")]
    total = keyed.agg(F.sum("__size")).first()[0] or 0
    n = min(ranges[1], max(ranges[0], total // RANGE_BYTES))
    bounds = _splitters(keyed, SAMPLES * n / total, SAMPLES) if total else []
    loads = _loads(keyed, bounds)
    for _ in range(SPLITS):
        full = [r for r, b, rows in loads if b > OVERFULL * total / n and rows > 1]
        if not full:
            break
        inside = keyed.where(_range_of(bounds).isin(full))
        more = sorted({*bounds, *_splitters(inside, SAMPLES * n / total, SAMPLES // 2)})
        if more == bounds or len(more) >= 2 * ranges[1]:
            break
        bounds, loads = more, _loads(keyed, more)
    starts, at_byte, at_row = [], 0, 0
    for r, size, rows in loads:
        starts.append((r, at_byte, at_row))
        at_byte, at_row = at_byte + size, at_row + rows
    offsets = F.broadcast(spark.createDataFrame(starts, "__r int, __byte long, __row long"))
    inside = Window.partitionBy("__r").orderBy("__k1", "__k2", "__size").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = keyed.withColumn("__r", _range_of(bounds).cast("int")).withColumns({"__bytes": F.sum("__size").over(inside) - F.col("__size"), "__place": F.row_number().over(Window.partitionBy("__r").orderBy("__k1", "__k2", "__size")) - 1})
    rows = rows.join(offsets, "__r").withColumns({"__at": F.col("__row") + F.col("__place"), "shard": F.floor((F.col("__byte") + F.col("__bytes")) * n_shards / F.lit(max(total, 1))).cast("int")})
    first = F.broadcast(rows.groupBy("shard").agg(F.min("__at").alias("__first")))
    return rows.join(first, "shard").select(*keep, F.col("__size").alias("size"), "shard", (F.col("__at") - F.col("__first")).alias("slot"))


def query(spark, sf_dir):
    from .common import table

    text = F.coalesce(F.col("text"), F.lit(""))
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    slim = docs.select(
        "doc_id",
        F.crc32(text).alias("text_crc32"),
        md5_bits(text).alias("__k1"),
        md5_bits(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))).alias("__k2"),
        (F.octet_length(text) + 1).cast("long").alias("__size"),
    )
    placed = place_keyed(cut(slim, "shard-keys"), 16)
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
