"""Searching the index: batches of items, directory probes, two-way scans, and the exhaustive and tree-keyed baselines."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..encoder.relevance import relevance, top_k
from ..functions.hashing import universal_hash
from ..functions.linalg import dot
from ..operators.joins import WINDOW_ROWS, asof
from ..sources.storage import settle
from . import exhaustive
from .blocks import PRIME, A, B


def entry_budget(b: int, d: int) -> int:
    """Entries that a scan may read: four blocks of b vector components."""
    return math.ceil(4 * b / d)


def cluster_items(items: DataFrame) -> DataFrame:
    """(z, items, n): items with equal keys share one probe."""
    return items.groupBy("z").agg(F.sort_array(F.collect_list("v")).alias("items"), F.count("*").alias("n"))


def probe(clusters: DataFrame, directory: DataFrame, buckets: int, on_miss: str = "nearest", a: int = A, b: int = B, p: int = PRIME, width: int = 1 << 20) -> DataFrame:
    """(z, pos, steps, miss): where each key's run starts. steps counts the chain entries that were read.

    on_miss: 'nearest' takes the last key before (else the first after), 'skip' drops the cluster.
    """
    keys = clusters.select("z").withColumn("bucket", universal_hash(F.col("z"), a, b, p, buckets))
    chain = directory.select("bucket", "key", "pos", "chain_no")
    hits = keys.join(chain, "bucket").where("key = z").select("z", "pos", F.col("chain_no").alias("steps"), F.lit(False).alias("miss"))
    if on_miss == "skip":
        return hits
    lost = keys.join(hits.select("z"), "z", "left_anti").select("z")
    near = asof(lost, directory.select("key", "pos"), "z", "key", width, nearest=True)
    return hits.unionByName(near.where("at is not null").select("z", F.col("at.pos").alias("pos"), F.lit(0).alias("steps"), F.lit(True).alias("miss")))


def tree_probe(clusters: DataFrame, blocks: DataFrame, width: int = 1 << 20) -> DataFrame:
    """(z, pos) by ordered search on the sorted keys instead of the directory."""
    first = blocks.groupBy("z").agg(F.min("pos").alias("pos")).withColumnRenamed("z", "key")
    return asof(clusters.select("z"), first, "z", "key", width, nearest=True).where("at is not null").select("z", F.col("at.pos").alias("pos"))


def scan(probes: DataFrame, blocks: DataFrame, budget: int, rows_per_block: int) -> DataFrame:
    """(z, g, vec, pos, step): entries around each place, right and left in turn, until the budget is used.

    The places that an alternating scan can touch lie within budget of its start, so the scan is a join on block numbers
    with a bound on the distance. At an end of the list the other side goes on.
    """
    lo, hi = F.greatest(F.col("start") - budget, F.lit(0)), F.col("start") + budget
    touched = F.sequence(F.floor(lo / rows_per_block), F.floor(hi / rows_per_block))
    asked = probes.select("z", F.col("pos").alias("start")).withColumn("block", F.explode(touched))
    rows = asked.join(blocks.select("block", "pos", "g", "vec"), "block")
    away = F.col("pos") - F.col("start")
    rows = rows.where(F.abs(away) <= budget).withColumn("away", away)
    turn = F.when(F.col("away") >= 0, 2 * F.col("away")).otherwise(-2 * F.col("away") - 1)
    step = F.row_number().over(Window.partitionBy("z").orderBy(turn, "pos"))
    return rows.withColumn("step", step).where(F.col("step") <= budget).select("z", "g", "vec", "pos", "step")


def rank(candidates: DataFrame, items: DataFrame, k: int, d: int) -> DataFrame:
    """(v, rank, g, score): exact scores of each item's candidates."""
    rows = items.select("z", "v", F.col("vec").alias("iv")).join(candidates.select("z", "g", F.col("vec").alias("gv")), "z")
    return top_k(rows.select("v", "g", dot(F.col("iv"), F.col("gv"), d).alias("score")), k)


def reach(start: np.ndarray, n: int, budget: int) -> tuple[np.ndarray, np.ndarray]:
    """The first place and the end of what an alternating scan from each start reads of n places: it is one run of them."""
    left = np.minimum(start, budget // 2)
    right = np.minimum(n - start, budget - left)
    left = np.minimum(start, budget - right)
    return start - left, start + right


def best_around(probes: DataFrame, blocks: DataFrame, items: DataFrame, budget: int, k: int) -> DataFrame:
    """What rank says of scan's entries, without a row for each of them: (v, rank, g, score).

    The places that a scan reads are a run, so every task holds a window of items with their runs, goes through its own
    entries, and sends on no more than an item's first k.
    """
    asked = settle(items.select("z", "v", "vec").join(probes.select("z", "pos"), "z").select("v", "vec", "pos"), "places")
    n, windows, out = blocks.count(), max(1, -(-asked.count() // WINDOW_ROWS)), None
    for w in range(windows):
        some = asked if windows == 1 else asked.where(F.pmod(F.xxhash64("v"), F.lit(windows)) == w)
        found = _around(blocks, some.collect(), n, budget, k)  # about WINDOW_ROWS rows
        out = found if out is None else out.unionByName(found)
    return top_k(out, k)


def _around(blocks: DataFrame, items: list, n: int, budget: int, k: int) -> DataFrame:
    layout = "v long, g long, score double"
    if not items:
        return blocks.sparkSession.createDataFrame([], layout)
    names, matrix = np.array([r["v"] for r in items], np.int64), np.array([r["vec"] for r in items], np.float64)
    first, end = reach(np.array([r["pos"] for r in items], np.int64), n, budget)

    def run(batches):
        best = exhaustive.Best(matrix, k)
        for b in batches:
            if len(b):
                b = b.sort_values("pos")
                best.add_within(b["pos"].to_numpy(np.int64), b["g"].to_numpy(np.int64), np.array(b["vec"].tolist(), np.float64), first, end)
        for item, g, score in best.rows():
            yield pd.DataFrame({"v": names[item], "g": g, "score": score})

    return blocks.select("pos", "g", "vec").mapInPandas(run, layout)


def batch_match(groups: DataFrame, items: DataFrame, k: int, d: int) -> DataFrame:
    """The exhaustive baseline: every item against every group. Of many items against few groups, all pairs are ranked by
    columns; else each task sends on no more than an item's first k."""
    n = items.count()
    if n > WINDOW_ROWS and groups.limit(WINDOW_ROWS + 1).count() <= WINDOW_ROWS:
        return top_k(relevance(groups, items, d), k)
    return exhaustive.top_k(groups, items, k, n)
