"""Locality-sensitive cells of coordinates, and their bits interleaved to one key in Z order."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.linalg import matvec


def directions(n_hash: int, axes: int, seed: int = 3) -> tuple[list[list[float]], list[float]]:
    """Random directions and offsets, rounded so that every engine reads the same numbers."""
    rng = np.random.default_rng(seed)
    return np.round(rng.normal(size=(n_hash, axes)), 4).tolist(), np.round(rng.uniform(0, 1, n_hash), 4).tolist()


def fitted(points: DataFrame, a: list[list[float]], bits: int) -> tuple[list[list[float]], list[float]]:
    """Directions and offsets for width 1 under which the projections of points (.., xs) fill all 2**bits cells of each hash."""
    top = 1 << bits
    value = matvec(a, F.col("xs"))
    ends = points.agg(*[f(F.get(value, F.lit(i))).alias(f"{f.__name__}{i}") for i in range(len(a)) for f in (F.min, F.max)]).first()
    low = [ends[f"min{i}"] or 0.0 for i in range(len(a))]
    scale = [top / max((ends[f"max{i}"] or 0.0) - x, 1e-12) for i, x in enumerate(low)]
    return [[x * s for x in row] for row, s in zip(a, scale)], [-x * s - (top >> 1) for x, s in zip(low, scale)]


def hash_axes(points: DataFrame, a: list[list[float]], b: list[float], width: float, bits: int) -> DataFrame:
    """points (.., xs) with cells: floor(a.x / width + b), moved to the middle of [0, 2**bits) and clipped to it."""
    half, top = 1 << (bits - 1), (1 << bits) - 1
    scaled = [[x / width for x in row] for row in a]
    cells = F.transform(matvec(scaled, F.col("xs"), b), lambda x: F.least(F.greatest(F.floor(F.round(x, 9)) + half, F.lit(0).cast("long")), F.lit(top).cast("long")))
    return points.withColumn("cells", cells)


def interleave(cells: Column, n: int, bits: int) -> Column:
    """The bits of n cells, the most significant first, the first cell's before the others': at most 62 of them."""
    if n * bits > 62:
        raise ValueError("more than 62 bits do not fit into a key")
    key, place = F.lit(0).cast("long"), n * bits
    for bit in range(bits - 1, -1, -1):
        for i in range(n):
            place -= 1
            one = F.shiftright(F.get(cells, F.lit(i)), bit).bitwiseAND(F.lit(1).cast("long"))
            key = key.bitwiseOR(F.shiftleft(one, place))
    return key


def keyed(points: DataFrame, a, b, width: float, bits: int) -> DataFrame:
    """points with their key z."""
    return hash_axes(points, a, b, width, bits).withColumn("z", interleave(F.col("cells"), len(a), bits))
