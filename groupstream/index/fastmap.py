"""From inner products to few coordinates: distances that keep the order of scores, pivots, and FastMap projections.

Up to EXPRESSIONS axes are column expressions. Every coordinate needs all before it, so their size doubles with each axis;
more axes are worked out in Arrow batches.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.linalg import dot, norm

EXPRESSIONS = 3


def to_distance(groups: DataFrame, items: DataFrame, d: int, mode: str = "mips") -> tuple[DataFrame, DataFrame]:
    """Vectors whose Euclidean distance stands for relevance.

    mips: groups get the component that brings all of them to the longest one's length, items get a zero and are scaled to
    that length, which changes no order; then a higher inner product is a smaller distance. euclid: the vectors as they are.
    """
    if mode == "euclid":
        return groups.select("g", "vec"), items.select("v", "vec")
    longest = F.broadcast(groups.agg(F.max(norm(F.col("vec"), d)).alias("longest")))
    rest = F.sqrt(F.greatest(F.col("longest") * F.col("longest") - dot(F.col("vec"), F.col("vec"), d), F.lit(0.0)))
    return groups.join(longest).select("g", F.concat("vec", F.array(rest)).alias("vec")), items.join(longest).select("v", scaled(F.col("longest"), d))


def scaled(length: Column, d: int) -> Column:
    """An item's vector at the given length (zero stays zero), with the zero that completes it."""
    own = norm(F.col("vec"), d)
    return F.when(own > 0, F.concat(F.transform("vec", lambda x: x * (length / own)), F.array(F.lit(0.0)))).otherwise(F.concat("vec", F.array(F.lit(0.0)))).alias("vec")


def square(a: Column, b: Column, d: int) -> Column:
    total = F.lit(0.0)
    for i in range(d):
        gap = F.get(a, F.lit(i)) - F.get(b, F.lit(i))
        total = total + gap * gap
    return total


def _literal(vec) -> Column:
    return F.array(*[F.lit(float(x)) for x in vec])


def _residual(vec: Column, coords: list[Column], pivot: dict, d: int) -> Column:
    """Squared distance to a pivot, less what the earlier coordinates explain."""
    out = square(vec, _literal(pivot["vec"]), d)
    for c, own in zip(coords, pivot["coords"]):
        out = out - (c - F.lit(own)) * (c - F.lit(own))
    return F.greatest(out, F.lit(0.0))


def _coordinates(vec: Column, pivots: list[dict], d: int, variant: str) -> list[Column]:
    made: list[Column] = []
    for axis in pivots:
        first, second = _residual(vec, made, axis["x"], d), _residual(vec, made, axis["y"], d)
        if variant == "printed":
            value = (first + F.lit(axis["gap"] ** 2) - F.sqrt(second)) / F.lit(2 * axis["gap"])
        else:
            value = (first + F.lit(axis["gap"] ** 2) - second) / F.lit(2 * axis["gap"])
        made.append(value)
    return made


def coordinates(x: np.ndarray, pivots: list[dict], variant: str = "standard") -> np.ndarray:
    """The coordinates of the rows of a matrix."""
    made = np.zeros((len(x), len(pivots)))
    for i, axis in enumerate(pivots):
        first, second = (residual(x, made[:, :i], axis[k]) for k in "xy")
        made[:, i] = (first + axis["gap"] ** 2 - (np.sqrt(second) if variant == "printed" else second)) / (2 * axis["gap"])
    return made


def residual(x: np.ndarray, made: np.ndarray, end: dict) -> np.ndarray:
    """Squared distances to a pivot, less what the coordinates so far explain."""
    gap = ((x - np.array(end["vec"])) ** 2).sum(1) - ((made - np.array(end["coords"][: made.shape[1]])) ** 2).sum(1)
    return np.maximum(gap, 0.0)


def _farthest(groups: DataFrame, pivots: list[dict], here: dict, d: int):
    """The group (g, vec, away) farthest from `here` beyond what the axes so far explain, ties to the smaller id."""
    if len(pivots) < EXPRESSIONS:
        away = F.round(_residual(F.col("vec"), _coordinates(F.col("vec"), pivots, d, "standard"), here, d), 9)
        return groups.withColumn("away", away).orderBy(F.desc("away"), "g").limit(1).collect()[0]

    def run(batches):
        for b in batches:
            if len(b):
                x = np.array(b["vec"].tolist())
                away = np.round(residual(x, coordinates(x, pivots), here), 9)
                at = np.lexsort((b["g"].to_numpy(), -away))[:1]
                yield b.iloc[at].assign(away=away[at])

    best = groups.select("g", "vec").mapInPandas(run, "g long, vec array<double>, away double")
    return best.orderBy(F.desc("away"), "g").limit(1).collect()[0]


def choose_pivots(groups: DataFrame, axes: int, d: int) -> list[dict]:
    """For each axis two far apart groups: the farthest from the smallest id, then the farthest from that one.

    Each hop brings one row to the driver. An axis along which nothing differs any more ends the list.
    """
    pivots: list[dict] = []
    start = groups.orderBy("g").limit(1).collect()
    if not start:
        return pivots

    def place(row) -> dict:
        """A group with its coordinates on the axes so far."""
        made: list[float] = []
        for axis in pivots:
            ends = []
            for end in (axis["x"], axis["y"]):
                gap = sum((p - q) ** 2 for p, q in zip(row["vec"], end["vec"]))
                ends.append(max(0.0, gap - sum((c - o) ** 2 for c, o in zip(made, end["coords"]))))
            made.append((ends[0] + axis["gap"] ** 2 - ends[1]) / (2 * axis["gap"]))
        return {"g": row["g"], "vec": list(row["vec"]), "coords": made}

    for _ in range(axes):
        here = place(start[0])
        for hop in range(2):
            far = _farthest(groups, pivots, here, d)
            if hop == 0:
                first = here = place(far)
            else:
                gap = far["away"] ** 0.5
        if gap <= 1e-9:
            break
        pivots.append({"x": first, "y": place(far), "gap": gap})
    return pivots


def project(rows: DataFrame, pivots: list[dict], d: int, variant: str = "standard") -> DataFrame:
    """rows with xs, their coordinates. 'printed' leaves one of the three distances unsquared."""
    if len(pivots) > EXPRESSIONS:
        layout = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in rows.schema)

        def run(batches):
            for b in batches:
                yield b.assign(xs=list(coordinates(np.array(b["vec"].tolist()).reshape(len(b), -1), pivots, variant)) if len(b) else pd.Series(dtype=object))

        return rows.mapInPandas(run, f"{layout}, xs array<double>")
    made = rows
    for i in range(len(pivots)):
        earlier = [F.col(f"__x{j}") for j in range(i)]
        axis = pivots[i]
        first, second = _residual(F.col("vec"), earlier, axis["x"], d), _residual(F.col("vec"), earlier, axis["y"], d)
        last = F.sqrt(second) if variant == "printed" else second
        made = made.withColumn(f"__x{i}", (first + F.lit(axis["gap"] ** 2) - last) / F.lit(2 * axis["gap"]))
    return made.select(*rows.columns, F.array(*[F.col(f"__x{i}") for i in range(len(pivots))]).alias("xs"))
