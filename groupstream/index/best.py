"""Searching the lower level by its blocks' summaries, best first.

A block of neighbours in Z order is a ball: no group in it scores above item.centre + |item| * radius. Each item reads the
blocks whose balls promise most until its budget is used, so neither a place in the order nor a hit in the directory is
needed. Items come in windows of at most WINDOW_ROWS, which every task holds; groups never leave their blocks.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..encoder.relevance import top_k as first_k
from ..operators.joins import WINDOW_ROWS
from ..sources.storage import settle
from .exhaustive import MARGIN, Best

#: How much of its radius a block is given: none ranks it by its middle, all of it by what it could hold at most.
LEAN = 0.5
#: Blocks that are packed together, and items whose promises are counted together.
TOGETHER, CHUNK = 64, 256
#: Blocks that are looked at together, pairs of item and group that are ranked together, bins of promises and how often they are cut.
BLOCKS, PAIRS, BINS, CUTS = 128, 1 << 19, 64, 4
COLUMNS = ["block", "centre", "radius", "n", "ids", "matrix"]
LAYOUT = "block long, centre array<double>, radius double, n long, ids binary, matrix binary"


def pack(blocks: DataFrame) -> DataFrame:
    """(block, centre, radius, n, ids, matrix): one row for each block of (block, g, vec)."""

    def some(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["block", "g"])
        block, ids, x = rows["block"].to_numpy(), rows["g"].to_numpy(np.int64), np.array(rows["vec"].tolist(), np.float64)
        edge = [*np.flatnonzero(np.diff(block, prepend=block[0] - 1)).tolist(), len(block)]
        return pd.DataFrame([_summed(block[a], ids[a:b], x[a:b]) for a, b in zip(edge[:-1], edge[1:])], columns=COLUMNS)

    several = blocks.select("block", "g", "vec", F.floor(F.col("block") / TOGETHER).alias("part")).groupBy("part")
    return several.applyInPandas(some, LAYOUT)


def _summed(block: int, ids: np.ndarray, x: np.ndarray) -> tuple:
    centre = x.mean(0)
    return int(block), centre.tolist(), float(np.sqrt(((x - centre) ** 2).sum(1)).max()), len(x), ids.tobytes(), x.tobytes()


def members(packs: DataFrame) -> DataFrame:
    """(g, block): which block holds each group."""

    def run(batches):
        for b in batches:
            for r in b.itertuples():
                yield pd.DataFrame({"g": np.frombuffer(r.ids, np.int64), "block": r.block})

    return packs.select("block", "ids").mapInPandas(run, "g long, block long")


def update(packs: DataFrame, held: DataFrame, changed: DataFrame, rows_per_block: int) -> tuple[DataFrame, DataFrame]:
    """packs and held, their members (g, block), after some groups (g, vec) changed or came.

    A changed group leaves its block and enters the one with the nearest centre. Only blocks that lose or gain one are
    worked out anew; a block of more than twice the rows is halved along its widest component.
    """
    changed = changed.select("g", "vec")
    rows = changed.limit(WINDOW_ROWS + 1).collect()
    if len(rows) > WINDOW_ROWS:
        raise ValueError(f"more than {WINDOW_ROWS} groups at once: update in parts, or build the index anew")
    if not rows:
        return packs, held
    gone, points = np.array([r["g"] for r in rows], np.int64), np.array([r["vec"] for r in rows], np.float64)

    def nearest(batches):
        for b in batches:
            if len(b):
                away = ((points[:, None, :] - np.array(b["centre"].tolist())[None, :, :]) ** 2).sum(2)
                at = away.argmin(1)
                yield pd.DataFrame({"i": np.arange(len(points)), "block": b["block"].to_numpy()[at], "away": away[np.arange(len(points)), at]})

    goes = packs.select("block", "centre").mapInPandas(nearest, "i long, block long, away double").groupBy("i").agg(F.min_by("block", F.struct("away", "block")).alias("block"))
    goes = settle(goes.groupBy("block").agg(F.collect_list("i").alias("come")), "come")
    touched = settle(goes.select("block").unionByName(held.join(changed.select("g"), "g", "left_semi").select("block")).distinct(), "touched")

    def anew(batches):
        for b in batches:
            out = []
            for r in b.itertuples():
                ids = np.frombuffer(r.ids, np.int64)
                x = np.frombuffer(r.matrix).reshape(len(ids), -1)
                stay = ~np.isin(ids, gone)
                come = np.array(r.come if r.come is not None else [], np.int64)
                ids, x = np.append(ids[stay], gone[come]), np.vstack([x[stay], points[come]])
                if len(ids) > 2 * rows_per_block:
                    order = np.argsort(x[:, int(np.argmax(np.ptp(x, axis=0)))], kind="stable")
                    half = len(ids) // 2
                    new = int(np.bitwise_xor.reduce(ids[order[half:]] * np.int64(0x9E3779B97F4A7C1)) & np.int64((1 << 62) - 1)) | 1 << 61
                    out += [_summed(r.block, ids[order[:half]], x[order[:half]]), _summed(new, ids[order[half:]], x[order[half:]])]
                elif len(ids):
                    out.append(_summed(r.block, ids, x))
            yield pd.DataFrame(out, columns=COLUMNS)

    mine = packs.join(touched, "block", "left_semi").join(goes, "block", "left").select(*COLUMNS, "come")
    fresh = settle(mine.mapInPandas(anew, LAYOUT), "packs")
    kept = packs.join(touched, "block", "left_anti").select(*COLUMNS)
    return kept.unionByName(fresh), held.join(touched, "block", "left_anti").select("g", "block").unionByName(members(fresh))


def _promise(items: np.ndarray, length: np.ndarray, centre: np.ndarray, radius: np.ndarray, lean: float) -> np.ndarray:
    """A row for each block: what it promises each item."""
    return centre @ items.T + lean * radius[:, None] * length[None, :]


def bars(packs: DataFrame, items: np.ndarray, most: int, lean: float = LEAN) -> np.ndarray:
    """For each item what a block has to promise to be among its `most` first; -inf where there are no more blocks.

    Blocks are counted by promise in a few bins for each item, and the bin that holds the last one is cut again, so neither
    blocks nor their promises leave a task. Blocks within 1 / BINS ** CUTS of the last one's promise are read as well.
    """
    length = np.sqrt((items**2).sum(1))
    size = F.sqrt(F.aggregate("centre", F.lit(0.0), lambda s, x: s + x * x))
    far, wide = packs.agg(F.max(size), F.max("radius")).first()
    top = length * ((far or 0.0) + abs(lean) * (wide or 0.0)) * (1 + 1e-9) + 1e-9
    low, high, left = -top, top.copy(), np.full(len(items), most, np.int64)

    def cut(low, high):
        scale = BINS / (high - low)

        def count(batches):
            counts = np.zeros((len(items), BINS), np.int64)
            for b in batches:
                centre, radius = np.array(b["centre"].tolist()).reshape(len(b), -1), b["radius"].to_numpy(np.float64)
                for at in range(0, len(b), BLOCKS):
                    for c in range(0, len(items), CHUNK):
                        here = slice(c, c + CHUNK)
                        score = _promise(items[here], length[here], centre[at : at + BLOCKS], radius[at : at + BLOCKS], lean)
                        place = np.floor((score - low[here]) * scale[here])
                        inside = (place >= 0) & (place < BINS)
                        place += np.arange(score.shape[1]) * BINS
                        counts[here] += np.bincount(place[inside].astype(np.int64), minlength=score.shape[1] * BINS).reshape(-1, BINS)
            for c in range(0, len(items), CHUNK):
                yield pd.DataFrame({"chunk": [c], "counts": [counts[c : c + CHUNK].tobytes()]})

        def total(rows):
            return pd.DataFrame({"chunk": [int(rows["chunk"].iloc[0])], "counts": [sum(np.frombuffer(x, np.int64) for x in rows["counts"]).tobytes()]})

        found = packs.select("centre", "radius").mapInPandas(count, "chunk long, counts binary").groupBy("chunk").applyInPandas(total, "chunk long, counts binary").collect()
        return np.concatenate([np.frombuffer(r["counts"], np.int64) for r in sorted(found, key=lambda r: r["chunk"])]).reshape(-1, BINS)  # a few numbers an item

    enough = None
    for _ in range(CUTS):
        down = cut(low, high)[:, ::-1].cumsum(1)
        enough = down[:, -1] >= left if enough is None else enough
        at = np.minimum((down < left[:, None]).sum(1), BINS - 1)  # bins from the top
        left = np.maximum(1, left - np.where(at > 0, np.take_along_axis(down, np.maximum(at - 1, 0)[:, None], 1)[:, 0], 0))
        step = (high - low) / BINS
        low, high = high - (at + 1) * step, high - at * step
    return np.where(enough, low - 1e-12 * (1 + top), -np.inf)


def top_k(packs: DataFrame, items: DataFrame, k: int, budget: int, rows_per_block: int, lean: float = LEAN) -> DataFrame:
    """(v, rank, g, score): exact scores of all groups in the chosen blocks."""
    items = items.select("v", "vec")
    windows, out = max(1, -(-items.count() // WINDOW_ROWS)), None
    for w in range(windows):
        some = items if windows == 1 else items.where(F.pmod(F.xxhash64("v"), F.lit(windows)) == w)
        found = _window(packs, some.collect(), k, max(1, -(-budget // rows_per_block)), lean)  # about WINDOW_ROWS rows
        out = found if out is None else out.unionByName(found)
    return first_k(out, k)


def _window(packs: DataFrame, items: list, k: int, most: int, lean: float) -> DataFrame:
    """Each task goes through its blocks, scores them for the items that read them, and sends on an item's first k only."""
    layout = "v long, g long, score double"
    if not items or packs.isEmpty():
        return packs.sparkSession.createDataFrame([], layout)
    names, matrix = np.array([r["v"] for r in items], np.int64), np.array([r["vec"] for r in items], np.float64)
    bar, length = bars(packs, matrix, most, lean), np.sqrt((matrix**2).sum(1))

    def score(batches):
        best, held, n = Best(matrix, k), [], 0
        for b in batches:
            centre, radius = np.array(b["centre"].tolist()).reshape(len(b), -1), b["radius"].to_numpy(np.float64)
            for at in range(0, len(b), BLOCKS):
                reads = _promise(matrix, length, centre[at : at + BLOCKS], radius[at : at + BLOCKS], lean) >= bar
                for i, asked in enumerate(reads, at):
                    ids = np.frombuffer(b["ids"].iloc[i], np.int64)
                    points = np.frombuffer(b["matrix"].iloc[i]).reshape(len(ids), -1)
                    slack = MARGIN * (1 + float(np.sqrt((points**2).sum(1)).max()) * length)
                    low, item = best.scores[:, -1] - slack, np.flatnonzero(asked)
                    for c in range(0, len(item), PAIRS // len(ids) + 1):
                        some = item[c : c + PAIRS // len(ids) + 1]
                        row, col = np.nonzero(matrix[some] @ points.T >= low[some, None])
                        held.append((some[row], ids[col], points[col]))
                        n += len(row)
                        if n >= PAIRS:
                            best._merge(*(np.concatenate(x) for x in zip(*held)))
                            held, n = [], 0
        if n:
            best._merge(*(np.concatenate(x) for x in zip(*held)))
        for item, g, s in best.rows():
            yield pd.DataFrame({"v": names[item], "g": g, "score": s})

    return packs.select("centre", "radius", "ids", "matrix").mapInPandas(score, layout)
