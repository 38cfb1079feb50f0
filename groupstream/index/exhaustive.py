"""The exhaustive search in blocks: every item of a window against every group, of which only each item's first k leave a task.

Products of whole blocks, with a margin, say which pairs can be among an item's first k; those are then scored component by
component in the order of the column expression, so that scores, ties included, are the ones that it gives.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..encoder.relevance import RANK_DIGITS
from ..encoder.relevance import top_k as first_k
from ..operators.joins import WINDOW_ROWS

#: Items and groups of a block, and how far, relative to the vectors' lengths, a product may be off.
ITEMS, GROUPS, MARGIN = 256, 4096, 1e-9


def top_k(groups: DataFrame, items: DataFrame, k: int, count: int | None = None) -> DataFrame:
    """(v, rank, g, score) of all items (v, vec) against all groups (g, vec). Items come in windows that every task holds."""
    items = items.select("v", "vec")
    windows, out = max(1, -(-(items.count() if count is None else count) // WINDOW_ROWS)), None
    for w in range(windows):
        some = items if windows == 1 else items.where(F.pmod(F.xxhash64("v"), F.lit(windows)) == w)
        found = _window(groups, some.collect(), k)  # about WINDOW_ROWS rows
        out = found if out is None else out.unionByName(found)
    return first_k(out, k)


def _window(groups: DataFrame, items: list, k: int) -> DataFrame:
    layout = "v long, g long, score double"
    if not items:
        return groups.sparkSession.createDataFrame([], layout)
    names, matrix = np.array([r["v"] for r in items], np.int64), np.array([r["vec"] for r in items], np.float64)

    def run(batches):
        best = Best(matrix, k)
        for b in batches:
            if len(b):
                best.add(b["g"].to_numpy(np.int64), np.array(b["vec"].tolist(), np.float64))
        for item, g, score in best.rows():
            yield pd.DataFrame({"v": names[item], "g": g, "score": score})

    return groups.select("g", "vec").mapInPandas(run, layout)


class Best:
    """The k best groups of every item so far: by score, rounded as ranks are, ties to the smaller id."""

    def __init__(self, items: np.ndarray, k: int):
        self.items, self.k = items, k
        self.length = np.sqrt((items**2).sum(1))
        self.ids = np.zeros((len(items), k), np.int64)
        self.scores = np.full((len(items), k), -np.inf)

    def add(self, ids: np.ndarray, x: np.ndarray) -> None:
        for at in range(0, len(ids), GROUPS):
            own, part = ids[at : at + GROUPS], x[at : at + GROUPS]
            slack = MARGIN * (1 + float(np.sqrt((part**2).sum(1)).max()) * self.length)
            for first in range(0, len(self.items), ITEMS):
                here = slice(first, first + ITEMS)
                score = self.items[here] @ part.T
                low = self.scores[here, -1] - slack[here]
                if len(own) > self.k:
                    low = np.maximum(low, np.partition(score, -self.k, axis=1)[:, -self.k] - slack[here]) if np.isinf(low).any() else low
                item, col = np.nonzero(score >= low[:, None])
                if len(item):
                    self._merge(item + first, own[col], part[col])

    def add_within(self, place: np.ndarray, ids: np.ndarray, x: np.ndarray, first: np.ndarray, end: np.ndarray) -> None:
        """Groups at places in ascending order, of which each item counts those from its `first` place on, before its `end`."""
        for at in range(0, len(ids), GROUPS):
            where, own, part = place[at : at + GROUPS], ids[at : at + GROUPS], x[at : at + GROUPS]
            slack = MARGIN * (1 + float(np.sqrt((part**2).sum(1)).max()) * self.length)
            asked = np.flatnonzero((first <= where[-1]) & (end > where[0]))
            for c in range(0, len(asked), ITEMS):
                some = asked[c : c + ITEMS]
                inside = (where >= first[some, None]) & (where < end[some, None])
                score = np.where(inside, self.items[some] @ part.T, -np.inf)
                low = self.scores[some, -1] - slack[some]
                if len(own) > self.k and np.isinf(low).any():
                    low = np.maximum(low, np.partition(score, -self.k, axis=1)[:, -self.k] - slack[some])
                item, col = np.nonzero(inside & (score >= low[:, None]))
                if len(item):
                    self._merge(some[item], own[col], part[col])

    def _merge(self, item: np.ndarray, ids: np.ndarray, x: np.ndarray) -> None:
        """x: the groups' vectors of pairs (item, group)."""
        y = self.items[item]
        score = y[:, 0] * x[:, 0]
        for j in range(1, x.shape[1]):
            score += y[:, j] * x[:, j]
        changed = np.unique(item)
        old = np.repeat(changed, self.k)
        item, ids, score = np.append(item, old), np.append(ids, self.ids[changed].ravel()), np.append(score, self.scores[changed].ravel())
        known = score > -np.inf
        item, ids, score = item[known], ids[known], score[known]
        order = np.lexsort((ids, -np.round(score, RANK_DIGITS), item))
        item, ids, score = item[order], ids[order], score[order]
        start = np.flatnonzero(np.diff(item, prepend=item[0] - 1))
        place = np.arange(len(item)) - np.repeat(start, np.diff(np.append(start, len(item))))
        kept = place < self.k
        self.ids[item[kept], place[kept]], self.scores[item[kept], place[kept]] = ids[kept], score[kept]

    def rows(self):
        """(items, groups, scores) of what was kept, in parts."""
        for first in range(0, len(self.items), ITEMS):
            item, place = np.nonzero(self.scores[first : first + ITEMS] > -np.inf)
            item = item + first
            if len(item):
                yield item, self.ids[item, place], self.scores[item, place]
