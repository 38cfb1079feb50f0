"""Learning how interests move: an encoder for every slice, fine-tuned ones beside them, and the forecaster over both.

The long-term encoder of a slice learns from all interactions until then and starts from the one before; the short-term one
goes on from it with the slice's new interactions only. A group's profile in a slice is what both make of it, side by side,
and the forecaster predicts the profile after the last slice.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..encoder import relevance as R
from ..encoder import training as TR
from ..functions.linalg import dense
from ..sources.storage import settle
from . import recurrent
from .sequence import profiles, sequences


@dataclass
class Interest:
    """What was learned. log: (phase, slice, epoch, loss, seconds) of every epoch."""

    d: int
    slices: int
    weights: dict[str, np.ndarray]
    profiles: DataFrame
    forecaster: dict[str, np.ndarray]
    log: list[dict] = field(default_factory=list)

    def predicted(self, part: str = "both") -> DataFrame:
        """(g, vec): what the forecaster expects of each group after the last slice; its long- and short-term halves lie in
        one space, so both are averaged, or one is taken ('long' or 'short')."""
        d = self.d
        halves = [F.slice("predicted", 1, d), F.slice("predicted", d + 1, d)]
        vec = {"long": halves[0], "short": halves[1], "both": F.zip_with(*halves, lambda x, y: (x + y) / 2)}[part]
        return recurrent.predict(sequences(self.profiles), self.forecaster).select("g", vec.alias("vec"))

    def last(self) -> DataFrame:
        """(g, vec): the long-term half of the last slice, without a forecast."""
        return self.profiles.where(F.col("slice") == self.slices - 1).select("g", F.slice("profile", 1, self.d).alias("vec"))

    def items(self, inputs: DataFrame) -> DataFrame:
        """(v, vec) from the items' inputs (v, vec): their first layer, which has no neighbours."""
        return inputs.select("v", dense(self.weights["wv"].tolist(), F.col("vec"), self.weights["bv"].tolist()).alias("vec"))


def packed_slices(groups: DataFrame, items: DataFrame, graphs: DataFrame, sliced: DataFrame, layers: int = 2, shards: int = 8) -> DataFrame:
    """What learn trains on. Rates, penalties and numbers of epochs do not change it, so several runs can share it."""
    seen = settle(sliced.where("slice is not null").select("g", "v", "slice").distinct(), "seen")
    triples = R.training_triples(seen, items.select("v"), keep=("slice",))
    return TR.shards(groups, items, graphs, seen, triples.select("g", "pos", "neg", "slice"), shards, layers)


def learn(groups: DataFrame, items: DataFrame, graphs: DataFrame, sliced: DataFrame, slices: int, d: int, layers: int = 2, rate: float = 1e-1, penalty: float = 1e-6, epochs: int = 8, tune: int = 2, batches: int = 1, cell: str = "rnn", hidden: int = 8, rate2: float = 1e-2, penalty2: float = 1e-5, epochs2: int = 12, shards: int = 8, seed: int = 0, packed: DataFrame | None = None) -> Interest:
    """groups (g, vec) and items (v, vec): inputs of the first layer; graphs (slice, src, dst, lap); sliced (g, v, slice).

    The first slice's encoder takes `epochs`, the others a third of them. packed: what packed_slices made of the same tables.
    """
    packed = packed_slices(groups, items, graphs, sliced, layers, shards) if packed is None else packed
    sizes = [len(r) for r in groups.limit(1).select("vec").collect() for r in r] + [len(r) for r in items.limit(1).select("vec").collect() for r in r]
    weights = TR.new_weights(d, sizes[0], sizes[1], layers, seed)
    long, short, log = None, None, []
    for t in range(slices):
        rounds = epochs if t == 0 else max(1, epochs // 3)
        weights, found = TR.train(packed, weights, layers, rate, penalty, rounds, batches=batches, t=t)
        tuned, more = TR.train(packed, weights, layers, rate / 10, penalty, tune, t=t, new_only=True)
        log += [{"phase": p, "slice": t, **r} for p, rs in (("long", found), ("short", more)) for r in rs]
        for name, w in (("long", weights), ("short", tuned)):
            now = TR.encode(packed, w, layers, t).select("g", F.lit(t).alias("slice"), F.col("vec").alias(name))
            if name == "long":
                long = now if long is None else long.unionByName(now)
            else:
                short = now if short is None else short.unionByName(now)
    each = settle(profiles(long, short, d), "profiles")
    rows = settle(sequences(each), "sequences")
    middle = each.where(F.col("slice") == slices - 1).select(*[F.avg(F.get("profile", F.lit(i))).alias(f"m{i}") for i in range(2 * d)]).first()
    start = recurrent.new_weights(2 * d, hidden, cell, seed, np.array([m or 0.0 for m in middle]))
    forecaster, found = recurrent.train(rows, start, rate2, penalty2, epochs2)
    log += [{"phase": "forecast", "slice": slices - 1, **r} for r in found]
    return Interest(d, slices, weights, each, forecaster, log)
