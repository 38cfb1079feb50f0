"""Whole recommendation pipelines, composed from the parts: the enhanced one, its ablations, and the static predecessor.

A run learns interests slice by slice (on sampled graphs or whole ones), forecasts the groups' vectors after the last slice,
predicts from them how far each arriving item would spread from each group, and finds every item's best groups through the
index or by the exhaustive way.
"""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..encoder import layers as L
from ..encoder import relevance as R
from ..evaluation import measures as ME
from ..forecast import interest
from ..index import search
from ..index.build import GroupIndex
from ..influence import cascade as CA
from ..influence import dense
from ..influence import factors as FA
from ..influence import prop_graph as PG
from ..model.interactions import SLICES, chrono_split
from ..sampling import overlap as O
from ..sources.storage import settle
from . import catalog_model as M
from .catalog_influence import Spread
from .catalog_sampling import OVERLAP, SHARE, Sampler
from .cte import D

K, LIST = 20, 5
#: What does not depend on any option, and is worked out once for all variants of a run.
SHARED = ("edges", "e0", "und", "quotas", "now", "counts", "sliced", "learned", "first_inputs")


class Pipeline(Sampler, Spread):
    """One run over the home family.

    sampler: learn on sampled graphs, else on whole ones. cascade: 'dynamic', 'static' or 'none'. index: search through it,
    else exhaustively. forecast: take the forecaster's vectors, else those of the last slice. drop, g1, g2: the factors of a
    propagation edge. learning: further options of interest.learn. base: a run whose tables are shared; same: what of its
    results this run has as well, since its options do not change them.
    """

    def __init__(self, spark, sf_dir, sampler: bool = True, cascade: str = "dynamic", index: bool = True, forecast: bool = True, alpha_r: float = 1e-6, alpha_v: float = 0.8, layers: int = 2, g1: float = FA.GAMMA1, g2: float = FA.GAMMA2, drop: str | None = None, learning: dict | None = None, runs: int = 1, base: "Pipeline | None" = None, same: tuple[str, ...] = ()):
        super().__init__(spark, sf_dir)
        self.t.keep_lines()
        if base is not None:
            self.t = base.t
            self.__dict__.update({k: getattr(base, k) for k in (*SHARED, *same) if k != "graph" or k in base.__dict__})
        self.sampler, self.cascade, self.use_index, self.forecast, self.runs = sampler, cascade, index, forecast, runs
        self.alpha_r, self.alpha_v, self.n_layers, self.factors, self.learning = alpha_r, alpha_v, layers, {"g1": g1, "g2": g2, "drop": drop}, learning or {}

    @cached_property
    def sliced(self) -> DataFrame:
        """The groups' lines with their split and slice, which every step of every variant reads."""
        return settle(chrono_split(self.group_lines), "sliced")

    @cached_property
    def learned(self) -> dict:
        """What was learned so far, by the options that learning depends on."""
        return {}

    @cached_property
    def first_inputs(self) -> tuple[DataFrame, DataFrame]:
        groups, items = M.inputs(self)
        return settle(groups, "inputs"), settle(items, "inputs")

    def training_graphs(self) -> DataFrame:
        """(slice, src, dst, lap): the relation graph of each slice that the encoders propagate over, sampled or whole."""
        if self.sampler:
            edges = O.snapshot_sequence(self.und, self.counts, SLICES, SHARE, OVERLAP, quotas=self.quotas).select("slice", "a", "b", "lap")
        else:
            edges = None
            for t in range(SLICES):
                now = O.slice_graph(self.und, self.counts, t).select(F.lit(t).alias("slice"), "a", "b", "lap")
                edges = now if edges is None else edges.unionByName(now)
        both = edges.select("slice", F.col("a").alias("src"), F.col("b").alias("dst"), "lap")
        return settle(both.unionByName(both.select("slice", F.col("dst").alias("src"), F.col("src").alias("dst"), "lap")), "graphs")

    def training_edges(self) -> DataFrame:
        """(src, dst, lap) of the last slice's graph."""
        return self.training_graphs().where(F.col("slice") == SLICES - 1).select("src", "dst", "lap")

    @cached_property
    def interest(self) -> interest.Interest:
        key = (self.sampler, self.n_layers, *sorted(self.learning.items()))
        if key not in self.learned:
            groups, items = self.first_inputs
            train, made = self.sliced.where("split = 'train'"), ("packed", self.sampler, self.n_layers, self.learning.get("shards", 8))
            if made not in self.learned:
                self.learned[made] = interest.packed_slices(groups, items, self.training_graphs(), train, self.n_layers, self.learning.get("shards", 8))
            self.learned[key] = interest.learn(groups, items, None, train, SLICES, D, self.n_layers, packed=self.learned[made], **self.learning)
        return self.learned[key]

    @cached_property
    def vectors(self) -> DataFrame:
        """(g, vec): where the groups' interests are expected to be."""
        return settle(self.interest.predicted() if self.forecast else self.interest.last(), "vectors")

    @cached_property
    def item_vectors(self) -> DataFrame:
        return settle(self.interest.items(self.first_inputs[1]), "item-vectors")

    @cached_property
    def asked(self) -> DataFrame:
        """(v, vec): the arriving items, refreshed by the groups that touched them in the last 30 days."""
        train = self.sliced.where("split = 'train'")
        last = F.broadcast(train.agg((F.max("day") - 30).alias("since")))
        recent = train.join(last).where("day > since").select("g", "v").distinct()
        return settle(L.refresh_items(self.item_vectors.where(f"v % {M.ASK} = 0"), recent, self.vectors, self.alpha_v, D), "asked")

    @cached_property
    def graph(self) -> DataFrame:
        """The propagation graphs of the arriving items."""
        return settle(PG.build(self.ties, self.active, FA.willingness(self.asked, self.vectors, D), **self.factors), "graph")

    @cached_property
    def ties(self) -> DataFrame:
        """(src, dst, sim) of the relation graph under the forecast vectors, which all arriving items share."""
        return settle(FA.similarity(self.lap, self.vectors, D), "ties")

    def spread(self, seeds: DataFrame | None = None, cascade: str | None = None) -> DataFrame:
        """(s, v, spread, influence) of seed sets (s, v, g), or of each group alone, over the propagation graphs."""
        n, static = self.vectors.count(), (cascade or self.cascade) == "static"
        batches = [] if static else [(settle(self.fresh(i), "fresh"), settle(self.active_after(i), "act")) for i in (1, 2)]
        if ids := dense.few(self.vectors, *[fresh for fresh, _ in batches], *([] if seeds is None else [seeds])):
            return dense.spreads(ids, self.ties, self.active, self.asked, self.vectors, n, seeds, batches, self.runs, self.factors)
        if seeds is None:
            seeds = self.vectors.select("g").join(self.asked.select("v")).select(F.col("g").alias("s"), "v", "g")
        if static:
            return CA.spread(CA.run(PG.by_in_degree(self.graph), seeds, self.runs), n, self.runs)
        return CA.spread(CA.run_dynamic(self.graph, seeds, batches, self.runs, weights=self.factors, scale=PG.by_in_degree), n, self.runs)

    @cached_property
    def influences(self) -> DataFrame:
        """(v, g, influence): how far each arriving item would spread from each group alone."""
        if self.cascade == "none":
            return self.vectors.select("g").join(self.asked.select("v")).select("v", "g", F.lit(0.0).alias("influence"))
        return settle(self.spread().select("v", F.col("s").alias("g"), "influence"), "influences")

    @cached_property
    def sides(self) -> DataFrame:
        """(g, vec): the groups' vectors with their history added."""
        seen = self.sliced.where("split = 'train'").select("g", "v").distinct()
        return settle(R.group_side(self.vectors, R.history_vectors(seen, self.item_vectors, D), D), "sides")

    def scored(self, pairs: DataFrame) -> DataFrame:
        """(v, g, score): the whole relevance of pairs (v, g), with the influence of that group for that item."""
        rows = pairs.join(self.asked.withColumnRenamed("vec", "iv"), "v").join(self.sides.withColumnRenamed("vec", "gv"), "g").join(self.influences, ["v", "g"], "left")
        like = M.dot(F.col("iv"), F.col("gv"), D)
        return rows.select("v", "g", ((1 - self.alpha_r) * like + self.alpha_r * F.coalesce("influence", F.lit(0.0))).alias("score"))

    def recommend(self, k: int = K, budget: int = 60) -> DataFrame:
        """(v, rank, g, score) of the arriving items.

        The index knows a group's mean influence, as a further coordinate; the candidates that it finds are ranked with the
        influence for the item itself.
        """
        if not self.use_index:
            return R.top_k(self.scored(self.asked.select("v").join(self.vectors.select("g"))), k)
        mean = self.influences.groupBy("g").agg(F.avg("influence").alias("influence"))
        groups, items = R.augment(self.sides, self.asked, mean, self.alpha_r)
        index = GroupIndex.build(settle(groups, "sides"), D + 1, axes=D, n_hash=8, bits=6, width=None, rows_per_block=8, buckets=64)
        found = index.top_k(settle(items, "items"), 2 * k, budget, on_miss="scan")
        return R.top_k(self.scored(found.select("v", "g")), k)

    def truth(self) -> DataFrame:
        """(v, g): pairs of the test part that training had not seen, of the arriving items."""
        old = self.sliced.where("split = 'train'").select("g", "v").distinct()
        test = self.sliced.where(f"split = 'test' and v % {M.ASK} = 0")
        return test.select("v", "g").distinct().join(old, ["g", "v"], "left_anti").select("v", "g")

    def judged(self, several: list[DataFrame], truth: DataFrame, k: int = K) -> list[tuple[float, float, float]]:
        """(HR@k, NDCG@k, sigma_inf) of each of several recommendations (v, rank, g): the spread of an item's first groups as
        one seed set, over the propagation graphs of this run and with live updates. All seed sets share one cascade."""
        several, lists = [settle(r, "recs") for r in several], None
        for i, recs in enumerate(several):
            own = recs.where(F.col("rank") <= LIST).select(F.lit(i).cast("long").alias("s"), "v", "g")
            lists = own if lists is None else lists.unionByName(own)
        reach = {r["s"]: r["mean"] for r in self.spread(lists, "dynamic").groupBy("s").agg(F.avg("influence").alias("mean")).collect()}
        return [(ME.hit_ratio(r, truth, k).first()["hr"] or 0.0, ME.ndcg(r, truth, k).first()["ndcg"] or 0.0, reach.get(i, 0.0)) for i, r in enumerate(several)]
