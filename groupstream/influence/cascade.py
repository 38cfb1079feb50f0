"""Independent cascades over propagation graphs, static and refreshed, for many runs and seed sets at once.

State rows are (run, s, v, g, round): in run `run` group g became active for item v and seed set s. An edge is tried once,
when its source becomes active. Thresholds are a function of the run and the edge (or node), so a task that runs again
tries the same ones, and all runs share one join per round.
"""

from __future__ import annotations

import itertools
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import uniform
from ..sources.storage import settle
from .prop_graph import apply_updates

_KEY = ["run", "s", "v", "g"]


def threshold(mode: str = "per_edge_uniform", tau: float = 0.5, salt: str = "threshold"):
    """What a weight has to exceed: a fixed value, or a hashed number per run and edge or per run and receiving node."""
    if mode == "fixed":
        return F.lit(float(tau))
    return uniform(salt, "run", "src", "dst") if mode == "per_edge_uniform" else uniform(salt, "run", "dst")


def live_edges(graph: DataFrame, runs: int = 1, **kw) -> DataFrame:
    """(run, v, src, dst): the edges that would pass in each run. A cascade from any seeds reaches what they reach over these."""
    each = graph.withColumn("run", F.explode(F.sequence(F.lit(0), F.lit(runs - 1))))
    return each.where(F.col("p") > threshold(**kw)).select("run", "v", "src", "dst")


def _next(active: DataFrame, frontier: DataFrame, live: DataFrame, number: int) -> DataFrame:
    tried = frontier.select("run", "s", "v", F.col("g").alias("src")).join(live, ["run", "v", "src"])
    reached = tried.select("run", "s", "v", F.col("dst").alias("g")).distinct()
    return reached.join(active.select(*_KEY), _KEY, "left_anti").withColumn("round", F.lit(number))


def _seeded(seeds: DataFrame, runs: int) -> DataFrame:
    return seeds.select("s", "v", "g").distinct().withColumn("run", F.explode(F.sequence(F.lit(0), F.lit(runs - 1)))).select(*_KEY, F.lit(0).alias("round"))


def run(graph: DataFrame, seeds: DataFrame, runs: int = 1, max_rounds: int | None = None, **kw) -> DataFrame:
    """The static cascade from seeds (s, v, g): all active (run, s, v, g, round), to the end or for max_rounds.

    A round adds groups that were not active, so it ends after as many rounds as there are groups at the latest.
    """
    live = settle(live_edges(graph, runs, **kw), "live")
    active = frontier = settle(_seeded(seeds, runs), "active")
    for number in itertools.count(1) if max_rounds is None else range(1, max_rounds + 1):
        frontier = settle(_next(active, frontier, live, number), "active")
        if frontier.isEmpty():
            break
        active = active.unionByName(frontier)
    return active


def run_dynamic(graph: DataFrame, seeds: DataFrame, batches: list[tuple[DataFrame, DataFrame]], runs: int = 1, inject_new: bool = True, max_rounds: int | None = None, weights: dict | None = None, scale: Callable[[DataFrame], DataFrame] | None = None, **kw) -> DataFrame:
    """The dynamic cascade. batches: per round the new interactions (v, g) and the activeness (g, act) after them.

    Before each round its batch refreshes the graph; groups with new interactions become active as well (inject_new). It
    ends when nothing new is active and no batch is left, or after max_rounds, if given. scale: what is done to the weights
    of the refreshed graph before they meet the thresholds.
    """
    active = frontier = settle(_seeded(seeds, runs), "active")
    sets = active.select("run", "s", "v").distinct()
    edges = lambda g: settle(live_edges(scale(g) if scale else g, runs, **kw), "live")
    live = None if batches else edges(graph)
    for number in itertools.count(1) if max_rounds is None else range(1, max_rounds + 1):
        added = None
        if number <= len(batches):
            fresh, now = batches[number - 1]
            graph = settle(apply_updates(graph, fresh, now, **(weights or {})), "graph")
            live = edges(graph)
            if inject_new:
                added = sets.join(fresh.select("v", "g").distinct(), "v").select(*_KEY)
        reached = _next(active, frontier, live, number)
        if added is not None:
            new = added.join(active.select(*_KEY), _KEY, "left_anti").withColumn("round", F.lit(number))
            reached = reached.unionByName(new).dropDuplicates(_KEY)
        frontier = settle(reached, "active")
        if frontier.isEmpty() and number >= len(batches):
            break
        active = active.unionByName(frontier)
    return active


def spread(active: DataFrame, n_groups: int, runs: int = 1) -> DataFrame:
    """(s, v, spread, influence): mean number of active groups per seed set, and as a share of all groups."""
    sizes = active.groupBy("s", "v").agg((F.count("*") / runs).alias("spread"))
    return sizes.withColumn("influence", F.col("spread") / n_groups)


def predict(graph: DataFrame, groups: DataFrame, n_groups: int, runs: int = 1, **kw) -> DataFrame:
    """(v, g, influence): how far an item would spread from each group alone."""
    items = graph.select("v").distinct()
    seeds = groups.select("g").join(items).select(F.col("g").alias("s"), "v", "g")
    return spread(run(graph, seeds, runs, **kw), n_groups, runs).select("v", F.col("s").alias("g"), "influence")


def sketch_reach(live: DataFrame, groups: DataFrame, k: int = 16, salt: str = "rank") -> DataFrame:
    """(run, v, g, reach): estimated numbers of groups reached, from bottom-k sketches that flow against the edges.

    Each node keeps the k least ranks among what it reaches; with r the k-th, it reaches about (k - 1) / r. Work per round
    is k per edge, whatever the sets' sizes, which suits graphs whose reachable sets do not fit anywhere.
    """
    frame = live.select("run", "v").distinct().join(groups.select("g"))
    now = settle(frame.withColumn("sketch", F.array(uniform(salt, "run", "g"))), "sketch")
    while True:  # sketches only ever take smaller ranks in, of which there are finitely many
        sent = live.join(now.select("run", "v", F.col("g").alias("dst"), "sketch"), ["run", "v", "dst"]).select("run", "v", F.col("src").alias("g"), F.explode("sketch").alias("r"))
        every = now.select("run", "v", "g", F.explode("sketch").alias("r")).unionByName(sent).distinct()
        merged = every.groupBy("run", "v", "g").agg(F.slice(F.sort_array(F.collect_set("r")), 1, k).alias("sketch"))
        after = settle(merged, "sketch")
        changed = after.join(now.withColumnRenamed("sketch", "old"), ["run", "v", "g"]).where("sketch <> old").isEmpty()
        now = after
        if changed:
            break
    full = F.size("sketch") >= k
    return now.select("run", "v", "g", F.when(full, (k - 1) / F.element_at("sketch", k)).otherwise(F.size("sketch").cast("double")).alias("reach"))
