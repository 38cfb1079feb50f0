"""Cascades of many items where groups are few: a task holds all groups and their edges, and works items out one by one.

The rounds are those of cascade.run and cascade.run_dynamic over the graphs of prop_graph, with the same thresholds, but
neither an item's propagation graph nor the active groups of a seed set leave the task; only the sizes do. Work per item is
that of its edges and of one small matrix product a round.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .cascade import threshold
from .factors import GAMMA1, GAMMA2, weight

#: The most groups that a task holds with all their edges; with more, cascades go on as joins.
FEW = 512
#: Items that a task works out before it sends their sizes on.
TOGETHER = 256


def few(groups: DataFrame, *more: DataFrame) -> list[int] | None:
    """The ids of all groups that may become active, in order, or nothing if they are too many."""
    rows = groups.select("g")
    for m in more:
        rows = rows.unionByName(m.select("g"))
    found = rows.distinct().limit(FEW + 1).collect()
    return sorted(r["g"] for r in found) if len(found) <= FEW else None


def spreads(ids: list[int], sims: DataFrame, active: DataFrame, items: DataFrame, groups: DataFrame, n_groups: int, seeds: DataFrame | None = None, batches: list[tuple[DataFrame, DataFrame]] = (), runs: int = 1, weights: dict | None = None, **kw) -> DataFrame:
    """(s, v, spread, influence) as cascade.spread has them, of seed sets (s, v, g), or of each group alone, which is then s.

    ids: what few found. sims (src, dst, sim), active (g, act) and groups (g, vec) are the parts of the items' propagation
    graphs, whose weights are divided by in-degrees; items (v, vec) are any number. batches as in cascade.run_dynamic.
    """
    weight(**(weights or {}))  # refuses coefficients that do not fit
    g1, g2, drop = ((weights or {}).get(k, x) for k, x in (("g1", GAMMA1), ("g2", GAMMA2), ("drop", None)))
    at = {g: i for i, g in enumerate(ids)}
    vectors = {r["g"]: r["vec"] for r in groups.select("g", "vec").collect()}
    each = sims.withColumn("run", F.explode(F.sequence(F.lit(0), F.lit(runs - 1)))).select("run", "src", "dst", "sim", threshold(**kw).alias("u"))
    edges = sorted((r["src"], r["dst"], r["run"], r["sim"], r["u"]) for r in each.collect() if r["src"] in vectors and r["dst"] in vectors)
    first = edges[::runs]
    src, dst = (np.array([at[e[k]] for e in first], np.int64) for k in (0, 1))
    sim, bar = np.array([e[3] for e in first], np.float64), np.array([e[4] for e in edges], np.float64).reshape(-1, runs)
    degree = np.bincount(dst, minlength=len(ids))[dst] if len(dst) else np.zeros(0)
    acts = []
    for rows in (active, *[now for _, now in batches]):
        acts.append(np.zeros(len(ids)))
        for r in rows.select("g", "act").collect():
            if r["g"] in at:
                acts[-1][at[r["g"]]] = r["act"]
    known = np.array([at[g] for g in vectors], np.int64)
    matrix = np.array(list(vectors.values()), np.float64).reshape(len(known), -1)
    names, rounds, each_alone = np.array(ids, np.int64), len(batches), seeds is None  # kernels must not hold DataFrames

    def live(a, w):
        send = a[src] if drop == "willingness" else w[src] if drop == "activeness" else a[src] * w[src]
        s, r = 0.0 if drop == "similarity" else g2, 0.0 if drop == "willingness" else 1 - g1 - g2
        p = (g1 * send + s * sim + r * w[dst]) / degree
        out = np.zeros((runs, len(ids), len(ids)), np.float32)
        for k in range(runs):
            on = p > bar[:, k]
            out[k, src[on], dst[on]] = 1
        return out

    def sizes(will, fresh, sets):
        """The numbers of active groups, over all runs, of start sets (set, group)."""
        now = front = np.repeat(sets[None], runs, 0)
        a, w, number = acts[0].copy(), will.copy(), 0
        edges = None if rounds else live(a, w)
        while number < rounds or front.any():
            hit = fresh[number] if number < rounds else None
            if hit is not None:
                a[hit], w[hit] = acts[number + 1][hit], 1.0
                edges = live(a, w)
            reached = np.matmul(front.astype(np.float32), edges) > 0
            if hit is not None:
                reached[:, :, hit] = True
            front = reached & ~now
            now, number = now | front, number + 1
        return now.sum((0, 2))

    alone = np.zeros((len(known), len(ids)), bool)
    alone[np.arange(len(known)), known] = True

    def run(parts):
        for part in parts:
            vs, raw = part["v"].to_numpy(np.int64), None
            x = np.array(part["vec"].tolist(), np.float64).reshape(len(part), -1)
            for j in range(matrix.shape[1]):  # in the order of the column expression
                term = x[:, j : j + 1] * matrix[None, :, j]
                raw = term if raw is None else raw + term
            will = np.zeros((len(part), len(ids)))
            will[:, known] = 1.0 / (1.0 + np.exp(-raw))
            lists = [[np.array([at[g] for g in (found if found is not None else ())], np.int64) for found in part[f"fresh{i}"]] for i in range(rounds)]
            made = []
            for i, v in enumerate(vs):
                if each_alone:
                    s, start = names[known], alone
                else:
                    s = sorted({r["s"] for r in part["seeds"].iloc[i]})
                    start, place = np.zeros((len(s), len(ids)), bool), {x: n for n, x in enumerate(s)}
                    for r in part["seeds"].iloc[i]:
                        start[place[r["s"]], at[r["g"]]] = True
                made.append((s, np.full(len(s), v), sizes(will[i], [x[i] for x in lists], start)))
                if len(made) == TOGETHER or i + 1 == len(vs):
                    s, v_, n = (np.concatenate(x) for x in zip(*made))
                    yield pd.DataFrame({"s": s, "v": v_, "spread": n / runs, "influence": n / runs / n_groups})
                    made = []

    asked = items.select("v", "vec")
    if seeds is not None:
        asked = asked.join(seeds.select("v", "s", "g").distinct().groupBy("v").agg(F.collect_list(F.struct("s", "g")).alias("seeds")), "v")
    for i, (fresh, _) in enumerate(batches):
        asked = asked.join(fresh.select("v", "g").distinct().groupBy("v").agg(F.collect_list("g").alias(f"fresh{i}")), "v", "left")
    parts = asked.sparkSession.conf.get("spark.sql.shuffle.partitions")
    return asked.repartition(int(parts), "v").mapInPandas(run, "s long, v long, spread double, influence double")
