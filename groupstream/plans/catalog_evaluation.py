"""Queries on baselines, measures and experiment workloads, with their SQL where there is any."""

from __future__ import annotations

import time
import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..baselines import aggregate as BA

from ..evaluation import measures as ME
from ..functions.hashing import uniform
from ..index import search
from ..influence import cascade as CA
from ..model import groups as G
from ..model import interactions as I
from ..sampling import overlap as O
from ..sources.storage import settle, shared_dir
from ..streaming import jobs
from . import catalog_influence as CI
from . import catalog_model as M
from .catalog_index import INDEX, Indexed, build_index, scan_budget
from .cte import D, columns, compose, uniform_sql, vdot, vmap, vmean, vsum, vzeros, vzip
from .catalog_sampling import OVERLAP, SHARE
from .pipeline import Pipeline

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None, **extra: str):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = compose(sql, extra)
        return f

    return add


_SCORES = f"SELECT u, i.v, {vdot('w.vec', 'i.vec')} AS score FROM uv w, (SELECT * FROM iv WHERE v % 50 = 0) i"
for _how, _f in (("average", "avg"), ("least_misery", "min"), ("most_pleasure", "max")):

    @query(f"score_aggregate_{_how}", f"SELECT g, v, round({_f}(score), 6) AS score FROM mem_home JOIN scores USING (u) GROUP BY 1, 2", scores=_SCORES)
    def _(spark, d, how=_how):
        h = M.Home(spark, d)
        first = h.items.where(f"v % {M.ASK} = 0")
        return BA.score_aggregate(BA.user_scores(h.users, first, D), h.members, how).select("g", "v", F.round("score", 6).alias("score"))


@query("preference_aggregate", f"SELECT g, {columns(vmean('vec'))} FROM mem_taste JOIN uv USING (u) GROUP BY 1")
def _(spark, d):
    h = M.Home(spark, d)
    return BA.preference_aggregate(G.memberships(h.t, "taste"), h.users, D).select("g", *M.spread("vec"))


def _weighed(e: str, rest: str) -> str:
    return f"SELECT g, {columns(vmap('vec', '{} / total'))} FROM (SELECT m.g, {vsum(vmap('w.vec', '{} * ' + e))} AS vec, sum({e}) AS total FROM mem_home m JOIN uv w USING (u) {rest} GROUP BY 1)"


@query("member_attention", _weighed(f"exp({vdot('w.vec', 'p.vec')})", "JOIN pg_home p ON p.g = m.g"))
def _(spark, d):
    h = M.Home(spark, d)
    return BA.member_attention(h.members, h.users, D).select("g", *M.spread("vec"))


@query("static_attention", f"SELECT g, {columns(vmap('vec', '{} / total'))} FROM (SELECT m.g, {vsum(vmap('w.vec', '{} * k.k::DOUBLE'))} AS vec, sum(k.k::DOUBLE) AS total FROM mem_market m JOIN uv w USING (u) JOIN (SELECT u, count(*) AS k FROM mem_market GROUP BY 1) k USING (u) GROUP BY 1)")
def _(spark, d):
    h = M.Home(spark, d)
    return BA.static_attention(G.memberships(h.t), h.users, D).select("g", *M.spread("vec"))


_B = "SELECT p.g, p.v, 1 / sqrt((x.n * y.n)::DOUBLE) AS w FROM pairs_home p JOIN (SELECT g, count(*) AS n FROM pairs_home GROUP BY 1) x USING (g) JOIN (SELECT v, count(*) AS n FROM pairs_home GROUP BY 1) y USING (v)"


def _hop(to: str, have: str, base: str, vectors: str) -> str:
    return f"SELECT b.{to}, coalesce(x.vec, {vzeros()}) AS vec FROM {base} b LEFT JOIN (SELECT w.{to}, {vsum(vmap('s.vec', '{} * w.w'))} AS vec FROM bip w JOIN {vectors} s USING ({have}) GROUP BY 1) x USING ({to})"


_LIGHT = {"bip": _B, "lg1": _hop("g", "v", "pg_home", "iv"), "lv1": _hop("v", "g", "iv", "pg_home"), "lg2": _hop("g", "v", "pg_home", "lv1"), "lv2": _hop("v", "g", "iv", "lg1")}


@query("light_conv_groups", f"SELECT g, {columns(vmean('vec'))} FROM (SELECT * FROM pg_home UNION ALL SELECT * FROM lg1 UNION ALL SELECT * FROM lg2) GROUP BY 1", **_LIGHT)
def _(spark, d):
    h = M.Home(spark, d)
    return BA.light_conv(h.pairs, h.latent, h.items, 2, D)[0].select("g", *M.spread("vec"))


@query("light_conv_items", f"SELECT v, {columns(vmean('vec'))} FROM (SELECT * FROM iv UNION ALL SELECT * FROM lv1 UNION ALL SELECT * FROM lv2) GROUP BY 1", **_LIGHT)
def _(spark, d):
    h = M.Home(spark, d)
    return BA.light_conv(h.pairs, h.latent, h.items, 2, D)[1].select("v", *M.spread("vec"))


_E = {k: f"exp({vdot(k, 'm')})" for k in "abc"}


@query(
    "multi_view",
    f"SELECT g, {columns('[' + ', '.join(f'(ea * a[{i + 1}] + eb * b[{i + 1}] + ec * c[{i + 1}]) / (ea + eb + ec)' for i in range(D)) + ']')} FROM (SELECT *, {_E['a']} AS ea, {_E['b']} AS eb, {_E['c']} AS ec FROM (SELECT *, {vmap(vzip(vzip('a', 'b', '{} + {}'), 'c', '{} + {}'), '{} / 3')} AS m FROM views))",
    views=f"SELECT p.g, p.vec AS a, coalesce(i.vec, {vzeros()}) AS b, coalesce(n.vec, {vzeros()}) AS c FROM pg_home p LEFT JOIN (SELECT g, {vmean('vec')} AS vec FROM pairs_home JOIN iv USING (v) GROUP BY 1) i USING (g) LEFT JOIN (SELECT dst AS g, {vmean('vec')} AS vec FROM sym_home JOIN pg_home q ON q.g = src GROUP BY 1) n USING (g)",
)
def _(spark, d):
    h = M.Home(spark, d)
    return BA.multi_view(h.members, h.users, h.pairs, h.items, h.lap, D).select("g", *M.spread("vec"))


@query("item_knn", "SELECT v, rank, other, n FROM (SELECT *, row_number() OVER (PARTITION BY v ORDER BY n DESC, other)::INTEGER AS rank FROM (SELECT x.v, y.v AS other, count(*) AS n FROM ub x JOIN ub y ON x.u = y.u AND x.v <> y.v GROUP BY 1, 2)) WHERE rank <= 10", ub="SELECT DISTINCT u, v FROM lines")
def _(spark, d):
    return BA.item_neighbours(M.Tables(spark, d).lines())


@query("popularity", "SELECT v, n, row_number() OVER (ORDER BY n DESC, v)::INTEGER AS rank FROM (SELECT v, count(*) AS n FROM gl_market GROUP BY 1) ORDER BY rank LIMIT 20")
def _(spark, d):
    return BA.popularity(I.group_lines(M.Tables(spark, d)))


_TRUTH = "SELECT DISTINCT v, g FROM sliced_home s WHERE split = 'test' AND NOT EXISTS (SELECT 1 FROM sliced_home o WHERE o.split = 'train' AND o.v = s.v AND o.g = s.g)"
_RECS = f"SELECT v, g, row_number() OVER (PARTITION BY v ORDER BY score DESC, g) AS rank FROM (SELECT i.v, e.g, round({vdot('i.vec', 'e.vec')}, 12) AS score FROM e0_item i, e2_home e)"


def _recs(h: M.Home) -> DataFrame:
    return search.batch_match(h.encoded(2), h.e0_items, 20, D)


def _truth(h: M.Home) -> DataFrame:
    old = h.sliced.where("split = 'train'").select("g", "v").distinct()
    return h.sliced.where("split = 'test'").select("v", "g").distinct().join(old, ["g", "v"], "left_anti").select("v", "g")


@query("hit_ratio", "SELECT 20 AS k, count(r.g) AS hits, count(*) AS truths, round(count(r.g) / count(*)::DOUBLE, 6) AS hr FROM truth t LEFT JOIN (SELECT v, g FROM recs WHERE rank <= 20) r USING (v, g)", truth=_TRUTH, recs=_RECS)
def _(spark, d):
    h = M.Home(spark, d)
    return ME.hit_ratio(_recs(h), _truth(h), 20)


@query("ndcg", "SELECT 20 AS k, count(*) AS queries, round(avg(coalesce(dcg, 0) / ideal), 6) AS ndcg FROM (SELECT v, list_sum(list_transform(range(1, least(count(*), 20) + 1), lambda i: 1 / log2(i + 1))) AS ideal FROM truth GROUP BY 1) LEFT JOIN (SELECT v, sum(1 / log2(rank + 1)) AS dcg FROM recs JOIN truth USING (v, g) WHERE rank <= 20 GROUP BY 1) USING (v)", truth=_TRUTH, recs=_RECS)
def _(spark, d):
    h = M.Home(spark, d)
    return ME.ndcg(_recs(h), _truth(h), 20)


@query(
    "sigma_inf",
    "SELECT count(*) AS sets, round(avg(n / (SELECT count(*) FROM e0_home)::DOUBLE), 6) AS sigma_inf FROM (SELECT v, count(*) AS n FROM reach GROUP BY 1)",
    tops=f"SELECT v, g FROM (SELECT v, g, row_number() OVER (PARTITION BY v ORDER BY score DESC, g) AS rank FROM (SELECT i.v, e.g, round({vdot('i.vec', 'e.vec')}, 12) AS score FROM window_items i, e2_home e)) WHERE rank <= 5",
    reach=f"SELECT v, g FROM tops UNION SELECT q.v, q.dst FROM reach r JOIN graph_home q ON q.v = r.v AND q.src = r.g WHERE q.p > {CI.TAU}e0",
)
def _(spark, d):
    s = CI.Spread(spark, d)
    seeds = search.batch_match(s.encoded(2), s.window, 5, D).select(F.lit(0).cast("long").alias("s"), "v", "g")
    return ME.sigma_inf(CA.spread(CA.run(s.graph, seeds, mode="fixed", tau=CI.TAU), s.e0.count()))


@query("relative_change", "SELECT event_type AS variant, round(100 * (k - k_all) / k_all, 2) + 0.0e0 AS events, round(100 * (u - u_all) / u_all, 2) + 0.0e0 AS users, round(100 * (m - m_all) / m_all, 2) + 0.0e0 AS mean_value FROM (SELECT event_type, count(*)::DOUBLE AS k, count(DISTINCT user_id)::DOUBLE AS u, avg(value) AS m FROM events GROUP BY 1), (SELECT count(*)::DOUBLE AS k_all, count(DISTINCT user_id)::DOUBLE AS u_all, avg(value) AS m_all FROM events)")
def _(spark, d):
    """How the events of each type differ from all events, in percent: their number, users and mean value."""
    events = M.Tables(spark, d).events
    measures = lambda rows, end: rows.agg(F.count("*").cast("double").alias(f"k{end}"), F.countDistinct("user_id").cast("double").alias(f"u{end}"), F.avg("value").alias(f"m{end}"))
    both = measures(events.groupBy("event_type"), "").join(F.broadcast(measures(events, "_all")))  # one row
    change = lambda k, name: (F.round(ME.relative_change(F.col(k), F.col(f"{k}_all")), 2) + F.lit(0.0)).alias(name)
    return both.select(F.col("event_type").alias("variant"), change("k", "events"), change("u", "users"), change("m", "mean_value"))


_SETS = {"home": ("mem_home", "gl_home"), "market": ("mem_market", "gl_market"), "taste": ("mem_taste", "(SELECT m.g, l.v FROM lines l JOIN mem_taste m USING (u))")}


@query(
    "dataset_stats",
    " UNION ALL ".join(
        f"SELECT '{f}' AS family, (SELECT count(DISTINCT u) FROM {m}) AS users, (SELECT count(DISTINCT v) FROM lines) AS items, (SELECT count(DISTINCT g) FROM {m}) AS groups, (SELECT round(count(*) / count(DISTINCT g)::DOUBLE, 4) FROM (SELECT DISTINCT g, v FROM {l})) AS items_per_group, (SELECT round(count(*) / count(DISTINCT u)::DOUBLE, 4) FROM (SELECT DISTINCT u, v FROM lines)) AS items_per_user"
        for f, (m, l) in _SETS.items()
    ),
)
def _(spark, d):
    t, out = M.Tables(spark, d), None
    pairs = t.lines().select("u", "v").distinct()
    items = pairs.agg(F.countDistinct("v").alias("items"), F.round(F.count("*") / F.countDistinct("u"), 4).alias("items_per_user"))
    for family in ("home", "market", "taste"):
        members = G.memberships(t, family).agg(F.countDistinct("u").alias("users"), F.countDistinct("g").alias("groups"))
        touched = I.group_lines(t, family).select("g", "v").distinct().agg(F.round(F.count("*") / F.countDistinct("g"), 4).alias("items_per_group"))
        row = members.join(touched).join(items).select(F.lit(family).alias("family"), "users", "items", "groups", "items_per_group", "items_per_user")
        out = row if out is None else out.unionByName(row)
    return out


@query("tuning_groups", f"SELECT g FROM (SELECT DISTINCT g FROM mem_market) ORDER BY {uniform_sql('tuning', 'g')}, g LIMIT 100")
def _(spark, d):
    groups = G.memberships(M.Tables(spark, d)).select("g").distinct()
    return groups.withColumn("u", uniform("tuning", "g")).orderBy("u", "g").limit(100).select("g")


# Workloads that train, time or simulate have no SQL.


@query("recommend")
def recommend(spark, d):
    return Pipeline(spark, d).recommend()


@query("static_predecessor")
def _(spark, d):
    """The same learning on whole graphs, static cascades and the exhaustive search."""
    return Pipeline(spark, d, sampler=False, cascade="static", index=False).recommend()


@query("recommend_without_influence")
def _(spark, d):
    return Pipeline(spark, d, cascade="none", alpha_r=0.0).recommend()


@query("interest_profiles")
def _(spark, d):
    """What the encoders of every slice make of each group: long-term and short-term, side by side."""
    return Pipeline(spark, d).interest.profiles.select("g", "slice", *M.spread("profile", 2 * D))


@query("training_times")
def _(spark, d):
    """Epochs, seconds and last loss of each phase of learning, with and without the sampler."""
    base, rows = Pipeline(spark, d), []
    for name, sampler in (("sampled", True), ("all edges", False)):
        log = Pipeline(spark, d, sampler=sampler, base=base).interest.log
        for phase in ("long", "short", "forecast"):
            for t in range(I.SLICES):
                part = [r for r in log if r["phase"] == phase and r["slice"] == t]
                if part:
                    rows.append((name, phase, t, len(part), float(part[-1]["seconds"]), float(part[-1]["loss"])))
    return _table(spark, rows, "edges string, phase string, slice int, epochs int, seconds double, loss double")


def _table(spark, rows: list[tuple], names: str) -> DataFrame:
    return spark.createDataFrame([tuple(round(float(x), 9) if isinstance(x, float) else x for x in r) for r in rows], names)


_SAME = ("vectors", "item_vectors", "sides", "asked", "ties", "graph")
VARIANTS = {
    "full": {},
    "no sampler": {"sampler": False},
    "no dynamic cascade": {"cascade": "static", "same": _SAME},
    "no influence": {"cascade": "none", "same": _SAME},
    "no index": {"index": False, "same": (*_SAME, "influences")},
}


@query("ablation_components")
def _(spark, d):
    base = Pipeline(spark, d)
    runs = [(Pipeline(spark, d, base=base, **kw) if kw else base).recommend() for kw in VARIANTS.values()]
    rows = [(name, *found) for name, found in zip(VARIANTS, base.judged(runs, settle(base.truth(), "truth")))]
    full = rows[0]
    change = [tuple(ME.relative_change(x, y) if y else 0.0 for x, y in zip(r[1:], full[1:])) for r in rows]
    return _table(spark, [(*r, *c) for r, c in zip(rows, change)], "variant string, hr double, ndcg double, sigma_inf double, hr_change double, ndcg_change double, sigma_change double")


@query("ablation_cascade")
def _(spark, d):
    """The spread of the recommended lists when an edge's weight lacks a factor."""
    base, rows = Pipeline(spark, d), []
    recs = settle(base.recommend(), "recs").where(F.col("rank") <= 5).select(F.lit(0).cast("long").alias("s"), "v", "g")
    for name, drop in (("no similarity", "similarity"), ("no willingness", "willingness"), ("no activeness", "activeness"), ("all factors", None)):
        p = Pipeline(spark, d, drop=drop, base=base, same=("vectors", "item_vectors", "sides", "asked", "ties"))
        rows.append((name, float(ME.sigma_inf(p.spread(recs)).first()["sigma_inf"] or 0.0)))
    return _table(spark, rows, "variant string, sigma_inf double")


@query("cascade_baselines")
def _(spark, d):
    """The spread of the same lists over random and over static weights, which know neither items nor live events."""
    s = CI.Spread(spark, d)
    n, rows = s.e0.count(), []
    for name, weights in (("random", CI.FA.random_weights(s.lap)), ("static", CI.FA.static_weights(s.lap, s.active, s.sims)), ("item-aware", s.graph.select("v", "src", "dst", "p"))):
        edges = weights if "v" in weights.columns else weights.join(s.window.select("v"))
        found = CA.spread(CA.run(CI.PG.by_in_degree(settle(edges, "weights")), s.seeds), n)
        rows.append((name, float(ME.sigma_inf(found).first()["sigma_inf"] or 0.0)))
    return _table(spark, rows, "weights string, sigma_inf double")


def baseline_vectors(h: M.Home) -> dict[str, tuple[DataFrame, DataFrame]]:
    """(groups, items) of each baseline, all items."""
    light = BA.light_conv(h.pairs, h.latent, h.items, 2, D)
    return {
        "light convolution": light,
        "member attention": (BA.member_attention(h.members, h.users, D), h.items),
        "multi-view hypergraph": (BA.multi_view(h.members, h.users, h.pairs, h.items, h.lap, D), h.items),
    }


def _baseline_recs(h: M.Home) -> dict:
    """For each baseline what recommends groups to the arriving items. It may know the training part only."""
    h.__dict__["pairs"] = h.sliced.where("split = 'train'").select("g", "v").distinct()
    return {name: (lambda g=g, v=v: search.batch_match(g, v.where(f"v % {M.ASK} = 0"), 20, D)) for name, (g, v) in baseline_vectors(h).items()}


@query("effectiveness")
def _(spark, d):
    """HR, NDCG and the spread of the first groups, of all methods on the same items."""
    base = Pipeline(spark, d)
    runs = {"enhanced": base.recommend(), "static predecessor": Pipeline(spark, d, sampler=False, cascade="static", index=False, base=base).recommend()}
    runs |= {name: way() for name, way in _baseline_recs(M.Home(spark, d)).items()}
    rows = [(name, *found) for name, found in zip(runs, base.judged(list(runs.values()), settle(base.truth(), "truth")))]
    return _table(spark, rows, "method string, hr double, ndcg double, sigma_inf double")


@query("hit_ratio_items_of_groups", "SELECT 20 AS k, count(r.v) AS hits, count(*) AS truths, round(count(r.v) / count(*)::DOUBLE, 6) AS hr FROM truth t LEFT JOIN (SELECT g, v FROM back WHERE rank <= 20) r USING (g, v)", truth=_TRUTH, back=_RECS.replace("PARTITION BY v ORDER BY score DESC, g", "PARTITION BY g ORDER BY score DESC, v"))
def _(spark, d):
    """The other direction: which items are recommended to a group."""
    h = M.Home(spark, d)
    items = h.e0_items.select(F.col("v").alias("g"), "vec")
    back = search.batch_match(items, h.encoded(2).select(F.col("g").alias("v"), "vec"), 20, D)
    return ME.hit_ratio(back, _truth(h).select(F.col("g").alias("v"), F.col("v").alias("g")), 20)


@query("response_times")
def _(spark, d):
    """Seconds from arriving items to recommendations, end to end, of each method. What was learned is there before."""
    rows, base = [], Pipeline(spark, d)
    _ = base.vectors
    ways = {"enhanced": lambda: Pipeline(spark, d, base=base).recommend(), "static predecessor": lambda: Pipeline(spark, d, cascade="static", index=False, base=base).recommend()}
    for name, way in {**ways, **_baseline_recs(M.Home(spark, d))}.items():
        began = time.perf_counter()
        n = way().count()
        rows.append((name, n, time.perf_counter() - began))
    return _table(spark, rows, "method string, n long, seconds double")


def _ways(index, groups: DataFrame, items: DataFrame, budget: int) -> dict:
    return {
        "batch": lambda: search.batch_match(groups, items, 20, D),
        "tree": lambda: index.tree_top_k(items, 20, budget),
        "two-level": lambda: index.top_k(items, 20, budget),
        "two-level, best blocks": lambda: index.top_k(items, 20, budget, on_miss="scan"),
    }


@query("index_effect")
def _(spark, d):
    """Seconds for the arriving items by each way of matching, and what it finds of the exact lists."""
    s, rows = Indexed(spark, d), []
    index, groups, items = s.fitted, s.groups, settle(s.arriving, "arriving")
    exact, budget = settle(search.batch_match(groups, items, 20, D), "exact"), scan_budget(groups.count())
    for name, way in _ways(index, groups, items, budget).items():
        began = time.perf_counter()
        found = settle(way(), "found")
        seconds = time.perf_counter() - began
        rows.append((name, found.count(), seconds, float(ME.recall_at_k(found, exact, 20).first()["recall"])))
    return _table(spark, rows, "method string, n long, seconds double, recall double")


@query("growth")
def _(spark, d):
    """How the seconds of matching grow with the groups: 1, 2 and 4 times as many, the added ones near given ones."""
    s, rows = Indexed(spark, d), []
    items = settle(s.arriving, "arriving")
    for times in (1, 2, 4):
        near = F.transform("vec", lambda x: x * (1 + (uniform("growth", "g", "copy") - 0.5) * 0.1 * (F.col("copy") > 0).cast("double")))
        groups = settle(s.groups.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(times - 1)))).select((F.col("g") * 4 + F.col("copy")).alias("g"), near.alias("vec")), "grown")
        n, began = groups.count(), time.perf_counter()
        index = build_index(groups)
        rows.append((times, n, "build", time.perf_counter() - began))
        for name, way in _ways(index, groups, items, scan_budget(n)).items():
            began = time.perf_counter()
            way().count()
            rows.append((times, n, name, time.perf_counter() - began))
    return _table(spark, rows, "times int, n_groups long, method string, seconds double")


@query("sampling_effect")
def _(spark, d):
    """Training of the encoder on the whole graph and on a sampled one: edges, epochs and seconds until the loss settles."""
    p, rows = Pipeline(spark, d), []
    for name, edges in (("sampled", p.training_edges()), ("all edges", p.lap)):
        held = M.packed(p, edges)
        _, log = M.train_encoder(p, epochs=12, held=held, tolerance=5e-3)
        rows.append((name, edges.count(), len(log), float(log[-1]["seconds"]), float(log[-1]["loss"])))
    return _table(spark, rows, "edges string, n long, epochs int, seconds double, loss double")


def sweep(spark, d, name: str, values: list) -> DataFrame:
    """HR and NDCG for each value of a parameter of the pipeline, or of learning, and the spread where it depends on it. The
    tables, and the results that the parameter does not change, are shared."""
    base, rows = Pipeline(spark, d, index=False), []
    truth = settle(base.truth(), "truth")
    spreads, held = name in ("alpha_r", "g1", "g2"), []
    for value in values:
        kw = {"learning": {"epochs": 4, "tune": 1, "epochs2": 4, name: value}} if name in LEARNING else {name: value}
        p = Pipeline(spark, d, index=False, cascade="dynamic" if spreads else "none", base=base, same=SAME.get(name, ()), **kw)
        if name == "alpha_r":
            held.append(p.recommend())
        elif spreads:
            rows.append((float(value), *p.judged([p.recommend()], truth)[0]))
        else:
            recs = settle(p.recommend(), "recs")
            rows.append((float(value), ME.hit_ratio(recs, truth, 20).first()["hr"] or 0.0, ME.ndcg(recs, truth, 20).first()["ndcg"] or 0.0, None))
    rows += [(float(v), *found) for v, found in zip(values, base.judged(held, truth))] if held else []
    return _table(spark, rows, "value double, hr double, ndcg double, sigma_inf double")


_LEARNT = ("vectors", "item_vectors", "sides")
SAME = {"alpha_v": _LEARNT, "alpha_r": (*_LEARNT, "asked", "ties", "graph", "influences"), "g1": (*_LEARNT, "asked", "ties"), "g2": (*_LEARNT, "asked", "ties")}
LEARNING = ("rate", "rate2", "penalty", "penalty2")
SWEEPS = {
    "layers": [0, 1, 2, 3, 4],
    "alpha_v": [0.0, 0.4, 0.8, 0.9, 1.0],
    "alpha_r": [1e-8, 1e-6, 1e-2, 0.5, 1.0],
    "g1": [0.0, 0.1, 0.2, 0.3],
    "g2": [0.0, 0.4, 0.7, 0.9],
    "rate": [1e-4, 1e-3, 1e-2, 1e-1, 1.0],
    "rate2": [1e-4, 1e-3, 1e-2, 1e-1, 1.0],
    "penalty": [1e-8, 1e-7, 1e-6, 1e-5, 1e-4],
    "penalty2": [1e-8, 1e-7, 1e-6, 1e-5, 1e-4],
}
for _name, _values in SWEEPS.items():
    query(f"sweep_{_name}")(lambda spark, d, n=_name, v=tuple(_values): sweep(spark, d, n, list(v)))


@query("sweep_g1_g2")
def _(spark, d):
    """The grid of both coefficients of a propagation edge: the spread of the same recommended lists."""
    base, rows = Pipeline(spark, d), []
    recs = settle(base.recommend(), "recs").where(F.col("rank") <= 5).select(F.lit(0).cast("long").alias("s"), "v", "g")
    for g1 in (0.0, 0.1, 0.5, 1.0):
        for g2 in (0.0, 0.4, 0.7, 0.9):
            if g1 + g2 <= 1:
                rows.append((g1, g2, float(ME.sigma_inf(Pipeline(spark, d, g1=g1, g2=g2, base=base, same=(*_LEARNT, "asked", "ties")).spread(recs)).first()["sigma_inf"] or 0.0)))
    return _table(spark, rows, "g1 double, g2 double, sigma_inf double")


@query("operation_counts")
def _(spark, d):
    """What the sampler, the cascade and the searches touch, next to what their analysis says."""
    s = CI.Spread(spark, d)
    x, rows = Indexed(spark, d), []
    p = Pipeline(spark, d)
    n_edges, kept = p.und.count(), O.snapshot_sequence(p.und, p.counts, 1, SHARE, OVERLAP, quotas=p.quotas).count()
    rows.append(("sampler: edges read", n_edges, "edges"))
    rows.append(("sampler: edges kept", kept, "share of edges"))
    live = settle(CI.PG.by_in_degree(s.graph), "live")
    active = settle(CA.run(live, s.seeds), "active")
    tried = active.select("run", "v", F.col("g").alias("src")).join(live.select("v", "src", "dst"), ["v", "src"]).count()
    rows.append(("cascade: edges tried", tried, "propagation edges at most"))
    rows.append(("cascade: propagation edges", live.count(), "propagation edges"))
    items, groups = x.arriving.count(), x.groups.count()
    found = settle(search.probe(x.clusters, x.index.directory, x.index.buckets), "probes")
    rows.append(("batch: pairs scored", items * groups, "items times groups"))
    rows.append(("two-level: directory entries read", int(found.agg(F.sum("steps")).first()[0] or 0), "one per probe, with chains"))
    rows.append(("two-level: probes that missed", found.where("miss").count(), "probes"))
    rows.append(("two-level: entries scanned", search.scan(found, x.index.blocks, 200, x.index.rows_per_block).count(), "budget per probe"))
    return _table(spark, rows, "operation string, n long, bound string")


@query("stream_recommendations", "SELECT v, rank, g, round(score, 6) + 0.0e0 AS score FROM ranked WHERE rank <= 20", **INDEX)
def _(spark, d):
    """The arriving items as a stream of four files; each micro-batch is recommended and stored as it comes."""
    s = Indexed(spark, d)
    folder = f"{shared_dir(spark)}/arrivals-{uuid.uuid4().hex}"
    s.arriving.repartition(4, "v").write.parquet(f"{folder}/in")
    stream = spark.readStream.schema("v long, vec array<double>").option("maxFilesPerTrigger", 1).parquet(f"{folder}/in")
    jobs.recommend_stream(stream, s.index, 20, 200, f"{folder}/out")
    return spark.read.parquet(f"{folder}/out").select("v", "rank", "g", "score")


@query("stream_refresh", "SELECT v, src, dst, round(p, 6) AS p FROM graph2", **CI.GRAPH)
def _(spark, d):
    """Two days of live interactions, checked one after the other, refresh the propagation graphs."""
    s = CI.Spread(spark, d)
    folder = f"{shared_dir(spark)}/live-{uuid.uuid4().hex}"
    for day in (1, 2):
        s.fresh(day).withColumn("day", F.lit(day)).coalesce(1).write.mode("append").parquet(f"{folder}/{day}")
    state = {"graph": s.graph}
    for day in (1, 2):
        stream = spark.readStream.schema("v long, g long, day int").parquet(f"{folder}/{day}")
        jobs.refresh_stream(stream, state, lambda n, day=day: s.active_after(day), f"{folder}/check{day}")
    return state["graph"].select("v", "src", "dst", F.round("p", 6).alias("p"))
