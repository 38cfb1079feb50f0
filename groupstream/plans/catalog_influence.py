"""Queries on activeness, willingness, propagation graphs and cascades, with their SQL."""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.linalg import sigmoid
from ..influence import cascade as CA
from ..influence import dense
from ..influence import factors as FA
from ..influence import prop_graph as PG
from ..operators.joins import top_n
from ..sources.storage import settle
from ..sources.tables import day
from . import catalog_model as M
from .cte import D, compose, uniform_sql, vdot

QUERIES: dict = {}
SQL: dict[str, str] = {}
HORIZON, BEFORE_END = 7, 10


def query(name: str, sql: str | None = None, **extra: str):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = compose(sql, GRAPH | extra)
        return f

    return add


class Spread(M.Home):
    """The home family with its activity and the propagation graphs of the arriving items."""

    @cached_property
    def activity(self) -> DataFrame:
        events = self.t.events.select(F.col("user_id").alias("u"), day(F.col("ts")).alias("day"), "event_type", "props")
        return events.join(M.G.home_groups(self.t), "u")

    @cached_property
    def now(self) -> int:
        return (self.activity.agg(F.max("day")).first()[0] or 0) - BEFORE_END

    active = cached_property(lambda self: FA.activeness(self.activity, self.now, HORIZON))
    sims = cached_property(lambda self: FA.similarity(self.lap, self.encoded(2), D))
    will = cached_property(lambda self: settle(FA.willingness(self.window, self.encoded(2), D), "will"))
    graph = cached_property(lambda self: settle(PG.build(self.sims, self.active, self.will), "graph"))

    def fresh(self, batch: int) -> DataFrame:
        """(v, g): interactions of the days after `now`, one batch a day; an event's k points to the k-th arriving item."""
        k = F.get_json_object("props", "$.k").cast("long")
        rows = self.activity.where((F.col("day") == self.now + batch) & F.col("event_type").isin("view", "click", "purchase"))
        return rows.select((k * M.ASK).alias("v"), "g").distinct().join(self.window.select("v"), "v", "left_semi")

    def active_after(self, batch: int) -> DataFrame:
        return FA.activeness(self.activity, self.now + batch, HORIZON)

    @cached_property
    def seeds(self) -> DataFrame:
        """(s, v, g): for every item the groups that are most willing, as its seed set."""
        best = top_n(self.will.withColumn("r", F.round("will", 9)), ["v"], [F.desc("r"), F.col("g")], SEEDS)
        return best.select(F.lit(0).cast("long").alias("s"), "v", "g")


def _act(batch: int) -> str:
    return f"SELECT g, count(CASE WHEN day > now + {batch} - 7 THEN 1 END) / count(*)::DOUBLE AS act FROM activity, (SELECT max(day) - 10 AS now FROM activity) WHERE day <= now + {batch} GROUP BY g"


def _fresh(batch: int) -> str:
    return f"SELECT DISTINCT i.v, h.g FROM events e JOIN home h ON h.u = e.user_id JOIN window_items i ON i.v = 50 * json_extract_string(e.props, '$.k')::BIGINT WHERE e.event_type IN ('view', 'click', 'purchase') AND date_diff('day', DATE '1970-01-01', e.ts::DATE) = (SELECT max(day) - 10 FROM activity) + {batch}"


def _updated(graph: str, batch: int) -> str:
    return f"""SELECT v, src, dst, a_src, w_src, w_dst, sim, CASE WHEN touched THEN 0.1e0 * (a_src * w_src) + 0.7e0 * sim + (1 - 0.1e0 - 0.7e0) * w_dst ELSE p END AS p FROM (
      SELECT q.v, q.src, q.dst, CASE WHEN x.g IS NULL THEN q.a_src ELSE coalesce(t.act, 0.0e0) END AS a_src, CASE WHEN x.g IS NULL THEN q.w_src ELSE 1.0e0 END AS w_src,
        CASE WHEN y.g IS NULL THEN q.w_dst ELSE 1.0e0 END AS w_dst, q.sim, q.p, x.g IS NOT NULL OR y.g IS NOT NULL AS touched
      FROM {graph} q LEFT JOIN fresh{batch} x ON x.v = q.v AND x.g = q.src LEFT JOIN fresh{batch} y ON y.v = q.v AND y.g = q.dst LEFT JOIN act{batch} t ON t.g = q.src)"""


#: A fixed threshold has to lie among the weights, which are high with the small repeatable layers: below all of them a cascade
#: reaches whatever is connected, above all of them nothing.
TAU, SEEDS = 0.935, 3
GRAPH = {
    "act1": _act(1),
    "act2": _act(2),
    "fresh1": _fresh(1),
    "fresh2": _fresh(2),
    "graph1": _updated("graph_home", 1),
    "graph2": _updated("graph1", 2),
    "seeds": f"SELECT v, g FROM (SELECT v, g, row_number() OVER (PARTITION BY v ORDER BY round(will, 9) DESC, g) AS n FROM will_home) WHERE n <= {SEEDS}",
    "round0": "SELECT v, g, 0 AS round FROM seeds",
    "active1": f"SELECT * FROM round0 UNION ALL SELECT v, g, 1 FROM (SELECT q.v, q.dst AS g FROM graph1 q JOIN round0 r ON r.v = q.v AND r.g = q.src WHERE q.p > {TAU}e0 UNION SELECT v, g FROM fresh1) n WHERE NOT EXISTS (SELECT 1 FROM round0 r WHERE r.v = n.v AND r.g = n.g)",
    "active2": f"SELECT * FROM active1 UNION ALL SELECT v, g, 2 FROM (SELECT q.v, q.dst AS g FROM graph2 q JOIN active1 r ON r.v = q.v AND r.g = q.src AND r.round = 1 WHERE q.p > {TAU}e0 UNION SELECT v, g FROM fresh2) n WHERE NOT EXISTS (SELECT 1 FROM active1 r WHERE r.v = n.v AND r.g = n.g)",
}
_EDGE = "v, src, dst, round(p, 6) AS p"


@query("activeness", "SELECT g, recent, total, round(act, 6) AS act FROM act_home")
def _(spark, d):
    return Spread(spark, d).active.select("g", "recent", "total", F.round("act", 6).alias("act"))


@query("similarity_edges", "SELECT src, dst, round(sim, 6) AS sim FROM sim_home")
def _(spark, d):
    return Spread(spark, d).sims.select("src", "dst", F.round("sim", 6).alias("sim"))


_RAW = vdot("i.vec", "e.vec")
for _mode, _sql in {
    "sigmoid": "SELECT v, g, round(will, 6) AS will FROM will_home",
    "none": f"SELECT v, g, round({_RAW}, 6) AS will FROM window_items i, e2_home e",
    "clip": f"SELECT v, g, round(least(greatest({_RAW}, 0.0e0), 1.0e0), 6) AS will FROM window_items i, e2_home e",
    "minmax": f"SELECT v, g, round((raw - min(raw) OVER (PARTITION BY v)) / (max(raw) OVER (PARTITION BY v) - min(raw) OVER (PARTITION BY v)), 6) AS will FROM (SELECT v, g, {_RAW} AS raw FROM window_items i, e2_home e)",
}.items():

    @query(f"willingness_{_mode}", _sql)
    def _(spark, d, mode=_mode):
        s = Spread(spark, d)
        return FA.willingness(s.window, s.encoded(2), D, mode).select("v", "g", F.round("will", 6).alias("will"))


@query("edge_weights", f"SELECT {_EDGE} FROM graph_home")
def _(spark, d):
    return Spread(spark, d).graph.select("v", "src", "dst", F.round("p", 6).alias("p"))


for _drop, _expr in {
    "similarity": "0.1e0 * (a_src * w_src) + (1 - 0.1e0 - 0.7e0) * w_dst",
    "willingness": "0.1e0 * a_src + 0.7e0 * sim",
    "activeness": "0.1e0 * w_src + 0.7e0 * sim + (1 - 0.1e0 - 0.7e0) * w_dst",
}.items():

    @query(f"edge_weights_no_{_drop}", f"SELECT v, src, dst, round({_expr}, 6) AS p FROM graph_home")
    def _(spark, d, drop=_drop):
        return Spread(spark, d).graph.withColumn("p", FA.weight(drop=drop)).select("v", "src", "dst", F.round("p", 6).alias("p"))


@query("edge_weights_renormalised", "SELECT v, src, dst, round((0.1e0 * (a_src * w_src) + (1 - 0.1e0 - 0.7e0) * w_dst) / (0.1e0 + (1 - 0.1e0 - 0.7e0)), 6) AS p FROM graph_home")
def _(spark, d):
    return Spread(spark, d).graph.withColumn("p", FA.weight(drop="similarity", renorm=True)).select("v", "src", "dst", F.round("p", 6).alias("p"))


@query("propagation_graph", "SELECT v, src, dst, round(a_src, 6) AS a_src, round(w_src, 6) AS w_src, round(w_dst, 6) AS w_dst, round(sim, 6) AS sim FROM graph_home")
def _(spark, d):
    return Spread(spark, d).graph.select("v", "src", "dst", *[F.round(c, 6).alias(c) for c in ("a_src", "w_src", "w_dst", "sim")])


@query("apply_updates", f"SELECT {_EDGE} FROM graph1")
def _(spark, d):
    s = Spread(spark, d)
    return PG.apply_updates(s.graph, s.fresh(1), s.active_after(1)).select("v", "src", "dst", F.round("p", 6).alias("p"))


@query("baseline_random", f"SELECT src, dst, round({uniform_sql('random', 'src', 'dst')}, 6) AS p FROM sym_home")
def _(spark, d):
    return FA.random_weights(M.Home(spark, d).lap).select("src", "dst", F.round("p", 6).alias("p"))


@query("baseline_static", "SELECT s.src, s.dst, round((coalesce(act, 0.0e0) + sim) / 2, 6) AS p FROM sim_home s LEFT JOIN act_home a ON a.g = s.src")
def _(spark, d):
    s = Spread(spark, d)
    return FA.static_weights(s.lap, s.active, s.sims).select("src", "dst", F.round("p", 6).alias("p"))


@query(
    "cascade_fixed",
    "SELECT v, g FROM reach",
    reach=f"SELECT v, g FROM seeds UNION SELECT q.v, q.dst FROM reach r JOIN graph_home q ON q.v = r.v AND q.src = r.g WHERE q.p > {TAU}e0",
)
def _(spark, d):
    s = Spread(spark, d)
    return CA.run(s.graph, s.seeds, mode="fixed", tau=TAU).select("v", "g")


_LIVE = "SELECT run, v, src, dst FROM (SELECT v, src, dst, p / count(*) OVER (PARTITION BY v, dst) AS p FROM graph_home), (SELECT unnest([0, 1, 2]) AS run) WHERE p > {}"
for _mode, _u in (("per_edge_uniform", uniform_sql("threshold", "run", "src", "dst")), ("per_node_uniform", uniform_sql("threshold", "run", "dst"))):

    @query(
        f"cascade_{_mode}",
        "SELECT run, v, g FROM reach",
        live=_LIVE.format(_u),
        reach="SELECT run, v, g FROM seeds, (SELECT unnest([0, 1, 2]) AS run) UNION SELECT l.run, l.v, l.dst FROM reach r JOIN live l ON l.run = r.run AND l.v = r.v AND l.src = r.g",
    )
    def _(spark, d, mode=_mode):
        s = Spread(spark, d)
        return CA.run(PG.by_in_degree(s.graph), s.seeds, 3, mode=mode).select("run", "v", "g")


@query("cascade_live_edges", "SELECT run, v, count(*) AS n FROM live GROUP BY 1, 2", live=_LIVE.format(uniform_sql("threshold", "run", "src", "dst")))
def _(spark, d):
    s = Spread(spark, d)
    return CA.live_edges(PG.by_in_degree(s.graph), 3).groupBy("run", "v").agg(F.count("*").alias("n"))


@query("cascade_dynamic_two_rounds", "SELECT v, g, round FROM active2")
def _(spark, d):
    s = Spread(spark, d)
    batches = [(s.fresh(i), s.active_after(i)) for i in (1, 2)]
    return CA.run_dynamic(s.graph, s.seeds, batches, max_rounds=2, mode="fixed", tau=TAU).select("v", "g", "round")


_STEP = """SELECT v, g, {n} AS round FROM (
      SELECT q.v, q.dst AS g FROM live{n} q JOIN reached{m} r ON r.v = q.v AND r.g = q.src AND r.round = {m} UNION SELECT i.v, f.g FROM (SELECT DISTINCT v FROM seeds) i JOIN fresh{n} f USING (v)) x
      WHERE NOT EXISTS (SELECT 1 FROM reached{m} r WHERE r.v = x.v AND r.g = x.g)"""
_DYNAMIC = {
    "fresh3": _fresh(3),
    "act3": _act(3),
    "graph3": _updated("graph2", 3),
    "reached0": "SELECT v, g, 0 AS round FROM seeds",
    **{f"live{n}": f"SELECT v, src, dst FROM (SELECT v, src, dst, p / count(*) OVER (PARTITION BY v, dst) AS p FROM graph{n}) WHERE p > {uniform_sql('threshold', '0', 'src', 'dst')}" for n in (1, 2, 3)},
    **{f"reached{n}": f"SELECT * FROM reached{n - 1} UNION ALL " + _STEP.format(n=n, m=n - 1) for n in (1, 2, 3)},
    # After the last batch the graph stays, and what the newest groups reach over it is a closure that avoids who was active.
    "tail": "SELECT v, g FROM reached3 WHERE round = 3 UNION SELECT q.v, q.dst FROM tail t JOIN live3 q ON q.v = t.v AND q.src = t.g WHERE NOT EXISTS (SELECT 1 FROM reached3 r WHERE r.v = q.v AND r.g = q.dst AND r.round < 3)",
}


@query("cascade_dynamic", "SELECT v, count(*)::DOUBLE AS spread, round(count(*) / (SELECT count(*) FROM e0_home)::DOUBLE, 6) AS influence FROM (SELECT v, g FROM reached3 UNION SELECT v, g FROM tail) GROUP BY 1", **_DYNAMIC)
def _(spark, d):
    s = Spread(spark, d)
    batches = [(s.fresh(i), s.active_after(i)) for i in (1, 2, 3)]
    active = CA.run_dynamic(s.graph, s.seeds, batches, scale=PG.by_in_degree)
    return CA.spread(active, s.e0.count()).select("v", "spread", F.round("influence", 6).alias("influence"))


_PREDICT = dict(
    live=_LIVE.format(uniform_sql("threshold", "run", "src", "dst")).replace("[0, 1, 2]", "[0, 1]"),
    reach="SELECT run, v, s.g AS s, s.g FROM e0_home s, (SELECT unnest([0, 1]) AS run), window_items UNION SELECT l.run, l.v, r.s, l.dst FROM reach r JOIN live l ON l.run = r.run AND l.v = r.v AND l.src = r.g",
)


@query("influence_predicted", "SELECT v, s AS g, round(count(*) / 2.0e0 / (SELECT count(*) FROM e0_home), 6) AS influence FROM reach GROUP BY 1, 2", **_PREDICT)
def _(spark, d):
    s, runs = Spread(spark, d), 2
    n, vectors = s.e0.count(), s.encoded(2)
    if ids := dense.few(vectors):
        found = dense.spreads(ids, FA.similarity(s.lap, vectors, D), s.active, s.window, vectors, n, runs=runs).select("v", F.col("s").alias("g"), "influence")
    else:
        found = CA.predict(PG.by_in_degree(s.graph), s.e0, n, runs)
    return found.select("v", "g", F.round("influence", 6).alias("influence"))


@query("influence_sketched")
def _(spark, d):
    s = Spread(spark, d)
    live = settle(CA.live_edges(PG.by_in_degree(s.graph), 1), "live")
    return CA.sketch_reach(live, s.e0, 8)


@query("sigmoid_weights", "SELECT v, src, dst, round(1.0e0 / (1.0e0 + exp(-p)), 6) AS p FROM graph_home")
def _(spark, d):
    return Spread(spark, d).graph.select("v", "src", "dst", F.round(sigmoid(F.col("p")), 6).alias("p"))
