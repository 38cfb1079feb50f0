"""Queries on the snapshot edge sampler, its estimators and its bounds, with their SQL."""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sampling import clusters as C
from ..sampling import draw as DR
from ..sampling import estimators as E
from ..sampling import overlap as O
from ..sources.storage import settle
from . import catalog_model as M
from .cte import D, columns, compose, uniform_sql, vdot, vmap, vsum, vzip

QUERIES: dict = {}
SQL: dict[str, str] = {}
SHARE, OVERLAP = 0.3, 0.5


def query(name: str, sql: str | None = None, **extra: str):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = compose(sql, SAMPLER | extra)
        return f

    return add


class Sampler(M.Home):
    """The home graph as undirected edges in sets between five strata of nations."""

    @cached_property
    def und(self) -> DataFrame:
        half = self.lap.where("src < dst").select(F.col("src").alias("a"), F.col("dst").alias("b"), "lap", F.col("deg_src").alias("deg_a"), F.col("deg_dst").alias("deg_b"))
        strata = C.cluster_by_column(M.G.home_groups(self.t), F.expr("(g div 5) % 5"))
        return settle(C.edge_sets(half, strata), "sets")

    quotas = cached_property(lambda self: settle(C.allocate(self.und, SHARE), "quotas"))

    def included(self, kind: str = "laplacian") -> DataFrame:
        scores = self.scored.select("a", "b", "score") if kind == "optimal" else None
        return DR.inclusion(DR.draw_probability(self.und, kind, scores), self.quotas)

    @cached_property
    def scored(self) -> DataFrame:
        """Edge scores with the layers' vectors as they enter layers one and two."""
        return settle(E.edge_scores(self.und, [self.e0, self.encoded(1)], D), "scores")

    @cached_property
    def previous(self) -> DataFrame:
        return DR.sample_fixed(DR.draw_probability(O.slice_graph(self.und, self.counts, 0), "laplacian").join(self.quotas.select("ci", "cj", "num"), ["ci", "cj"]), "slice0").select(*self.und.columns)


def _p(table: str) -> str:
    """Inclusion probabilities from q, by the rule for capped edges."""
    return f"""SELECT a, b, lap, deg_a, deg_b, ci, cj, q, num, CASE WHEN capped THEN 1.0e0 ELSE (num - sum(capped::INT) OVER s) * q / sum(CASE WHEN NOT capped THEN q END) OVER s END AS p, capped FROM (
      SELECT *, (num - place) * q >= rest - 1e-12 AND place < num AS capped FROM (
        SELECT d.*, z.num, row_number() OVER o - 1 AS place, sum(q) OVER s - coalesce(sum(q) OVER (o ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0e0) AS rest
        FROM {table} d JOIN quotas z USING (ci, cj) WINDOW s AS (PARTITION BY ci, cj), o AS (PARTITION BY ci, cj ORDER BY q DESC, a, b))) WINDOW s AS (PARTITION BY ci, cj)"""


def _q(weight: str) -> str:
    return f"SELECT *, ({weight}) / sum({weight}) OVER (PARTITION BY ci, cj) AS q FROM und_home"


def _race(salt: str) -> str:
    return f"round(-ln({uniform_sql(salt, 'a', 'b')} + {2.0**-33!r}) / q, 9)"


_ACTIVE = "SELECT g FROM counts_home WHERE slice <= {} GROUP BY 1"
_COLS = "a, b, lap, deg_a, deg_b, ci, cj"

SAMPLER = {
    "quotas": f"""SELECT ci, cj, n_edges, base + (row_number() OVER (ORDER BY rest DESC, ci, cj) <= round(sum(n_edges) OVER () * {SHARE}e0) - sum(base) OVER ())::BIGINT AS num FROM (
      SELECT ci, cj, count(*) AS n_edges, floor(count(*) * {SHARE}e0)::BIGINT AS base, count(*) * {SHARE}e0 - floor(count(*) * {SHARE}e0) AS rest FROM und_home GROUP BY 1, 2)""",
    "q_laplacian": _q("lap"),
    "q_degree_sum": _q("(deg_a + deg_b)::DOUBLE"),
    "q_uniform": _q("1.0e0"),
    "p_laplacian": _p("q_laplacian"),
    "scored": f"SELECT u.*, {vmap(vzip(vzip('x0.vec', 'y0.vec', '{} + {}'), vzip('x1.vec', 'y1.vec', '{} + {}'), '{} + {}'), '{} * lap')} AS c FROM und_home u JOIN e0_home x0 ON x0.g = a JOIN e0_home y0 ON y0.g = b JOIN e1_home x1 ON x1.g = a JOIN e1_home y1 ON y1.g = b",
    "scores": f"SELECT *, sqrt({vdot('c', 'c')}) AS score FROM scored",
    "q_optimal": f"SELECT {_COLS}, score / sum(score) OVER (PARTITION BY ci, cj) AS q FROM scores",
    "p_optimal": _p("q_optimal"),
    "graph0": f"SELECT * FROM und_home WHERE a IN ({_ACTIVE.format(0)}) AND b IN ({_ACTIVE.format(0)})",
    "graph1": f"SELECT * FROM und_home WHERE a IN ({_ACTIVE.format(1)}) AND b IN ({_ACTIVE.format(1)})",
    "sample0": f"SELECT {_COLS} FROM (SELECT *, row_number() OVER (PARTITION BY ci, cj ORDER BY {_race('slice0')}, a, b) AS n FROM (SELECT *, lap / sum(lap) OVER (PARTITION BY ci, cj) AS q FROM graph0) JOIN quotas USING (ci, cj)) WHERE n <= num",
    "drift1": "SELECT coalesce(x.g, y.g) AS g FROM (SELECT * FROM counts_home WHERE slice = 1) x FULL JOIN (SELECT * FROM counts_home WHERE slice = 0) y ON x.g = y.g WHERE coalesce(x.n, 0) <> coalesce(y.n, 0)",
    "shared1": f"SELECT {_COLS}, a IN (SELECT g FROM drift1) OR b IN (SELECT g FROM drift1) AS changed FROM graph1 SEMI JOIN sample0 USING (a, b)",
    "reused1": f"SELECT {_COLS} FROM (SELECT *, row_number() OVER (PARTITION BY ci, cj ORDER BY changed DESC, deg_a + deg_b DESC, a, b) AS n FROM shared1 JOIN quotas USING (ci, cj)) WHERE n <= round(num * {OVERLAP}e0)",
    "fresh1": f"""SELECT {_COLS} FROM (SELECT *, row_number() OVER (PARTITION BY ci, cj ORDER BY {_race('slice1')}, a, b) AS n FROM (
      SELECT g.*, lap / sum(lap) OVER (PARTITION BY ci, cj) AS q FROM graph1 g ANTI JOIN sample0 USING (a, b)) JOIN (
      SELECT ci, cj, num - coalesce(taken, 0) AS missing FROM quotas LEFT JOIN (SELECT ci, cj, count(*) AS taken FROM reused1 GROUP BY 1, 2) USING (ci, cj)) USING (ci, cj)) WHERE n <= missing""",
    "sequence01": "SELECT 0 AS slice, * FROM sample0 UNION ALL SELECT 1, * FROM reused1 UNION ALL SELECT 1, * FROM fresh1",
}


@query("edge_sets", "SELECT ci, cj, count(*) AS n FROM und_home GROUP BY 1, 2")
def _(spark, d):
    return Sampler(spark, d).und.groupBy("ci", "cj").agg(F.count("*").alias("n"))


@query("cluster_nodes")
def _(spark, d):
    return C.cluster_nodes(M.Home(spark, d).latent, 8)


@query("allocation", "SELECT ci, cj, n_edges, num FROM quotas")
def _(spark, d):
    return Sampler(spark, d).quotas


for _kind in ("laplacian", "degree_sum", "uniform", "optimal"):

    @query(f"draw_probability_{_kind}", f"SELECT a, b, round(q, 6) AS q, round(p, 6) AS p, capped FROM p_{_kind}", **{f"p_{_kind}": _p(f"q_{_kind}")})
    def _(spark, d, kind=_kind):
        return Sampler(spark, d).included(kind).select("a", "b", F.round("q", 6).alias("q"), F.round("p", 6).alias("p"), "capped")


@query("sample_poisson", f"SELECT a, b, ci, cj FROM p_laplacian WHERE {uniform_sql('edge', 'a', 'b')} < p")
def _(spark, d):
    return DR.sample_poisson(Sampler(spark, d).included()).select("a", "b", "ci", "cj")


@query("sample_fixed", f"SELECT a, b, ci, cj FROM (SELECT *, row_number() OVER (PARTITION BY ci, cj ORDER BY {_race('edge')}, a, b) AS n FROM p_laplacian) WHERE n <= num")
def _(spark, d):
    return DR.sample_fixed(Sampler(spark, d).included()).select("a", "b", "ci", "cj")


@query("sample_top_degree", "SELECT a, b, ci, cj FROM (SELECT *, row_number() OVER (PARTITION BY ci, cj ORDER BY deg_a + deg_b DESC, a, b) AS n FROM p_laplacian) WHERE n <= num")
def _(spark, d):
    return DR.sample_top_degree(Sampler(spark, d).included()).select("a", "b", "ci", "cj")


@query("overlap_edges", "SELECT a, b FROM graph1 SEMI JOIN sample0 USING (a, b)")
def _(spark, d):
    s = Sampler(spark, d)
    return O.overlap_edges(s.previous, O.slice_graph(s.und, s.counts, 1)).select("a", "b")


@query("changed_edges", "SELECT a, b, changed FROM shared1")
def _(spark, d):
    s = Sampler(spark, d)
    return O.changed_edges(O.overlap_edges(s.previous, O.slice_graph(s.und, s.counts, 1)), O.drifting(s.counts, 1)).select("a", "b", "changed")


@query("sample_overlap", "SELECT a, b, ci, cj FROM reused1")
def _(spark, d):
    s = Sampler(spark, d)
    return O.sample_overlap(s.previous, O.slice_graph(s.und, s.counts, 1), O.drifting(s.counts, 1), s.quotas, OVERLAP).select("a", "b", "ci", "cj")


@query("sample_fresh", "SELECT a, b, ci, cj FROM fresh1")
def _(spark, d):
    s = Sampler(spark, d)
    now = O.slice_graph(s.und, s.counts, 1)
    reused = O.sample_overlap(s.previous, now, O.drifting(s.counts, 1), s.quotas, OVERLAP)
    return O.sample_fresh(s.previous, now, reused, s.quotas, "laplacian", "slice1").select("a", "b", "ci", "cj")


def _sequence(s: Sampler, slices: int = 2) -> DataFrame:
    return O.snapshot_sequence(s.und, s.counts, slices, SHARE, OVERLAP, quotas=s.quotas)


@query("snapshot_sequence", "SELECT 0 AS slice, 'fresh' AS origin, a, b FROM sample0 UNION ALL SELECT 1, 'overlap', a, b FROM reused1 UNION ALL SELECT 1, 'fresh', a, b FROM fresh1")
def _(spark, d):
    return _sequence(Sampler(spark, d)).select("slice", "origin", "a", "b")


@query("subgraph_counts", "SELECT count(*) AS n, count(DISTINCT s.g) AS groups, count(DISTINCT v) AS items FROM sliced_home s SEMI JOIN (SELECT a AS g FROM sequence01 WHERE slice = 1 UNION SELECT b FROM sequence01 WHERE slice = 1) USING (g) WHERE s.slice <= 1")
def _(spark, d):
    s = Sampler(spark, d)
    part = O.generate_subgraph(_sequence(s).where("slice = 1"), s.sliced.where("slice <= 1"))
    return part.agg(F.count("*").alias("n"), F.countDistinct("g").alias("groups"), F.countDistinct("v").alias("items"))


@query("redundancy", "SELECT s.slice, count(*) AS n_edges, count(p.a) AS shared FROM sequence01 s LEFT JOIN (SELECT slice + 1 AS slice, a, b FROM sequence01) p USING (slice, a, b) GROUP BY 1")
def _(spark, d):
    return O.redundancy(_sequence(Sampler(spark, d)))


@query(
    "stratum_drift",
    "SELECT ci, cj, round(coalesce(x.s, 0), 6) AS share_all, round(coalesce(y.s, 0), 6) AS share_sample, round(abs(coalesce(x.s, 0) - coalesce(y.s, 0)), 6) AS gap FROM (SELECT ci, cj, count(*) / sum(count(*)) OVER () AS s FROM und_home GROUP BY 1, 2) x FULL JOIN (SELECT ci, cj, count(*) / sum(count(*)) OVER () AS s FROM sequence01 WHERE slice = 1 GROUP BY 1, 2) y USING (ci, cj)",
)
def _(spark, d):
    s = Sampler(spark, d)
    out = O.stratum_drift(s.und, _sequence(s).where("slice = 1"))
    return out.select("ci", "cj", *[F.round(c, 6).alias(c) for c in ("share_all", "share_sample", "gap")])


@query("drift_coverage", "SELECT count(*) AS drifting, count(n.g) AS covered FROM drift1 LEFT JOIN (SELECT a AS g FROM sequence01 WHERE slice = 1 UNION SELECT b FROM sequence01 WHERE slice = 1) n USING (g)")
def _(spark, d):
    s = Sampler(spark, d)
    return O.drift_coverage(_sequence(s), s.counts, 1)


_PV = "SELECT g, CASE WHEN max((p >= 1)::INT) = 1 THEN 1.0e0 ELSE 1 - exp(sum(CASE WHEN p < 1 THEN ln(1 - p) ELSE 0.0e0 END)) END AS p_v FROM (SELECT a AS g, p FROM p_laplacian UNION ALL SELECT b, p FROM p_laplacian) GROUP BY 1"


@query("node_inclusion", "SELECT g, round(p_v, 6) AS p_v FROM pv", pv=_PV)
def _(spark, d):
    return E.node_inclusion(Sampler(spark, d).included()).select("g", F.round("p_v", 6).alias("p_v"))


@query(
    "node_estimate",
    f"SELECT b AS g, {columns(vsum(vmap('e.vec', '{} * lap * p_v / p')))} FROM (SELECT a, b, lap, p FROM drawn UNION ALL SELECT b, a, lap, p FROM drawn) s JOIN pv ON pv.g = s.b JOIN e0_home e ON e.g = s.a GROUP BY 1",
    pv=_PV,
    drawn=f"SELECT * FROM p_laplacian WHERE {uniform_sql('edge', 'a', 'b')} < p",
)
def _(spark, d):
    s = Sampler(spark, d)
    p = s.included()
    return E.node_estimate(DR.sample_poisson(p), E.node_inclusion(p), s.e0, D).select("g", *M.spread("est"))


def _with_p(s: Sampler, kind: str) -> DataFrame:
    return s.scored.join(s.included(kind).select("a", "b", "p"), ["a", "b"])


@query("graph_estimate", f"SELECT {columns(vsum(vmap('s.c', '{} / p')))} FROM scored s JOIN (SELECT a, b, p FROM p_laplacian WHERE {uniform_sql('edge', 'a', 'b')} < p) USING (a, b)")
def _(spark, d):
    s = Sampler(spark, d)
    return E.graph_estimate(DR.sample_poisson(_with_p(s, "laplacian")), D).select(*M.spread("est"))


@query("edge_scores", f"SELECT a, b, round(score, 6) AS score, {columns('c')} FROM scores")
def _(spark, d):
    return Sampler(spark, d).scored.select("a", "b", F.round("score", 6).alias("score"), *M.spread("c"))


@query(
    "variance_closed_form",
    " UNION ALL ".join(f"SELECT '{k}' AS kind, round(sum(score * score / p) - sum(score * score), 4) AS variance FROM scores JOIN (SELECT a, b, p FROM pp_{k}) USING (a, b)" for k in ("laplacian", "degree_sum", "uniform", "optimal")),
    **{f"pp_{k}": _p(f"q_{k}") for k in ("laplacian", "degree_sum", "uniform", "optimal")},
)
def _(spark, d):
    s, out = Sampler(spark, d), None
    for kind in ("laplacian", "degree_sum", "uniform", "optimal"):
        row = E.variance(_with_p(s, kind)).select(F.lit(kind).alias("kind"), F.round("variance", 4).alias("variance"))
        out = row if out is None else out.unionByName(row)
    return out


@query("optimal_inclusion", "SELECT ci, cj, sum(capped::INT)::BIGINT AS capped, round(sum(p), 6) AS p_sum, max(num) AS num FROM p_optimal GROUP BY 1, 2")
def _(spark, d):
    return Sampler(spark, d).included("optimal").groupBy("ci", "cj").agg(F.sum(F.col("capped").cast("long")).alias("capped"), F.round(F.sum("p"), 6).alias("p_sum"), F.max("num").alias("num"))


@query("least_variance", "SELECT round(power(sum(score), 2) / 300 - sum(score * score), 4) AS bound FROM scores")
def _(spark, d):
    return E.least_variance(Sampler(spark, d).scored, 300).select(F.round("bound", 4).alias("bound"))


@query("variance_split", "SELECT origin, round(sum(score * score / p) - sum(score * score), 4) AS variance FROM (SELECT s.*, p, CASE WHEN z.a IS NULL THEN 'fresh' ELSE 'overlap' END AS origin FROM scores s JOIN (SELECT a, b, p FROM p_laplacian) USING (a, b) LEFT JOIN sample0 z ON z.a = s.a AND z.b = s.b) GROUP BY 1")
def _(spark, d):
    s = Sampler(spark, d)
    was = s.previous.select("a", "b", F.lit("overlap").alias("was"))
    rows = _with_p(s, "laplacian").join(was, ["a", "b"], "left").withColumn("origin", F.coalesce("was", F.lit("fresh")))
    return E.variance(rows, ("origin",)).select("origin", F.round("variance", 4).alias("variance"))


@query(
    "approx_bounds",
    f"""SELECT a, b, round(best, 9) AS best, round(plain, 9) AS plain, round(lower, 9) AS lower, round(upper, 9) AS upper, round(abs(plain - best), 9) AS error,
      best BETWEEN lower - 1e-12 AND upper + 1e-12 AND abs(plain - best) <= greatest(plain * (1 - m / {D}), lap * abs({D} / ms - 1 / qs)) + 1e-12 AS holds FROM (
      SELECT *, lap * m / ms AS best, lap / qs AS plain, lap * m / (qs * {D}) AS lower, lap * {D}.0e0 / ms AS upper FROM (
        SELECT *, sum(lap) OVER () AS qs, sum(lap * m) OVER () AS ms FROM (SELECT a, b, lap, score / lap / 4 AS m FROM scores)))""",
)
def _(spark, d):
    out = E.approx_bounds(Sampler(spark, d).scored, 2, D)
    return out.select("a", "b", *[F.round(c, 9).alias(c) for c in ("best", "plain", "lower", "upper", "error")], "holds")


@query("layer_sample", f"SELECT 2 AS layer, src, dst FROM hop2 UNION ALL SELECT 1, src, dst FROM (SELECT src, dst, row_number() OVER (PARTITION BY dst ORDER BY {uniform_sql('layer1', 'src', 'dst')}, src) AS n FROM sym_home WHERE dst IN (SELECT g FROM seeds UNION SELECT src FROM hop2)) WHERE n <= 3", seeds="SELECT DISTINCT g FROM home", hop2=f"SELECT src, dst FROM (SELECT src, dst, row_number() OVER (PARTITION BY dst ORDER BY {uniform_sql('layer2', 'src', 'dst')}, src) AS n FROM sym_home WHERE dst IN (SELECT g FROM seeds)) WHERE n <= 3")
def _(spark, d):
    h = M.Home(spark, d)
    return DR.layer_sample(h.lap, M.G.home_groups(h.t).select("g"), 3, 2)


@query("subgraph_sample", f"SELECT a, b FROM und_home ORDER BY {uniform_sql('subgraph', 'a', 'b')}, a, b LIMIT 100")
def _(spark, d):
    return DR.subgraph_sample(Sampler(spark, d).und, 100).select("a", "b")


