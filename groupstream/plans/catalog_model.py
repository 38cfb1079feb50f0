"""Queries on groups, interactions, the relation graph, the encoder and the forecaster, with their SQL."""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..encoder import layers as L
from ..encoder import relevance as R
from ..encoder import training as TR
from ..features import latent, tags
from ..forecast import recurrent, sequence
from ..functions.linalg import dot
from ..model import groups as G
from ..model import interactions as I
from ..model import relation_graph as RG
from ..sources.storage import settle
from ..sources.tables import Tables
from . import cte
from .cte import D, TAGS, columns, compose, sigmoid, vdot, vmap, vmean, vsum, vzeros, vzip


ASK = 50


def spread(vec: str, d: int = D, name: str = "x") -> list[Column]:
    """A vector as columns of rounded numbers."""
    return [(F.round(F.get(F.col(vec), F.lit(i)), 6) + F.lit(0.0)).alias(f"{name}{i}") for i in range(d)]


class Home:
    """The home family with small repeatable weights: what most queries start from.

    Parts are lazy DataFrames, but for the pruned graph and the first layer, which many branches share and which are
    written out once.
    """

    def __init__(self, spark, sf_dir):
        self.t = Tables(spark, sf_dir)

    lines = cached_property(lambda self: self.t.lines())
    members = cached_property(lambda self: G.memberships(self.t, "home"))
    group_lines = cached_property(lambda self: I.group_lines(self.t, "home"))
    pairs = cached_property(lambda self: self.group_lines.select("g", "v").distinct())
    sliced = cached_property(lambda self: I.chrono_split(self.group_lines))
    counts = cached_property(lambda self: I.slice_counts(self.sliced))
    friends = cached_property(lambda self: RG.friendship_edges(self.lines, 30))
    lifted = cached_property(lambda self: RG.lift_to_groups(self.friends, G.home_groups(self.t)))
    edges = cached_property(lambda self: settle(RG.prune(self.lifted.withColumnRenamed("friends", "w"), "top_neighbours", 10), "edges"))
    lap = cached_property(lambda self: RG.laplacian_weights(RG.symmetric(self.edges)))
    items = cached_property(lambda self: latent.item_vectors(self.t))
    users = cached_property(lambda self: latent.user_vectors(self.lines, self.items))
    latent = cached_property(lambda self: latent.hyperedge_aggregate(self.members, self.users))
    tagged = cached_property(lambda self: tags.hashed_tag_vectors(tags.item_tags(self.t)))
    group_tags = cached_property(lambda self: tags.group_tag_vectors(self.pairs, self.tagged))
    e0 = cached_property(lambda self: settle(L.initial_layer(self.latent, self.group_tags, "g", L.weights(D, D + TAGS, 0), L.bias(D, 0), TAGS), "layer0"))
    e0_items = cached_property(lambda self: L.initial_layer(self.items, self.tagged, "v", L.weights(D, D + TAGS, 1), L.bias(D, 1), TAGS))
    layers = [(L.weights(D, 2 * D, s), L.bias(D, s)) for s in (2, 3)]

    def encoded(self, n: int) -> DataFrame:
        return L.encode_groups(self.lap, self.e0, self.layers[:n], D)

    @cached_property
    def e2(self) -> DataFrame:
        return self.encoded(2)

    @cached_property
    def window(self) -> DataFrame:
        """The arriving items that every search asks for: all whose key is divisible by 50."""
        return self.e0_items.where(f"v % {ASK} = 0")


QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None, **extra: str):
    """Registers a query, and its SQL if there is one."""

    def add(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = compose(sql, extra)
        return f

    return add


for _family in G.FAMILIES:
    query(f"memberships_{_family}", f"SELECT g, u, first_day, last_day, n FROM mem_{_family}")(lambda spark, d, family=_family: G.memberships(Tables(spark, d), family))


@query("members_at", "SELECT g, u, last_day FROM mem_market WHERE first_day <= 10957 AND last_day >= 10957 - 365")
def _(spark, d):
    return G.members_at(G.memberships(Tables(spark, d), "market"), 10957, 365).select("g", "u", "last_day")


@query("group_interactions_market", "SELECT g, v, count(*) AS n, min(day) AS first_day, max(day) AS last_day FROM gl_market GROUP BY 1, 2")
def _(spark, d):
    return I.group_interactions(I.group_lines(Tables(spark, d)))


@query("group_interactions_taste", "SELECT m.g, l.v, count(*) AS n, min(l.day) AS first_day, max(l.day) AS last_day FROM lines l JOIN mem_taste m USING (u) GROUP BY 1, 2")
def _(spark, d):
    return I.group_interactions(I.group_lines(Tables(spark, d), "taste"))


@query("interactions_fresh", "SELECT g, v, count(*) AS n, min(day) AS first_day, max(day) AS last_day FROM gl_market WHERE day > 10957 AND day <= 10987 GROUP BY 1, 2")
def _(spark, d):
    return I.group_interactions(I.fresh(I.group_lines(Tables(spark, d)), 10957, 10987))


@query("interactions_upto", "SELECT g, count(*) AS n, count(DISTINCT v) AS items FROM gl_market WHERE day <= 10957 GROUP BY 1")
def _(spark, d):
    return I.upto(I.group_lines(Tables(spark, d)), 10957).groupBy("g").agg(F.count("*").alias("n"), F.countDistinct("v").alias("items"))


@query(
    "item_attributes_running",
    """SELECT v, slice, bought, (sum(bought) OVER w)::BIGINT AS popularity, round((sum(paid) OVER w)::DOUBLE / (sum(bought) OVER w), 8) AS avg_price FROM (
      SELECT v, slice, count(*) AS bought, sum(price::DECIMAL(18, 2)) AS paid FROM sliced_market WHERE slice IS NOT NULL GROUP BY 1, 2)
      WINDOW w AS (PARTITION BY v ORDER BY slice)""",
)
def _(spark, d):
    return I.item_attributes(I.chrono_split(I.group_lines(Tables(spark, d))))


@query("chrono_split_counts", "SELECT split, coalesce(slice, -1) AS slice, count(*) AS n, min(day) AS first_day, max(day) AS last_day FROM sliced_market GROUP BY 1, 2")
def _(spark, d):
    rows = I.chrono_split(I.group_lines(Tables(spark, d)))
    return rows.groupBy("split", F.coalesce("slice", F.lit(-1)).alias("slice")).agg(F.count("*").alias("n"), F.min("day").alias("first_day"), F.max("day").alias("last_day"))


@query("common_user_edges", "SELECT a, b, common FROM common_market WHERE common >= 3")
def _(spark, d):
    return RG.common_user_edges(G.memberships(Tables(spark, d)), 3)


@query("friendship_edges", "SELECT a, b, items FROM friends")
def _(spark, d):
    return Home(spark, d).friends


@query("friendship_lifted", "SELECT a, b, friends FROM lift_home")
def _(spark, d):
    return Home(spark, d).lifted


@query("relation_graph_home", "SELECT a, b, w FROM edges_home")
def _(spark, d):
    return Home(spark, d).edges


@query(
    "relation_graph_ties",
    "SELECT coalesce(c.a, f.a) AS a, coalesce(c.b, f.b) AS b, coalesce(c.common, 0) AS common, coalesce(f.friends, 0) AS friends, coalesce(c.common, 0) + coalesce(f.friends, 0) AS w FROM common_taste c FULL JOIN lift_taste f ON c.a = f.a AND c.b = f.b",
    common_taste="SELECT x.g AS a, y.g AS b, count(*) AS common FROM mem_taste x JOIN mem_taste y ON x.u = y.u AND x.g < y.g GROUP BY 1, 2",
    lift_taste="SELECT least(x.g, y.g) AS a, greatest(x.g, y.g) AS b, count(*) AS friends FROM friends f JOIN mem_taste x ON x.u = f.a JOIN mem_taste y ON y.u = f.b WHERE x.g <> y.g AND f.items >= 2 GROUP BY 1, 2",
)
def _(spark, d):
    h = Home(spark, d)
    members = G.memberships(h.t, "taste")
    return RG.ties(RG.common_user_edges(members), RG.lift_to_groups(h.friends.where("items >= 2"), members))


@query(
    "relation_graph_top_neighbours",
    """SELECT least(src, dst) AS a, greatest(src, dst) AS b, max(w) AS w FROM (
      SELECT *, row_number() OVER (PARTITION BY src ORDER BY w DESC, dst) AS n FROM (
        SELECT a AS src, b AS dst, common AS w FROM common_market UNION ALL SELECT b, a, common FROM common_market)) WHERE n <= 10 GROUP BY 1, 2""",
)
def _(spark, d):
    return RG.prune(RG.common_user_edges(G.memberships(Tables(spark, d))).withColumnRenamed("common", "w"), "top_neighbours", 10)


@query("relation_graph_jaccard", "SELECT a, b, common AS w FROM common_market JOIN sizes x ON x.g = a JOIN sizes y ON y.g = b WHERE common / (x.size + y.size - common)::DOUBLE >= 0.25", sizes="SELECT g, count(*) AS size FROM mem_market GROUP BY 1")
def _(spark, d):
    members = G.memberships(Tables(spark, d))
    return RG.prune(RG.common_user_edges(members).withColumnRenamed("common", "w"), "min_jaccard", 0.25, members.groupBy("g").agg(F.count("*").alias("size")))


@query("laplacian_weights", "SELECT src, dst, deg_src, deg_dst, round(lap, 6) AS lap FROM lap_home")
def _(spark, d):
    return Home(spark, d).lap.select("src", "dst", "deg_src", "deg_dst", F.round("lap", 6).alias("lap"))


@query("hyperedge_latent", f"SELECT g, {columns('vec')} FROM pg_market")
def _(spark, d):
    h = Home(spark, d)
    return latent.hyperedge_aggregate(G.memberships(h.t), h.users).select("g", *spread("vec"))


@query(
    "hyperedge_latent_degree",
    f"SELECT g, {columns(vmap('vec', '{} / sqrt(size::DOUBLE)'))} FROM (SELECT m.g, {vsum(vmap('u.vec', '{} / sqrt(k.k::DOUBLE)'))} AS vec, count(*) AS size FROM mem_market m JOIN uv u USING (u) JOIN degree k USING (u) GROUP BY 1)",
    degree="SELECT u, count(*) AS k FROM mem_market GROUP BY 1",
)
def _(spark, d):
    h = Home(spark, d)
    return latent.hyperedge_aggregate(G.memberships(h.t), h.users, "degree_norm").select("g", *spread("vec"))


@query("hashed_tags", f"SELECT v, {columns('vec', TAGS)} FROM tagvec")
def _(spark, d):
    return Home(spark, d).tagged.select("v", *spread("vec", TAGS))


@query("tag_vectors_learned")
def _(spark, d):
    return tags.tag_vectors(tags.item_tags(Tables(spark, d))).select("v", *spread("vec", TAGS))


@query("initial_layer", f"SELECT g, {columns('vec')} FROM e0_home")
def _(spark, d):
    return Home(spark, d).e0.select("g", *spread("vec"))


@query("initial_layer_items", f"SELECT v, {columns('vec')} FROM e0_item")
def _(spark, d):
    return Home(spark, d).e0_items.select("v", *spread("vec"))


@query("aggregate_neighbours", f"SELECT g, {columns('agg')} FROM agg0_home")
def _(spark, d):
    h = Home(spark, d)
    return L.aggregate_neighbours(h.lap, h.e0, D).select("g", *spread("agg"))


@query(
    "aggregate_neighbours_isolated",
    f"SELECT e.g, {columns(f'coalesce(x.agg, {vzeros()})')} FROM e0_home e LEFT JOIN (SELECT l.dst AS g, {vsum(vmap('s.vec', '{} * l.lap'))} AS agg FROM lap_home l JOIN e0_home s ON s.g = l.src WHERE l.src // 5 = l.dst // 5 GROUP BY 1) x USING (g)",
)
def _(spark, d):
    h = Home(spark, d)
    return L.aggregate_neighbours(h.lap.where("src div 5 = dst div 5"), h.e0, D).select("g", *spread("agg"))


for _n in (1, 2):
    query(f"encode_layers_{_n}", f"SELECT g, {columns('vec')} FROM e{_n}_home")(lambda spark, d, n=_n: Home(spark, d).encoded(n).select("g", *spread("vec")))

_FRESH = "SELECT DISTINCT g, v FROM gl_home WHERE day > (SELECT max(day) - 30 FROM gl_home)"


def _recent(h: Home) -> DataFrame:
    last = F.broadcast(h.group_lines.agg((F.max("day") - 30).alias("since")))
    return h.group_lines.join(last).where("day > since").select("g", "v").distinct()


for _empty, _alone in (("keep", "i.vec"), ("shrink", vmap("i.vec", "{} * 0.8e0"))):

    @query(
        f"refresh_items_{_empty}",
        f"SELECT i.v, {columns('CASE WHEN n.vec IS NULL THEN ' + _alone + ' ELSE ' + vzip('i.vec', 'n.vec', '0.8e0 * {} + (1 - 0.8e0) * {}') + ' END')} FROM e0_item i LEFT JOIN (SELECT v, {vmean('vec')} AS vec FROM fresh30 JOIN e2_home USING (g) GROUP BY 1) n USING (v)",
        fresh30=_FRESH,
    )
    def _(spark, d, empty=_empty):
        h = Home(spark, d)
        return L.refresh_items(h.e0_items, _recent(h), h.e2, 0.8, D, empty).select("v", *spread("vec"))


_HIST = f"SELECT g, {vmap('vec', '{} / sqrt(n::DOUBLE)')} AS hist, n FROM (SELECT g, {vsum('vec')} AS vec, count(*) AS n FROM pairs_home JOIN e0_item USING (v) GROUP BY 1)"
_SIDE = f"SELECT e.g, {vzip('e.vec', f'coalesce(h.hist, {vzeros()})', '{} + {}')} AS vec FROM e2_home e LEFT JOIN hist_home h USING (g)"
_INFL = "SELECT g, count(*) / (SELECT count(*) FROM e2_home)::DOUBLE AS influence FROM (SELECT src AS g FROM sym_home) GROUP BY 1"


@query("history_vectors", f"SELECT g, n AS n_items, {columns('hist')} FROM hist_home", hist_home=_HIST)
def _(spark, d):
    h = Home(spark, d)
    return R.history_vectors(h.pairs, h.e0_items, D).select("g", "n_items", *spread("hist"))


def _sides(h: Home) -> DataFrame:
    return R.group_side(h.e2, R.history_vectors(h.pairs, h.e0_items, D), D)


def _degree_share(h: Home) -> DataFrame:
    """A stand-in for influence that needs no simulation: neighbours as a share of all groups."""
    n = F.broadcast(h.e2.agg(F.count("*").alias("n")))
    return h.lap.groupBy(F.col("src").alias("g")).agg(F.count("*").alias("k")).join(n).select("g", (F.col("k") / F.col("n")).alias("influence"))


_TOP = "SELECT v, rank, g, round(raw, 6) + 0.0e0 AS score FROM (SELECT *, row_number() OVER (PARTITION BY v ORDER BY raw DESC, g)::INTEGER AS rank FROM ({}))"


@query(
    "relevance_topk",
    _TOP.format(f"SELECT i.v, s.g, round((1 - 0.5e0) * {vdot('i.vec', 's.vec')} + 0.5e0 * coalesce(f.influence, 0.0e0), 12) + 0.0e0 AS raw FROM window_items i, side_home s LEFT JOIN infl f ON f.g = s.g") + " WHERE rank <= 20",
    hist_home=_HIST,
    side_home=_SIDE,
    infl=_INFL,
)
def _(spark, d):
    h = Home(spark, d)
    groups, items = R.augment(_sides(h), h.window, _degree_share(h), 0.5)
    return R.top_k(R.relevance(groups, items, D + 1), 20)


@query("training_triples", "SELECT p.g, p.pos, p.draw, i.v AS neg FROM draws p JOIN numbered i ON i.place = p.place WHERE NOT EXISTS (SELECT 1 FROM pairs_home q WHERE q.g = p.g AND q.v = i.v)", numbered="SELECT p_partkey AS v, row_number() OVER (ORDER BY p_partkey) - 1 AS place FROM part", draws="SELECT g, v AS pos, draw, floor(" + cte.uniform_sql("negative", "g", "v", "draw") + " * (SELECT count(*) FROM part))::BIGINT AS place FROM pairs_home, (SELECT unnest([0, 1]) AS draw)")
def _(spark, d):
    h = Home(spark, d)
    return R.training_triples(h.pairs, h.t.part.select(F.col("p_partkey").alias("v")), 2)


@query(
    "pairwise_loss",
    f"SELECT count(*) AS n, round(sum(ln(1 + exp(-({vdot('g.vec', 'a.vec')} - {vdot('g.vec', 'b.vec')})))) + 0.5e0, 4) AS loss FROM triples t JOIN side_home g ON g.g = t.g JOIN e0_item a ON a.v = t.pos JOIN e0_item b ON b.v = t.neg",
    triples="SELECT p.g, p.pos, i.v AS neg FROM draws1 p JOIN numbered i ON i.place = p.place WHERE NOT EXISTS (SELECT 1 FROM pairs_home q WHERE q.g = p.g AND q.v = i.v)",
    numbered="SELECT p_partkey AS v, row_number() OVER (ORDER BY p_partkey) - 1 AS place FROM part",
    draws1="SELECT g, v AS pos, floor(" + cte.uniform_sql("negative", "g", "v", "0") + " * (SELECT count(*) FROM part))::BIGINT AS place FROM pairs_home",
    hist_home=_HIST,
    side_home=_SIDE,
)
def _(spark, d):
    h = Home(spark, d)
    triples = R.training_triples(h.pairs, h.t.part.select(F.col("p_partkey").alias("v")))
    return R.pairwise_loss(triples, _sides(h), h.e0_items, D, 0.5, 1.0).select("n", F.round("loss", 4).alias("loss"))


def inputs(h: Home) -> tuple[DataFrame, DataFrame]:
    """(g, vec) and (v, vec): latent vectors with the tag vectors behind them, the first layer's inputs."""
    none = F.array(*[F.lit(0.0)] * TAGS)
    xg = h.latent.join(h.group_tags.select("g", F.col("vec").alias("t")), "g", "left").select("g", F.concat("vec", F.coalesce("t", none)).alias("vec"))
    xv = h.items.join(h.tagged.select("v", F.col("vec").alias("t")), "v", "left").select("v", F.concat("vec", F.coalesce("t", none)).alias("vec"))
    return xg, xv


def packed(h: Home, edges: DataFrame | None = None, layers: int = 2, shards: int = 4) -> DataFrame:
    """The training pairs of the home family and what their shards need."""
    h.t.keep_lines()
    xg, xv = (settle(x, "inputs") for x in inputs(h))
    pairs = settle(h.sliced.where("split = 'train'").select("g", "v").distinct(), "pairs")
    triples = R.training_triples(pairs, h.t.part.select(F.col("p_partkey").alias("v")))
    edges = (h.lap if edges is None else edges).select("src", "dst", "lap")
    return TR.shards(xg, xv, edges, pairs, triples.select("g", "pos", "neg"), shards, layers)


def train_encoder(h: Home, epochs: int = 8, layers: int = 2, rate: float = 1e-1, penalty: float = 1e-6, edges: DataFrame | None = None, held: DataFrame | None = None, **kw):
    """Weights and log of the encoder on the home family's training pairs."""
    held = packed(h, edges, layers) if held is None else held
    return TR.train(held, TR.new_weights(D, D + TAGS, D + TAGS, layers), layers, rate, penalty, epochs, **kw)


def _losses(spark, log: list[dict]) -> DataFrame:
    return spark.createDataFrame([(r["epoch"], r["loss"], r["seconds"]) for r in log], "epoch int, loss double, seconds double")


@query("encoder_training")
def _(spark, d):
    return _losses(spark, train_encoder(Home(spark, d))[1])


@query("encoder_training_batches")
def _(spark, d):
    return _losses(spark, train_encoder(Home(spark, d), epochs=3, batches=4)[1])


@query("encoder_training_skipped_broadcasts")
def _(spark, d):
    return _losses(spark, train_encoder(Home(spark, d), epochs=4, sync_every=2)[1])


@query(
    "quadruple_counts",
    """SELECT s.slice, s.interactions, s.items, s.groups, coalesce(e.edges, 0) AS edges FROM (
      SELECT slice, count(*) AS interactions, count(DISTINCT v) AS items, count(DISTINCT g) AS groups FROM upto_home GROUP BY 1) s
      LEFT JOIN (SELECT x.slice, count(*) AS edges FROM sym_home JOIN active_home x ON x.g = src JOIN active_home y ON y.g = dst AND y.slice = x.slice GROUP BY 1) e USING (slice)""",
    upto_home="SELECT g, v, t.slice FROM sliced_home s, (SELECT unnest([0, 1, 2, 3]) AS slice) t WHERE s.slice <= t.slice",
    active_home="SELECT DISTINCT g, slice FROM upto_home",
)
def _(spark, d):
    h = Home(spark, d)
    return sequence.quadruples(h.sliced, h.lap, 4)


_LONG = f"SELECT g, slice, {vmap('vec', '{} / sqrt(n::DOUBLE)')} AS long FROM (SELECT g, slice, {vsum('vec')} AS vec, count(*) AS n FROM (SELECT DISTINCT g, v, t.slice FROM sliced_home s, (SELECT unnest([0, 1, 2, 3]) AS slice) t WHERE s.slice <= t.slice) JOIN e0_item USING (v) GROUP BY 1, 2)"
_SHORT = f"SELECT g, slice, {vmean('vec')} AS short FROM sliced_home JOIN e0_item USING (v) WHERE slice IS NOT NULL GROUP BY 1, 2"
_PROFILE = f"SELECT l.g, l.slice, list_concat(l.long, coalesce(s.short, {vzeros()})) AS profile FROM long_home l LEFT JOIN short_home s USING (g, slice)"


def _profiles(h: Home) -> DataFrame:
    return sequence.profiles(sequence.long_term(h.sliced, h.e0_items, 4, D), sequence.short_term(h.sliced, h.e0_items, D), D)


@query("profiles_concat", f"SELECT g, slice, {columns('profile', 2 * D)} FROM profile_home", long_home=_LONG, short_home=_SHORT, profile_home=_PROFILE)
def _(spark, d):
    return _profiles(Home(spark, d)).select("g", "slice", *spread("profile", 2 * D))


_H = 4
_CELL = "[" + ", ".join(f"tanh({a} + {b})" for a, b in zip(cte.matvec(L.weights(_H, 2 * D, 4), "p.profile", L.bias(_H, 4)), cte.matvec(L.weights(_H, _H, 5), "r.hidden", [0.0] * _H))) + "]"


@query(
    "rnn_fold",
    f"SELECT g, {columns('[' + ', '.join(cte.matvec(L.weights(2 * D, _H, 6), 'hidden', L.bias(2 * D, 6))) + ']', 2 * D)} FROM folded r JOIN (SELECT g, max(n) AS n FROM folded GROUP BY 1) USING (g, n)",
    long_home=_LONG,
    short_home=_SHORT,
    profile_home=_PROFILE,
    numbered_home="SELECT *, row_number() OVER (PARTITION BY g ORDER BY slice) AS n FROM profile_home",
    folded=f"SELECT DISTINCT g, 0::BIGINT AS n, {vzeros(_H)} AS hidden FROM profile_home UNION ALL SELECT r.g, r.n + 1, {_CELL} FROM folded r JOIN numbered_home p ON p.g = r.g AND p.n = r.n + 1",
)
def _(spark, d):
    seqs = sequence.sequences(_profiles(Home(spark, d)))
    hidden = recurrent.rnn_encode(seqs, L.weights(_H, 2 * D, 4), L.weights(_H, _H, 5), L.bias(_H, 4), _H)
    return recurrent.rnn_decode(hidden, L.weights(2 * D, _H, 6), L.bias(2 * D, 6)).select("g", *spread("predicted", 2 * D))


for _cell in ("rnn", "gru"):

    @query(f"forecaster_training_{_cell}")
    def _(spark, d, cell=_cell):
        seqs = sequence.sequences(_profiles(Home(spark, d))).persist()
        weights, log = recurrent.train(seqs, recurrent.new_weights(2 * D, 8, cell), epochs=6)
        out = recurrent.predict(seqs, weights)
        return out.select("g", *spread("predicted", 2 * D))
