"""Queries on the two-level index and its baselines, with their SQL.

The SQL reads pivots and directions as constants that the same rules produce, so it checks every step from the projection
on; the choice of pivots has its own query.
"""

from __future__ import annotations

from functools import cached_property

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..evaluation import measures as ME
from ..features import latent
from ..functions.hashing import next_prime
from ..index import blocks as B
from ..index import fastmap, lsh, search
from ..index.build import GroupIndex
from ..model import groups as G
from ..operators.joins import positions
from ..sources.storage import settle
from . import catalog_model as M
from .cte import D, compose, num, vdot, vmap

QUERIES: dict = {}
SQL: dict[str, str] = {}
BITS, N_HASH, WIDTH, ROWS, BUCKETS, BUDGET, K = 6, 4, 0.02, 64, 1024, 200, 20
AXES = 3
A_DIR, B_DIR = lsh.directions(N_HASH, AXES)


def query(name: str, sql: str | None = None, **extra: str):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = compose(sql, INDEX | extra)
        return f

    return add


def build_index(groups: DataFrame, d: int = D) -> GroupIndex:
    """The index that searches go through: as many axes as the distance has dimensions, cells fitted to the groups, small blocks."""
    return GroupIndex.build(groups, d, axes=d + 1, n_hash=9, bits=6, width=None, rows_per_block=16, buckets=BUCKETS)


def scan_budget(n_groups: int) -> int:
    """Entries that an item may read: one in fifteen of the groups, but 200 at least."""
    return max(200, n_groups // 15)


class Indexed(M.Home):
    """Market groups with their mean member preferences, and parts as arriving items."""

    groups = cached_property(lambda self: settle(latent.hyperedge_aggregate(G.memberships(self.t), self.users), "groups"))
    arriving = cached_property(lambda self: self.items.where(f"v % {M.ASK} = 0"))
    pivots = cached_property(lambda self: fastmap.choose_pivots(self.mapped, AXES, D + 1))
    mapped = cached_property(lambda self: fastmap.to_distance(self.groups, self.arriving, D)[0])

    @cached_property
    def index(self) -> GroupIndex:
        return GroupIndex.build(self.groups, D, AXES, N_HASH, BITS, WIDTH, ROWS, BUCKETS)

    @cached_property
    def fitted(self) -> GroupIndex:
        return build_index(self.groups)

    @cached_property
    def keyed(self) -> DataFrame:
        return lsh.keyed(fastmap.project(self.mapped, self.pivots, D + 1), A_DIR, B_DIR, WIDTH, BITS)

    asked = cached_property(lambda self: self.index.keys(self.arriving))
    clusters = cached_property(lambda self: search.cluster_items(self.asked))


def _square(a: str, b: str) -> str:
    return "(" + " + ".join(f"(({a})[{i + 1}] - ({b})[{i + 1}]) * (({a})[{i + 1}] - ({b})[{i + 1}])" for i in range(D + 1)) + ")"


def _far(table: str, away: str) -> str:
    return f"SELECT * FROM {table} ORDER BY round({away}, 9) DESC, g LIMIT 1"


def _axis(i: int) -> dict[str, str]:
    """Pivots of axis i and coordinates up to it, from the coordinates before."""
    rows, made = f"co{i}", {}
    rest = " ".join(f"- (r.x{j} - p.x{j}) * (r.x{j} - p.x{j})" for j in range(i))
    gap = f"greatest({_square('r.vec', 'p.vec')} {rest}, 0.0e0)"
    made[f"hop{i}"] = _far(f"(SELECT r.*, {gap} AS away FROM {rows} r, (SELECT * FROM {rows} ORDER BY g LIMIT 1) p)", "away")
    made[f"end{i}"] = _far(f"(SELECT r.*, {gap} AS away FROM {rows} r, hop{i} p)", "away")
    xs = " ".join(f"- (r.x{j} - x.x{j}) * (r.x{j} - x.x{j})" for j in range(i))
    ys = " ".join(f"- (r.x{j} - y.x{j}) * (r.x{j} - y.x{j})" for j in range(i))
    first, second = f"greatest({_square('r.vec', 'x.vec')} {xs}, 0.0e0)", f"greatest({_square('r.vec', 'y.vec')} {ys}, 0.0e0)"
    length = "sqrt(round(y.away, 9))"
    for kind, rows_ in (("co", rows), ("cv", f"cv{i}")):
        made[f"{kind}{i + 1}"] = f"SELECT r.*, ({first} + {length} * {length} - {second}) / (2 * {length}) AS x{i} FROM {rows_} r, hop{i} x, end{i} y"
    made[f"printed{i}"] = f"SELECT r.g, ({first} + {length} * {length} - sqrt({second})) / (2 * {length}) AS x{i} FROM {rows} r, hop{i} x, end{i} y"
    return made


def _cells(rows: str, key: str) -> str:
    half, top = 1 << (BITS - 1), (1 << BITS) - 1
    made = []
    for i in range(N_HASH):
        value = " + ".join(f"{num(A_DIR[i][j] / WIDTH)} * x{j}" for j in range(AXES)) + f" + {num(B_DIR[i])}"
        made.append(f"least(greatest(floor(round({value}, 9))::BIGINT + {half}, 0), {top})::BIGINT AS h{i}")
    return f"SELECT {key}, vec, {', '.join(made)} FROM {rows}"


def _z(table: str, key: str) -> str:
    place, terms = N_HASH * BITS, []
    for bit in range(BITS - 1, -1, -1):
        for i in range(N_HASH):
            place -= 1
            terms.append(f"(((h{i} >> {bit}) & 1) << {place})")
    return f"SELECT {key}, vec, {' | '.join(terms)} AS z FROM {table}"


_HASH = f"(((key % {B.PRIME}) * {B.A} + {B.B}) % {B.PRIME}) % {BUCKETS}"
INDEX = {
    "arriving": "SELECT * FROM iv WHERE v % 50 = 0",
    "co0": f"SELECT g, list_append(vec, sqrt(greatest(m * m - {vdot('vec', 'vec')}, 0.0e0))) AS vec FROM pg_market, (SELECT max(sqrt({vdot('vec', 'vec')})) AS m FROM pg_market)",
    "cv0": f"SELECT v, CASE WHEN own > 0 THEN list_append({vmap('vec', '{} * (m / own)')}, 0.0e0) ELSE list_append(vec, 0.0e0) END AS vec FROM (SELECT v, vec, sqrt({vdot('vec', 'vec')}) AS own FROM arriving), (SELECT max(sqrt({vdot('vec', 'vec')})) AS m FROM pg_market)",
    **_axis(0),
    **_axis(1),
    **_axis(2),
    "cell_g": _cells("co3", "g"),
    "cell_v": _cells("cv3", "v"),
    "zg": _z("cell_g", "g"),
    "zv": _z("cell_v", "v"),
    "blocks": f"SELECT z, g, pos, pos // {ROWS} AS block FROM (SELECT z, g, row_number() OVER (ORDER BY z, g) - 1 AS pos FROM zg)",
    "keys": "SELECT z AS key, min(pos) AS pos, count(*) AS n FROM blocks GROUP BY 1",
    "directory": f"SELECT {_HASH} AS bucket, key, pos, n, row_number() OVER (PARTITION BY {_HASH} ORDER BY key) AS chain_no, lead(key) OVER (PARTITION BY {_HASH} ORDER BY key) AS next_key FROM keys",
    "clusters": "SELECT z, count(*) AS n, min(v) AS first_v FROM zv GROUP BY 1",
    "probes": "SELECT z, coalesce((SELECT max(key) FROM keys WHERE key <= z), (SELECT min(key) FROM keys)) AS key FROM clusters",
    "starts": "SELECT p.z, p.key, k.pos, p.key <> p.z AS miss FROM probes p JOIN keys k USING (key)",
    "scanned": f"SELECT z, g, pos, step FROM (SELECT s.z, b.g, b.pos, row_number() OVER (PARTITION BY s.z ORDER BY CASE WHEN b.pos >= s.pos THEN 2 * (b.pos - s.pos) ELSE 2 * (s.pos - b.pos) - 1 END, b.pos) AS step FROM starts s JOIN blocks b ON abs(b.pos - s.pos) <= {BUDGET}) WHERE step <= {BUDGET}",
    "ranked": f"SELECT v, g, score, row_number() OVER (PARTITION BY v ORDER BY score DESC, g)::INTEGER AS rank FROM (SELECT i.v, c.g, round({vdot('a.vec', 'e.vec')}, 12) + 0.0e0 AS score FROM zv i JOIN arriving a USING (v) JOIN scanned c USING (z) JOIN pg_market e USING (g))",
    "exact": f"SELECT v, g, score, row_number() OVER (PARTITION BY v ORDER BY score DESC, g)::INTEGER AS rank FROM (SELECT a.v, e.g, round({vdot('a.vec', 'e.vec')}, 12) + 0.0e0 AS score FROM arriving a, pg_market e)",
}


@query("fastmap_pivots", " UNION ALL ".join(f"SELECT {i} AS axis, x.g AS x, y.g AS y, round(sqrt(round(y.away, 9)), 6) AS gap FROM hop{i} x, end{i} y" for i in range(AXES)))
def _(spark, d):
    return spark.createDataFrame([(i, p["x"]["g"], p["y"]["g"], round(p["gap"], 6)) for i, p in enumerate(Indexed(spark, d).pivots)], "axis int, x long, y long, gap double")


@query("fastmap_coords", "SELECT g, round(x0, 6) + 0.0e0 AS x0, round(x1, 6) + 0.0e0 AS x1, round(x2, 6) + 0.0e0 AS x2 FROM co3")
def _(spark, d):
    s = Indexed(spark, d)
    return fastmap.project(s.mapped, s.pivots, D + 1).select("g", *M.spread("xs", AXES))


@query("fastmap_coords_printed", "SELECT g, round(x0, 6) + 0.0e0 AS x0 FROM printed0")
def _(spark, d):
    s = Indexed(spark, d)
    return fastmap.project(s.mapped, s.pivots[:1], D + 1, "printed").select("g", *M.spread("xs", 1))


@query("distance_completed", "SELECT g, round(vec[9], 6) AS rest FROM co0")
def _(spark, d):
    return Indexed(spark, d).mapped.select("g", F.round(F.get("vec", F.lit(D)), 6).alias("rest"))


@query("lsh_axes", f"SELECT g, {', '.join(f'h{i}' for i in range(N_HASH))} FROM cell_g")
def _(spark, d):
    return Indexed(spark, d).keyed.select("g", *[F.get("cells", F.lit(i)).alias(f"h{i}") for i in range(N_HASH)])


@query("zorder_keys", "SELECT g, z FROM zg")
def _(spark, d):
    return Indexed(spark, d).keyed.select("g", "z")


@query("blocks", f"SELECT z, g, pos, block, CASE WHEN block > 0 THEN block - 1 END AS prev_block, CASE WHEN block < (SELECT max(block) FROM blocks) THEN block + 1 END AS next_block FROM blocks")
def _(spark, d):
    return Indexed(spark, d).index.blocks.select("z", "g", "pos", "block", "prev_block", "next_block")


@query("positions", "SELECT u, g, row_number() OVER (ORDER BY u, g) - 1 AS pos FROM mem_market")
def _(spark, d):
    return positions(G.memberships(M.Tables(spark, d)).select("u", "g"), ["u", "g"])


@query("universal_hash", f"SELECT key, {_HASH} AS bucket FROM (SELECT p_partkey AS key FROM part)")
def _(spark, d):
    t = M.Tables(spark, d)
    return t.part.select(F.col("p_partkey").alias("key"), search.universal_hash(F.col("p_partkey"), B.A, B.B, B.PRIME, BUCKETS).alias("bucket"))


@query(
    "next_prime",
    "SELECT s, n, p FROM counted JOIN (SELECT n, min(c) AS p FROM (SELECT DISTINCT n FROM counted) JOIN primes ON c >= n GROUP BY 1) USING (n)",
    counted="SELECT l_suppkey AS s, count(*) AS n FROM lineitem GROUP BY 1",
    upward="SELECT unnest(range(2, 2 * (SELECT max(n) FROM counted) + 2)) AS c",
    primes="SELECT c FROM upward x WHERE NOT EXISTS (SELECT 1 FROM upward k WHERE k.c * k.c <= x.c AND x.c % k.c = 0)",
)
def _(spark, d):
    """As many buckets as each supplier's lines would need: the least prime at or above their number."""

    @F.pandas_udf("long")
    def prime(n: pd.Series) -> pd.Series:
        return n.map(next_prime).astype("int64")

    counted = M.Tables(spark, d).lineitem.groupBy(F.col("l_suppkey").alias("s")).agg(F.count("*").alias("n"))
    return counted.select("s", "n", prime("n").alias("p"))


@query("directory", "SELECT bucket, key, pos, n, chain_no, next_key FROM directory")
def _(spark, d):
    return Indexed(spark, d).index.directory


@query("directory_stats", f"SELECT sum(chain)::BIGINT AS keys, count(*) AS used_buckets, round(sum(chain) / {BUCKETS}, 6) AS load, round(avg(chain), 6) AS mean_chain, max(chain) AS longest_chain, max(run) AS longest_run FROM (SELECT bucket, count(*) AS chain, max(n) AS run FROM directory GROUP BY 1)")
def _(spark, d):
    return B.directory_stats(Indexed(spark, d).index.directory, BUCKETS)


@query("item_clusters", "SELECT z, n, first_v FROM clusters")
def _(spark, d):
    return Indexed(spark, d).clusters.select("z", "n", F.element_at("items", 1).alias("first_v"))


@query("probe_hits", "SELECT s.z, s.pos, d.chain_no AS steps FROM starts s JOIN directory d USING (key) WHERE NOT miss")
def _(spark, d):
    s = Indexed(spark, d)
    return search.probe(s.clusters, s.index.directory, BUCKETS, "skip").select("z", "pos", "steps")


@query("probe_nearest", "SELECT z, pos, miss FROM starts")
def _(spark, d):
    s = Indexed(spark, d)
    return search.probe(s.clusters, s.index.directory, BUCKETS).select("z", "pos", "miss")


@query("tree_probe", "SELECT z, pos FROM starts")
def _(spark, d):
    s = Indexed(spark, d)
    return search.tree_probe(s.clusters, s.index.blocks)


@query("scan_candidates", "SELECT z, g, pos, step FROM scanned")
def _(spark, d):
    s = Indexed(spark, d)
    found = search.probe(s.clusters, s.index.directory, BUCKETS)
    return search.scan(found, s.index.blocks, BUDGET, ROWS).select("z", "g", "pos", "step")


@query("index_topk", f"SELECT v, rank, g, round(score, 6) + 0.0e0 AS score FROM ranked WHERE rank <= {K}")
def _(spark, d):
    s = Indexed(spark, d)
    return s.index.top_k(s.arriving, K, BUDGET)


@query("tree_topk", f"SELECT v, rank, g, round(score, 6) + 0.0e0 AS score FROM ranked WHERE rank <= {K}")
def _(spark, d):
    s = Indexed(spark, d)
    return s.index.tree_top_k(s.arriving, K, BUDGET)


@query("batch_topk", f"SELECT v, rank, g, round(score, 6) + 0.0e0 AS score FROM exact WHERE rank <= {K}")
def _(spark, d):
    s = Indexed(spark, d)
    return search.batch_match(s.groups, s.arriving, K, D)


@query("recall_at_k", f"SELECT {K} AS k, count(r.g) AS found, count(*) AS wanted, round(count(r.g) / count(*)::DOUBLE, 6) AS recall FROM (SELECT * FROM exact WHERE rank <= {K}) e LEFT JOIN (SELECT v, g FROM ranked WHERE rank <= {K}) r USING (v, g)")
def _(spark, d):
    s = Indexed(spark, d)
    return ME.recall_at_k(s.index.top_k(s.arriving, K, BUDGET), search.batch_match(s.groups, s.arriving, K, D), K)


@query("entries_per_item", f"SELECT v, count(*) AS entries, round(count(*) / (SELECT count(*) FROM pg_market)::DOUBLE, 6) AS ratio FROM zv JOIN scanned USING (z) GROUP BY 1")
def _(spark, d):
    s = Indexed(spark, d)
    n = F.broadcast(s.groups.agg(F.count("*").alias("n_groups")))
    found = search.scan(search.probe(s.clusters, s.index.directory, BUCKETS), s.index.blocks, BUDGET, ROWS)
    return s.asked.select("z", "v").join(found, "z").groupBy("v").agg(F.count("*").alias("entries")).join(n).select("v", "entries", F.round(F.col("entries") / F.col("n_groups"), 6).alias("ratio"))


@query("index_upsert", "SELECT g, CASE WHEN g % 50 = 0 THEN 0 ELSE z END AS z FROM zg")
def _(spark, d):
    s = Indexed(spark, d)
    rows = s.keyed.select("g", "z")
    return B.upsert(rows, rows.where("g % 50 = 0").select("g", F.lit(0).cast("long").alias("z")))


@query("index_multi_table")
def _(spark, d):
    """Two indexes with their own directions, their candidates united before the exact ranking."""
    s = Indexed(spark, d)
    other = GroupIndex.build(s.groups, D, AXES, N_HASH, BITS, WIDTH, ROWS, BUCKETS, seed=9)
    both = s.index.top_k(s.arriving, K, BUDGET // 2).unionByName(other.top_k(s.arriving, K, BUDGET // 2))
    return M.R.top_k(both.select("v", "g", "score").distinct(), K)


@query("index_best_blocks")
def _(spark, d):
    """The arriving items through the fitted index, best blocks first."""
    s = Indexed(spark, d)
    return s.fitted.top_k(s.arriving, K, scan_budget(s.groups.count()), on_miss="scan")


@query("recall_by_budget")
def _(spark, d):
    """What each way of scanning finds of the exact lists when it reads so many percent of the groups."""
    s = Indexed(spark, d)
    exact, n, rows = settle(search.batch_match(s.groups, s.arriving, K, D), "exact"), s.groups.count(), []
    for percent in (2, 5, 10, 20):
        for name, way in (("neighbours of the place", "nearest"), ("best blocks", "scan")):
            found = s.fitted.top_k(s.arriving, K, max(K, n * percent // 100), on_miss=way)
            rows.append((percent, name, ME.recall_at_k(found, exact, K).first()["recall"]))
    return spark.createDataFrame(rows, "percent int, scan string, recall double")


@query("index_size", f"SELECT count(*) AS entries, count(DISTINCT block) AS blocks, sum(8 * (2 + {D}))::BIGINT AS block_bytes, (SELECT count(*) FROM directory)::BIGINT AS keys, (SELECT 40 * count(*) FROM directory)::BIGINT AS directory_bytes FROM blocks")
def _(spark, d):
    """Entries, blocks and keys, and the bytes that they take: eight for each number that an entry holds."""
    s = Indexed(spark, d)
    lower = s.index.blocks.agg(F.count("*").alias("entries"), F.countDistinct("block").alias("blocks"), F.sum(F.lit(8) * (2 + F.size("vec"))).cast("long").alias("block_bytes"))
    upper = s.index.directory.agg(F.count("*").alias("keys"), (F.count("*") * 40).alias("directory_bytes"))
    return lower.join(upper)
