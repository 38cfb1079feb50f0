"""Exact top-k search by inner product with dual cover trees.

Centres picked far from each other in a bounded sample of CENTRES_FROM vectors are the top of both trees: every vector
belongs to the cell of its nearest centre, large cells are cut into blocks, and each block is indexed once, by a cover tree
whose nodes hold a centre, the radius that covers all below it and a range of rows. The sample decides how the work is dealt,
never the result. Queries are dealt and indexed alike.

Each block of queries first searches the first block of the cell that promises it most, which gives every query a k-th score. No vector q of
one node and p of another can have an inner product above cq.cp + rq |cp| + rp |cq| + rq rp. Cells, then blocks, that do not
reach the least k-th score of a block of queries are left out before anything is sent to them; inside the pairs that are left
both trees descend together under the same rule. Blocks of vectors then meet up to ASKS blocks of queries in one task.

Cases: vectors that are null, or hold null or non-finite components, take no part, nor do rows without an id; vectors meet
vectors of their own length only; every row is a candidate of its own, so a row that occurs n times is found n times, and a
query leaves out itself but not its equals; ties go to the smaller id; queries with fewer partners than k return what they
have; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import io

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, long_id, share_of

BLOCK, QUERY_BLOCK, ASKS, LEAF, QUERY_LEAF, FAN, TOGETHER = 2048, 512, 32, 64, 24, 8, 16
#: Sampled vectors that the centres are picked from, and the most centres of one length.
CENTRES_FROM, CENTRES = 4096, 256


def farthest_first(points: np.ndarray, most: int, stop: float = 0.0) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows that lie far from each other, the nearest of them for each row, and its distance.

    It starts with the first row and ends after `most` of them, or once all rows lie within `stop`.
    """
    chosen, nearest = [0], np.zeros(len(points), np.int64)
    away = np.sqrt(((points - points[0]) ** 2).sum(1))
    while len(chosen) < most and away.max(initial=0.0) > stop:
        chosen.append(int(away.argmax()))
        new = np.sqrt(((points - points[chosen[-1]]) ** 2).sum(1))
        closer = new < away
        nearest[closer], away[closer] = len(chosen) - 1, new[closer]
    return np.array(chosen), nearest, away


class Tree:
    """A cover tree over the rows of a matrix, as arrays. `order` brings the rows of each node side by side.

    The centres of a node's children are FAN rows at most, each further from the others than any row is from its own.
    """

    def __init__(self, points: np.ndarray, leaf: int = LEAF):
        self.order = np.arange(len(points))
        self.start, self.stop, self.radius, self.child, self.children, centres = [0], [len(points)], [0.0], [0], [0], [0]
        todo = [0]
        while todo:
            node = todo.pop()
            a, b = self.start[node], self.stop[node]
            own = points[self.order[a:b]]
            away = np.sqrt(((own - points[centres[node]]) ** 2).sum(1))
            self.radius[node] = float(away.max(initial=0.0))
            if b - a <= leaf or self.radius[node] == 0:
                continue
            chosen, nearest, _ = farthest_first(own, FAN, self.radius[node] / 2)
            heads, rank = self.order[a:b][chosen], np.argsort(nearest, kind="stable")
            self.order[a:b] = self.order[a:b][rank]
            edge = a + np.append(np.searchsorted(nearest[rank], np.arange(len(chosen))), b - a)
            self.child[node], self.children[node] = len(self.start), len(chosen)
            for i, head in enumerate(heads.tolist()):
                todo.append(len(self.start))
                for column, value in ((self.start, int(edge[i])), (self.stop, int(edge[i + 1])), (self.radius, 0.0), (self.child, 0), (self.children, 0), (centres, head)):
                    column.append(value)
        self._fixed(points[centres])

    def _fixed(self, centre: np.ndarray) -> None:
        self.start, self.stop, self.radius, self.child, self.children = (np.array(x) for x in (self.start, self.stop, self.radius, self.child, self.children))
        self.centre, self.norm = centre, np.sqrt((centre**2).sum(1))

    def below(self, nodes: np.ndarray) -> np.ndarray:
        """The children of some nodes."""
        many = self.children[nodes]
        return np.repeat(self.child[nodes] - (np.cumsum(many) - many), many) + np.arange(many.sum())


def packed(points: np.ndarray, leaf: int, **columns: np.ndarray) -> bytes:
    """A matrix with its tree, rows in the tree's order, and other columns of the same rows."""
    tree, out = Tree(points, leaf), io.BytesIO()
    rows = {k: v[tree.order] for k, v in columns.items()} | {"points": points[tree.order]}
    np.savez(out, **rows, start=tree.start, stop=tree.stop, radius=tree.radius, child=tree.child, children=tree.children, centre=tree.centre)
    return out.getvalue()


def unpacked(data: bytes) -> tuple[dict[str, np.ndarray], Tree]:
    with np.load(io.BytesIO(data), allow_pickle=False) as held:
        rows = {k: held[k] for k in held.files}
    tree = object.__new__(Tree)
    tree.order = np.arange(len(rows["points"]))
    for k in ("start", "stop", "radius", "child", "children"):
        setattr(tree, k, rows.pop(k))
    tree._fixed(rows.pop("centre"))
    return rows, tree


def reach(centre_q, radius_q, norm_q, centre_d, radius_d, norm_d):
    """The highest inner product that a row of one node can have with one of the other; a little is added for rounding."""
    bound = centre_q @ centre_d.T + radius_q * norm_d + radius_d * norm_q + radius_q * radius_d
    return bound + 1e-9 * np.abs(bound) + 1e-6


class Search:
    """The k best partners of every query of a block, so far. `scored` counts the pairs whose product was worked out."""

    def __init__(self, queries: np.ndarray, ids: np.ndarray, k: int):
        self.queries, self.ids, self.k, self.scored = queries, ids, k, 0
        self.scores = np.full((len(queries), k), -np.inf)
        self.found = np.full((len(queries), k), np.iinfo(np.int64).max)

    def run(self, q: Tree, d: Tree, points: np.ndarray, ids: np.ndarray, copy: np.ndarray) -> None:
        """points, ids and copy are in the order of the tree d.

        Each node of queries takes over the nodes of vectors that its parent could not rule out, opens those wider than
        itself, and rules out what it can; leaves of queries score what is left, the most promising first.
        """
        todo = [(0, np.array([0]))]
        while todo:
            a, nodes = todo.pop()
            asked = q.order[q.start[a] : q.stop[a]]
            worst = self.scores[asked, -1].min()
            nodes = nodes[self._bounds(q, a, d, nodes) >= worst]
            leaf = not q.children[a]
            while (wide := (d.children[nodes] > 0) & (leaf | (d.radius[nodes] > q.radius[a]))).any():
                nodes = np.concatenate([nodes[~wide], d.below(nodes[wide])])
                nodes = nodes[self._bounds(q, a, d, nodes) >= worst]
            if not leaf:
                todo += [(q.child[a] + i, nodes) for i in range(q.children[a])] if len(nodes) else []
                continue
            bounds = self._bounds(q, a, d, nodes)
            best = np.argsort(-bounds, kind="stable")
            for at in range(0, len(best), TOGETHER):
                part = best[at : at + TOGETHER]
                if bounds[part[0]] < self.scores[asked, -1].min():
                    break
                rows = np.concatenate([np.arange(d.start[n], d.stop[n]) for n in nodes[part].tolist()])
                self.score(asked, rows, points, ids, copy)

    @staticmethod
    def _bounds(q: Tree, a: int, d: Tree, nodes: np.ndarray) -> np.ndarray:
        return reach(q.centre[a], q.radius[a], q.norm[a], d.centre[nodes], d.radius[nodes], d.norm[nodes])

    def score(self, asked: np.ndarray, rows: np.ndarray, points: np.ndarray, ids: np.ndarray, copy: np.ndarray) -> None:
        part = points[rows]
        made = self.queries[asked] @ part.T
        self.scored += made.size
        same = (self.ids[asked][:, None] == ids[rows][None, :]) & (copy[rows] == 0)[None, :]
        for i, j in zip(*np.nonzero(same)) if same.any() else ():  # a query is no partner of its own
            if (self.queries[asked[i]] == part[j]).all():
                made[i, j] = -np.inf
        hits = made >= self.scores[asked, -1][:, None]
        some, columns = np.flatnonzero(hits.any(1)), np.flatnonzero(hits.any(0))
        if not len(some):
            return
        asked, made, names = asked[some], made[np.ix_(some, columns)], ids[rows[columns]]
        wide = np.hstack([self.scores[asked], made])
        names = np.hstack([self.found[asked], np.broadcast_to(names, made.shape)])
        order = np.lexsort((names, -wide), axis=-1)[:, : self.k]
        self.scores[asked] = np.take_along_axis(wide, order, 1)
        self.found[asked] = np.take_along_axis(names, order, 1)


def _matrix(rows: pd.DataFrame) -> np.ndarray:
    return np.array(rows["vec"].tolist(), np.float64).reshape(len(rows), -1)


def _centres(vectors: DataFrame, size: int) -> dict[int, np.ndarray]:
    """Centres of each sampled length, about one for every `size` vectors of it."""
    lengths = vectors.groupBy(F.size("vec").alias("dim")).count()
    hashed = F.xxhash64("id", "vec")
    few = vectors.where(share_of(vectors.count(), 1.5 * CENTRES_FROM, hashed))
    by_length: dict[int, list] = {}
    for r in few.select("vec", hashed.alias("h")).orderBy("h").limit(CENTRES_FROM).collect():
        by_length.setdefault(len(r["vec"]), []).append(r["vec"])
    per = lengths.where(F.col("dim").isin(list(by_length))).collect() if by_length else []
    many = {r["dim"]: min(CENTRES, -(-r["count"] // size)) for r in per}
    return {n: np.array(v)[farthest_first(np.array(v), many[n])[0]] for n, v in by_length.items()}


def _in_cells(vectors: DataFrame, size: int) -> DataFrame:
    """(id, vec, n, dim, cell): cell is the number of the nearest centre (0 where no vector of that length was sampled)."""
    centres = _centres(vectors, size)

    def run(batches):
        for b in batches:
            cell = np.zeros(len(b), np.int64)
            size = b["vec"].map(len).to_numpy()
            for n in np.unique(size).tolist():
                if n in centres:
                    x, c = _matrix(b[size == n]), centres[n]
                    cell[size == n] = ((c * c).sum(1)[None, :] - 2 * x @ c.T).argmin(1)
            yield b.assign(dim=size, cell=cell)

    return vectors.select("id", "vec", "n").mapInPandas(run, "id long, vec array<double>, n long, dim long, cell long")


def _blocks(rows: DataFrame, size: int, copies: bool) -> DataFrame:
    """(dim, cell, sub, centre, radius, size, tree): rows (id, vec, n, dim, cell) in blocks of about `size`, each with its tree."""
    if copies:
        rows = rows.withColumn("copy", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1)))
    else:
        rows = rows.withColumn("copy", F.lit(0).cast("long"))
    per = rows.groupBy("dim", "cell").agg(F.ceil(F.count(F.lit(1)) / size).alias("subs"))
    dealt = rows.join(per, ["dim", "cell"]).withColumn("sub", F.pmod(F.xxhash64("id", "vec", "copy"), F.col("subs")))

    def pack(key, rows):
        rows = rows.sort_values(["id", "copy"], kind="stable")
        points = _matrix(rows)
        held = packed(points, LEAF if copies else QUERY_LEAF, **{c: rows[c].to_numpy(np.int64) for c in ("id", "copy", "n")})
        centre = points.mean(0)
        radius = float(np.sqrt(((points - centre) ** 2).sum(1)).max())
        return pd.DataFrame([(*key, centre.tolist(), radius, len(rows), held)], columns=["dim", "cell", "sub", "centre", "radius", "size", "tree"])

    by_block = dealt.select("dim", "cell", "sub", "id", "vec", "n", "copy").groupBy("dim", "cell", "sub")
    return by_block.applyInPandas(pack, "dim long, cell long, sub long, centre array<double>, radius double, size long, tree binary")


def _dot(a: str, b: str) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def _may_reach(worst: Column) -> Column:
    """Whether rows of a block (centre, radius) can reach `worst` with queries of (q_centre, q_radius)."""
    norm = F.sqrt(_dot("centre", "centre"))
    q_norm = F.sqrt(_dot("q_centre", "q_centre"))
    bound = _dot("centre", "q_centre") + F.col("q_radius") * norm + F.col("radius") * q_norm + F.col("q_radius") * F.col("radius")
    return bound + F.abs(bound) * 1e-9 + 1e-6 >= worst


def cells_of(blocks: DataFrame) -> DataFrame:
    """(dim, cell, centre, radius): for each cell the ball around its first block's centre that covers all its blocks."""
    middle = blocks.groupBy("dim", "cell").agg(F.min_by("centre", "sub").alias("m"))
    off = F.sqrt(F.aggregate(F.zip_with("centre", "m", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))
    return blocks.join(middle, ["dim", "cell"]).groupBy("dim", "cell").agg(F.first("m").alias("centre"), F.max(off + F.col("radius")).alias("radius"))


def meetings(asks: DataFrame, blocks: DataFrame) -> DataFrame:
    """(dim, ask, cell, sub): which blocks of vectors each block of queries has to search after the first of its home cell.

    asks: (dim, ask, home, q_centre, q_radius, worst); blocks: (dim, cell, sub, centre, radius). Cells are ruled out first.
    """
    near = asks.join(cells_of(blocks), "dim").where(_may_reach(F.col("worst"))).select("dim", "ask", "home", "cell", "q_centre", "q_radius", "worst")
    pairs = near.join(blocks, ["dim", "cell"]).where(_may_reach(F.col("worst")))
    return pairs.where((F.col("cell") != F.col("home")) | (F.col("sub") != 0)).select("dim", "ask", "cell", "sub")


_FOUND = "dim long, ask long, at long, query_id long, n long, id long, score double"


def _rows(dim: int, ask: int, found: Search, n: np.ndarray) -> pd.DataFrame:
    i, j = np.nonzero(np.isfinite(found.scores) & (found.found != np.iinfo(np.int64).max))
    return pd.DataFrame({"dim": dim, "ask": ask, "at": i, "query_id": found.ids[i], "n": n[i], "id": found.found[i, j], "score": found.scores[i, j]})


def top_k(vectors: DataFrame, is_query: Column, k: int = 10) -> DataFrame:
    """(id long, vec array<double>, n long), finite, n rows alike -> (query_id, rank, id, score), score as double."""
    found = F.least("n", F.lit(k + 1).cast("long"))  # of more equal rows than that no list has a place for
    blocks = cut(_blocks(_in_cells(vectors.withColumn("n", found), BLOCK), BLOCK, True), "top-vectors")
    asked = _blocks(_in_cells(vectors.where(is_query), QUERY_BLOCK), QUERY_BLOCK, False)
    number = F.col("cell") * (1 << 32) + F.col("sub")
    asked = cut(asked.select("dim", number.alias("ask"), F.col("centre").alias("q_centre"), F.col("radius").alias("q_radius"), "size", F.col("tree").alias("q_tree")), "top-queries")
    promise = asked.select("dim", "ask", "q_centre").join(cells_of(blocks), "dim").groupBy("dim", "ask").agg(F.max_by("cell", F.struct(_dot("q_centre", "centre"), "cell")).alias("home"))
    asked = asked.join(promise, ["dim", "ask"])

    def search(asks: dict, q: Tree, rows: dict, d: Tree, worst: np.ndarray | None = None) -> Search:
        one = Search(asks["points"], asks["id"], k)
        if worst is not None:
            one.scores[:] = worst[:, None]  # what is known already; places without an id are no results
        one.run(q, d, rows["points"], rows["id"], rows["copy"])
        return one

    def first(batches):
        for b in batches:
            for r in b.itertuples():
                asks, q = unpacked(r.q_tree)
                one = search(asks, q, *unpacked(r.tree))
                out = _rows(r.dim, r.ask, one, asks["n"])
                yield out.assign(worst=one.scores[out["at"].to_numpy(np.int64), -1])

    home = asked.join(blocks.where("sub = 0").select("dim", F.col("cell").alias("home"), "tree"), ["dim", "home"])
    begun = cut(home.select("dim", "ask", "q_tree", "tree").mapInPandas(first, f"{_FOUND}, worst double"), "top-first")

    # A query's worst score so far, and that of its block; queries without k partners yet have none.
    per = begun.groupBy("dim", "ask", "at").agg(F.max("worst").alias("worst"))
    state = per.groupBy("dim", "ask").agg(F.min("worst").alias("least"), F.count(F.lit(1)).alias("known"), F.collect_list(F.struct("at", "worst")).alias("worsts"))
    asks = cut(asked.join(state, ["dim", "ask"], "left"), "top-asks")
    infinite = F.lit(float("-inf"))
    light = asks.select("dim", "ask", "home", "q_centre", "q_radius", F.coalesce("least", infinite).alias("worst"))
    pairs = meetings(light, blocks.select("dim", "cell", "sub", "centre", "radius"))
    groups = Window.partitionBy("dim", "cell", "sub").orderBy("ask")
    pairs = cut(pairs.withColumn("party", F.floor((F.row_number().over(groups) - 1) / ASKS)), "top-pairs")
    sent = pairs.join(asks.select("dim", "ask", "size", "q_tree", "worsts"), ["dim", "ask"])
    key = ["dim", "cell", "sub", "party"]
    wanted = pairs.groupBy(*key).count().join(blocks.select("dim", "cell", "sub", "tree"), key[:3])
    wanted = wanted.select(*[F.col(c).alias(f"{c}_") for c in key], "tree")

    def rest(queries, block):
        out = [pd.DataFrame({c.split()[0]: [] for c in _FOUND.split(", ")})]
        rows, d = unpacked(block["tree"].iloc[0]) if len(block) else (None, None)
        for r in queries.itertuples() if rows else ():
            worst = np.full(r.size, -np.inf)
            for w in r.worsts if r.worsts is not None else ():
                worst[w["at"]] = w["worst"]
            asks, q = unpacked(r.q_tree)
            out.append(_rows(r.dim, r.ask, search(asks, q, rows, d, worst), asks["n"]))
        return pd.concat(out)

    more = sent.groupBy(*key).cogroup(wanted.groupBy(*[f"{c}_" for c in key])).applyInPandas(rest, _FOUND)
    best = begun.drop("worst").unionByName(more)
    rank = F.row_number().over(Window.partitionBy("dim", "ask", "at").orderBy(F.desc("score"), "id"))
    best = best.withColumn("rank", rank).where(F.col("rank") <= k)
    return best.withColumn("_", F.explode(F.sequence(F.lit(1).cast("long"), F.col("n")))).select("query_id", "rank", "id", "score")


def integer_vectors(embeddings: DataFrame, scale: int = 1024) -> DataFrame:
    """(id, vec, n): the whole-number vectors of all usable rows; n rows are alike."""
    whole = F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    vec = F.transform("embedding", lambda x: F.floor(F.lit(scale) * x.cast("double")).cast("double"))
    usable = embeddings.where(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull()).where(whole)
    return usable.select(long_id(embeddings, "vec_id").alias("id"), vec.alias("vec")).groupBy("id", "vec").agg(F.count(F.lit(1)).alias("n"))


def query(spark, sf_dir):
    from .common import table

    vectors = cut(integer_vectors(table(spark, sf_dir, "embeddings").select("vec_id", "embedding")), "whole-vectors")
    found = top_k(vectors, F.pmod(F.col("id"), F.lit(100)) == 0)
    return found.select("query_id", F.col("rank").cast("int").alias("rank"), F.col("id").alias("vec_id"), F.col("score").cast("long").alias("score"))


SQL = """
WITH v AS (
  SELECT row_number() OVER () AS row, vec_id AS id, list_transform(embedding, lambda x: floor(1024 * x::DOUBLE)) AS v
  FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (
  SELECT q.row, q.id AS query_id, d.id AS vec_id, CASE WHEN len(q.v) = len(d.v) THEN list_dot_product(q.v, d.v) END::BIGINT AS score
  FROM v q JOIN v d ON q.id % 100 = 0 AND q.row <> d.row AND len(q.v) = len(d.v)),
r AS (SELECT *, row_number() OVER (PARTITION BY row ORDER BY score DESC, vec_id)::INTEGER AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 10
"""
