"""Worked examples, closed forms, gradients, brute force and invariants of the methods."""

import math

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from groupstream import queries as own
from groupstream.baselines import aggregate
from groupstream.encoder import layers, relevance, training
from groupstream.evaluation import measures
from groupstream.features import tags
from groupstream.forecast import interest, recurrent
from groupstream.functions.hashing import next_prime, universal_hash
from groupstream.index import best, blocks, exhaustive, fastmap, lsh, search
from groupstream.index.build import GroupIndex
from groupstream.influence import cascade, dense, factors, prop_graph
from groupstream.model import relation_graph
from groupstream.operators import joins
from groupstream.operators.joins import asof, positions
from groupstream.plans.catalog_sampling import SHARE
from groupstream.plans.pipeline import Pipeline
from groupstream.sampling import clusters, draw, estimators, overlap


def frame(spark, rows, schema):
    return spark.createDataFrame(rows, schema)


def test_laplacian_of_a_path(spark):
    path = relation_graph.symmetric(frame(spark, [(1, 2), (2, 3)], "a long, b long"))
    rows = relation_graph.laplacian_weights(path).collect()
    assert all(r.lap == pytest.approx(1 / math.sqrt(2)) for r in rows)


def test_item_refresh(spark):
    items = frame(spark, [(1, [1.0, 0.0]), (2, [1.0, 0.0])], "v long, vec array<double>")
    fresh = frame(spark, [(7, 1), (8, 1)], "g long, v long")
    groups = frame(spark, [(7, [0.0, 1.0]), (8, [1.0, 1.0])], "g long, vec array<double>")
    kept = {r.v: r.vec for r in layers.refresh_items(items, fresh, groups, 0.8, 2).collect()}
    assert kept[1] == pytest.approx([0.9, 0.2]) and kept[2] == [1.0, 0.0]
    shrunk = {r.v: r.vec for r in layers.refresh_items(items, fresh, groups, 0.8, 2, "shrink").collect()}
    assert shrunk[2] == pytest.approx([0.8, 0.0])
    with pytest.raises(ValueError):
        layers.refresh_items(items, fresh, groups, 1.5, 2)


def test_edge_weight(spark):
    row = frame(spark, [(1, 1, 2, 0.5, 0.4, 0.8, 0.6, 0.0)], "v long, src long, dst long, a_src double, w_src double, w_dst double, sim double, p double")
    value = lambda **kw: row.select(factors.weight(**kw).alias("p")).first().p
    assert value() == pytest.approx(0.60)
    assert value(drop="similarity") == pytest.approx(0.18)
    after = prop_graph.apply_updates(row, frame(spark, [(1, 1)], "v long, g long"), frame(spark, [(1, 0.6)], "g long, act double")).first()
    assert after.p == pytest.approx(0.64) and after.sim == 0.6
    with pytest.raises(ValueError):
        factors.weight(0.6, 0.6)


def test_optimal_probabilities(spark):
    edges = frame(spark, [(1, 2, 0, 0, 3.0), (1, 3, 0, 0, 1.0)], "a long, b long, ci long, cj long, score double")
    quotas = frame(spark, [(0, 0, 1)], "ci long, cj long, num long")
    best = draw.inclusion(draw.draw_probability(edges, "optimal", edges.select("a", "b", "score")), quotas)
    assert {r.b: r.p for r in best.collect()} == pytest.approx({2: 0.75, 3: 0.25})
    assert estimators.variance(best).first().variance == pytest.approx(6)
    assert estimators.least_variance(edges, 1).first().bound == pytest.approx(6)
    even = edges.withColumn("p", F.lit(0.5))
    assert estimators.variance(even).first().variance == pytest.approx(10)


def test_capped_edges(spark):
    edges = frame(spark, [(1, 2, 0, 0, 10.0), (1, 3, 0, 0, 1.0), (1, 4, 0, 0, 1.0)], "a long, b long, ci long, cj long, score double")
    found = draw.inclusion(draw.draw_probability(edges, "optimal", edges), frame(spark, [(0, 0, 2)], "ci long, cj long, num long"))
    assert {r.b: r.p for r in found.collect()} == pytest.approx({2: 1.0, 3: 0.5, 4: 0.5})


def random_graph(spark, n=20, share=0.3, seed=1):
    rng = np.random.default_rng(seed)
    pairs = [(i, j) for i in range(n) for j in range(i + 1, n) if rng.random() < share]
    edges = relation_graph.laplacian_weights(relation_graph.symmetric(frame(spark, pairs, "a long, b long")))
    half = edges.where("src < dst").select(F.col("src").alias("a"), F.col("dst").alias("b"), "lap", F.col("deg_src").alias("deg_a"), F.col("deg_dst").alias("deg_b"))
    x = frame(spark, [(i, rng.random(3).tolist()) for i in range(n)], "g long, vec array<double>")
    return clusters.edge_sets(half, clusters.cluster_by_column(x, F.lit(0))), x


def test_estimator_is_unbiased_with_the_variance_of_the_closed_form(spark):
    edges, x = random_graph(spark)
    scored = estimators.edge_scores(edges, [x], 3)
    quotas = clusters.allocate(edges, 0.4)
    found = scored.join(draw.inclusion(draw.draw_probability(edges, "laplacian"), quotas).select("a", "b", "p"), ["a", "b"])
    rows = found.collect()
    c, p = np.array([r.c for r in rows]), np.array([r.p for r in rows])
    rng = np.random.default_rng(0)
    draws = np.array([((rng.random(len(p)) < p) / p) @ c for _ in range(4000)])
    error = draws.std(0) / math.sqrt(len(draws))
    assert (abs(draws.mean(0) - c.sum(0)) < 4 * error).all()
    assert ((draws - c.sum(0)) ** 2).sum(1).mean() == pytest.approx(estimators.variance(found).first().variance, rel=0.1)
    assert p.sum() == pytest.approx(quotas.first().num)


def test_optimal_draw_has_the_least_variance_and_the_bounds_hold(spark):
    edges, x = random_graph(spark)
    scored = estimators.edge_scores(edges, [x], 3)
    quotas = clusters.allocate(edges, 0.3)
    got = {}
    for kind in ("optimal", "laplacian", "uniform", "degree_sum"):
        p = draw.inclusion(draw.draw_probability(edges, kind, scored), quotas).select("a", "b", "p")
        got[kind] = estimators.variance(scored.join(p, ["a", "b"])).first().variance
    assert got["optimal"] == min(got.values())
    assert estimators.approx_bounds(scored, 1, 3).where("not holds").isEmpty()


def test_snapshot_sampler_invariants(spark):
    edges, _ = random_graph(spark)
    counts = frame(spark, [(g, s, 1 + (g * s) % 3) for g in range(20) for s in range(3)], "g long, slice int, n long")
    seq = overlap.snapshot_sequence(edges, counts, 3, 0.4, 0.5).collect()
    num = clusters.allocate(edges, 0.4).first().num
    by = {t: {(r.a, r.b): r.origin for r in seq if r.slice == t} for t in range(3)}
    assert all(len(by[t]) == num for t in by)
    for t in (1, 2):
        assert all((o == "overlap") == (e in by[t - 1]) for e, o in by[t].items())
    alone = overlap.snapshot_sequence(edges, counts, 2, 0.4, 0.0).where("slice = 1")
    assert {r.origin for r in alone.collect()} == {"fresh"}
    full = {(r.a, r.b) for r in edges.collect()}
    reuse = overlap.snapshot_sequence(edges, counts, 2, 0.4, 1.0).collect()
    assert {(r.a, r.b) for r in reuse if r.slice == 1} == {(r.a, r.b) for r in reuse if r.slice == 0}
    assert {(r.a, r.b) for r in overlap.snapshot_sequence(edges, counts, 1, 1.0, 0.5).collect()} == full
    assert overlap.snapshot_sequence(edges.limit(0), counts, 2, 0.4, 0.5).collect() == []


def test_clusters_and_tags_bring_like_things_together(spark):
    groups, items = planted(spark)
    found = {r.g: r.cluster for r in clusters.cluster_nodes(groups, 8, seed=4).collect()}
    rows = {r.g: np.array(r.vec) for r in groups.collect()}
    centre = {c: np.mean([rows[g] for g in rows if found[g] == c], axis=0) for c in set(found.values())}
    assert all(min(centre, key=lambda c: ((rows[g] - centre[c]) ** 2).sum()) == found[g] for g in rows)
    lists = [["red", "wool", "hat"], ["red", "wool", "scarf"], ["steel", "bolt", "nut"], ["steel", "bolt", "screw"]] * 30
    learned = [np.array(r.vec) for r in sorted(tags.tag_vectors(frame(spark, list(enumerate(lists)), "v long, tags array<string>"), 8).collect(), key=lambda r: r.v)]
    assert len(learned) == 120 and all(len(x) == 8 and np.isfinite(x).all() for x in learned)
    assert (learned[0] == learned[4]).all() and (learned[0] != learned[2]).any()


def test_pipeline_trains_on_the_last_slice(spark):
    edges, _ = random_graph(spark)
    late = frame(spark, [(g, 0 if g < 2 else 3, 1) for g in range(20)], "g long, slice int, n long")
    run = object.__new__(Pipeline)
    run.__dict__.update(sampler=True, und=edges, counts=late, quotas=clusters.allocate(edges, SHARE))
    got = run.training_edges().collect()
    assert len(got) == 2 * clusters.allocate(edges, SHARE).first().num
    assert {r.src for r in got} - {0, 1}


EDGES = "v long, src long, dst long, a_src double, w_src double, w_dst double, sim double, p double"


def graph(spark, edges):
    return frame(spark, [(1, a, b, 0.0, 0.0, 0.0, 0.0, p) for a, b, p in edges], EDGES)


def test_cascade_worked_example(spark):
    g = graph(spark, [(1, 2, 0.6), (2, 3, 0.4), (1, 4, 0.2)])
    seeds = frame(spark, [(0, 1, 1)], "s long, v long, g long")
    found = cascade.run(g, seeds, mode="fixed", tau=0.5)
    assert {r.g for r in found.collect()} == {1, 2}
    assert cascade.spread(found, 4).first().influence == 0.5
    batches = [(frame(spark, [(1, 3)], "v long, g long"), frame(spark, [(3, 0.0)], "g long, act double"))]
    dynamic = cascade.run_dynamic(g, seeds, batches, mode="fixed", tau=0.5)
    assert {r.g for r in dynamic.collect()} == {1, 2, 3}


def test_cascade_ends_on_a_cycle(spark):
    g = graph(spark, [(1, 2, 1.0), (2, 3, 1.0), (3, 1, 1.0)])
    found = cascade.run(g, frame(spark, [(0, 1, 1)], "s long, v long, g long"), mode="fixed", tau=0.5).collect()
    assert sorted((r.g, r.round) for r in found) == [(1, 0), (2, 1), (3, 2)]


def test_gradients_of_the_encoder():
    rng = np.random.default_rng(0)
    w = training.new_weights(3, 4, 5, 2)
    xg, xv = rng.normal(size=(6, 4)), rng.normal(size=(7, 5))
    src, dst, lap = np.array([0, 1, 2, 3, 1]), np.array([1, 0, 3, 2, 4]), rng.random(5)
    owner, held = np.array([0, 0, 1, 3, 3, 3, 4, 5]), np.array([0, 1, 2, 3, 4, 5, 6, 0])
    g, pos, neg = np.array([0, 1, 3, 5]), np.array([0, 2, 4, 1]), np.array([5, 6, 0, 2])
    run = lambda: training.loss_and_gradients(w, xg, xv, src, dst, lap, owner, held, g, pos, neg, 2, 1e-3)
    _, grads = run()
    for k in w:
        for at in [tuple(rng.integers(0, n) for n in w[k].shape) for _ in range(3)]:
            keep = w[k][at]
            w[k][at] = keep + 1e-6
            up = run()[0]
            w[k][at] = keep - 1e-6
            down = run()[0]
            w[k][at] = keep
            assert grads[k][at] == pytest.approx((up - down) / 2e-6, rel=1e-4, abs=1e-6)


def test_shards_add_up_to_the_whole_graph(spark):
    edges, _ = random_graph(spark, 30, 0.15)
    rng = np.random.default_rng(4)
    groups = frame(spark, [(i, rng.normal(size=5).tolist()) for i in range(30)], "g long, vec array<double>")
    items = frame(spark, [(i, rng.normal(size=4).tolist()) for i in range(40)], "v long, vec array<double>")
    both = relation_graph.symmetric(edges, "lap")
    seen = frame(spark, [(int(g), int(v), int(s)) for g, v, s in zip(rng.integers(0, 30, 150), rng.integers(0, 40, 150), rng.integers(0, 2, 150))], "g long, v long, slice int").dropDuplicates(["g", "v"])
    triples = relevance.training_triples(seen, items, keep=("slice",))
    graphs = both.withColumn("slice", F.lit(0)).unionByName(both.where("src < 20 and dst < 20").withColumn("slice", F.lit(1)))
    w = training.new_weights(3, 5, 4, 2)
    packs = [training.shards(groups, items, graphs, seen, triples, n).persist() for n in (1, 4)]
    for t, new_only in ((0, False), (1, False), (1, True)):
        (loss, grads, n), (loss4, grads4, n4) = (training.gradients(p, w, 2, t, new_only) for p in packs)
        assert n == n4 > 0 and loss == pytest.approx(loss4) and all(grads[k] == pytest.approx(grads4[k]) for k in w)
        parts = [training.gradients(packs[1], w, 2, t, new_only, batch, 3) for batch in range(3)]
        assert sum(p[2] for p in parts) == n and sum(p[0] for p in parts) == pytest.approx(loss)
    # The kernel's layers are those of the column expressions.
    first = groups.select("g", layers.dense(w["wg"].tolist(), F.col("vec"), w["bg"].tolist()).alias("vec"))
    want = layers.encode_groups(both, first, [(w["w1"].tolist(), w["b1"].tolist()), (w["w2"].tolist(), w["b2"].tolist())], 3)
    got = {r.g: r.vec for r in training.encode(packs[1], w, 2, 0).collect()}
    assert len(got) == 30 and all(got[r.g] == pytest.approx(r.vec) for r in want.collect())
    start, end = (training.train(p, w, 2, 1e-1, 1e-3, 2, batches=2, t=1)[1] for p in packs)
    assert [r["loss"] for r in start] == pytest.approx([r["loss"] for r in end])


def test_learning_finds_planted_interests(spark):
    """Groups of four communities, each with items of its own: what was learned ranks unseen items of the right kind higher."""
    rng = np.random.default_rng(6)
    kind = lambda x: x % 4
    groups = frame(spark, [(g, (np.eye(4)[kind(g)] + 0.3 * rng.normal(size=4)).tolist()) for g in range(40)], "g long, vec array<double>")
    items = frame(spark, [(v, (np.eye(4)[kind(v)] + 0.3 * rng.normal(size=4)).tolist()) for v in range(80)], "v long, vec array<double>")
    rows = [(g, int(v), int(rng.integers(0, 3))) for g in range(40) for v in rng.choice([x for x in range(80) if kind(x) == kind(g)], 8, replace=False)]
    seen = frame(spark, rows, "g long, v long, slice int")
    pairs = [(a, b) for a in range(40) for b in range(a + 1, 40) if kind(a) == kind(b) and rng.random() < 0.4]
    lap = relation_graph.laplacian_weights(relation_graph.symmetric(frame(spark, pairs, "a long, b long")))
    graphs = lap.select(F.explode(F.array(*[F.lit(t) for t in range(3)])).alias("slice"), "src", "dst", "lap")
    made = interest.learn(groups, items, graphs, seen, 3, 6, epochs=30, shards=2)
    assert {r["phase"] for r in made.log} == {"long", "short", "forecast"} and made.profiles.count() == 120
    vectors = {r.v: np.array(r.vec) for r in made.items(items).collect()}

    def right(found) -> float:
        """How often an unseen item of the group's kind scores above one of another kind."""
        old, wins, n = {(g, v) for g, v, _ in rows}, 0, 0
        for r in found.collect():
            own = np.array(r.vec) + sum(vectors[v] for g, v in old if g == r.g) / 8**0.5
            score = {v: own @ x for v, x in vectors.items() if (r.g, v) not in old}
            for a in (v for v in score if kind(v) == kind(r.g)):
                wins, n = wins + sum(score[a] > score[b] for b in score if kind(b) != kind(r.g)), n + sum(kind(b) != kind(r.g) for b in score)
        return wins / n

    assert right(made.last()) > 0.8 and right(made.predicted()) > 0.8
    long = [r["loss"] for r in made.log if r["phase"] == "long"]
    assert long[-1] < long[0]


def test_a_little_influence_decides_between_equals(spark):
    groups = frame(spark, [(1, [0.5, 0.5]), (2, [0.5, 0.5]), (3, [0.5, 0.5])], "g long, vec array<double>")
    items = frame(spark, [(1, [1.0, 0.0])], "v long, vec array<double>")
    influence = frame(spark, [(1, 0.01), (2, 0.03), (3, 0.02)], "g long, influence double")
    g, v = relevance.augment(groups, items, influence, 1e-6)
    assert [r.g for r in sorted(relevance.top_k(relevance.relevance(g, v, 3), 3).collect(), key=lambda r: r["rank"])] == [2, 3, 1]


def test_recall_of_best_blocks(spark):
    rng = np.random.default_rng(8)
    groups = frame(spark, [(i, (0.3 * rng.normal(size=6)).tolist()) for i in range(4000)], "g long, vec array<double>")
    items = frame(spark, [(i, rng.normal(size=6).tolist()) for i in range(30)], "v long, vec array<double>")
    index = GroupIndex.build(groups, 6, axes=7, n_hash=7, bits=6, width=None, rows_per_block=8, buckets=64)
    exact = search.batch_match(groups, items, 20, 6).persist()
    recalls = [measures.recall_at_k(index.top_k(items, 20, b, on_miss="scan"), exact, 20).first().recall for b in (100, 600, 4000)]
    assert recalls == sorted(recalls) and recalls[1] >= 0.9 and recalls[2] == 1.0


def test_the_index_follows_changed_groups(spark):
    groups, items = planted(spark)
    index = GroupIndex.build(groups, 4, 3, 3, 6, 0.5, 8, 16)
    before = {r.block: bytes(r.matrix) for r in index.packed().collect()}
    rng = np.random.default_rng(1)
    moved = [(g, (3 * rng.normal(size=4)).tolist()) for g in (0, 5, 40)] + [(1000 + i, (2 + 0.01 * rng.normal(size=4)).tolist()) for i in range(20)]
    changed = frame(spark, moved, "g long, vec array<double>")
    index.update(changed)
    now = groups.join(changed.select("g"), "g", "left_anti").unionByName(changed)
    exact = search.batch_match(now, items, 10, 4)
    assert sorted(map(tuple, index.top_k(items, 10, 10_000, on_miss="scan").collect())) == sorted(map(tuple, exact.collect()))
    after = {r.block: (bytes(r.matrix), r.n) for r in index.packed().collect()}
    assert sum(n for _, n in after.values()) == now.count() == index.held.count() and max(n for _, n in after.values()) <= 24
    assert sum(after.get(b, (None,))[0] == m for b, m in before.items()) >= len(before) // 2
    index.update(changed.limit(0))
    index.update(frame(spark, [(1000, [0.0] * 4)], "g long, vec array<double>"))
    assert index.held.groupBy("g").count().where("count > 1").isEmpty() and index.held.count() == now.count()


@pytest.mark.parametrize("cell", ["rnn", "gru"])
def test_gradients_of_the_forecaster(cell):
    rng = np.random.default_rng(0)
    w = recurrent.new_weights(3, 4, cell)
    x, y = rng.normal(size=(5, 3, 3)), rng.normal(size=(5, 3))
    _, grads = recurrent.loss_and_gradients(w, x, y, 1e-3)
    for k in w:
        at = tuple(rng.integers(0, n) for n in w[k].shape)
        keep = w[k][at]
        w[k][at] = keep + 1e-6
        up = recurrent.loss_and_gradients(w, x, y, 1e-3)[0]
        w[k][at] = keep - 1e-6
        down = recurrent.loss_and_gradients(w, x, y, 1e-3)[0]
        w[k][at] = keep
        assert grads[k][at] == pytest.approx((up - down) / 2e-6, rel=1e-4, abs=1e-6)


def test_fastmap_and_zorder(spark):
    pivot = {"x": {"vec": [0.0, 0.0], "coords": []}, "y": {"vec": [5.0, 0.0], "coords": []}, "gap": 5.0}
    point = frame(spark, [(1, [1.8, 2.4])], "g long, vec array<double>")  # 3 from one pivot, 4 from the other
    assert fastmap.project(point, [pivot], 2).first().xs[0] == pytest.approx(1.8)
    assert fastmap.project(point, [pivot], 2, "printed").first().xs[0] == pytest.approx(3.0)
    cells = frame(spark, [([5, 3],), ([0, 0],), ([7, 7],)], "c array<long>")
    assert [r[0] for r in cells.select(lsh.interleave(F.col("c"), 2, 3)).collect()] == [39, 0, 63]


def test_universal_hash(spark):
    keys = frame(spark, [(29,), (130,)], "k long")
    assert [r[0] for r in keys.select(universal_hash(F.col("k"), 7, 3, 101, 8)).collect()] == [4, 4]
    assert [next_prime(n) for n in (1, 14, 97)] == [2, 17, 97]


def test_measures(spark):
    recs = frame(spark, [(1, 1, 10), (1, 2, 11), (1, 3, 12)], "v long, rank int, g long")
    one = frame(spark, [(1, 12)], "v long, g long")
    two = frame(spark, [(1, 10), (1, 12)], "v long, g long")
    assert measures.ndcg(recs, one, 3).first().ndcg == pytest.approx(0.5)
    assert measures.ndcg(recs, two, 3).first().ndcg == pytest.approx(0.9197, abs=1e-4)
    assert measures.hit_ratio(recs, two, 1).first().hr == 0.5
    assert measures.relative_change(0.3026, 0.3221) == pytest.approx(-6.05, abs=0.01)


def test_relevance_worked_example(spark):
    groups = frame(spark, [(1, [0.5, 0.5])], "g long, vec array<double>")
    items = frame(spark, [(1, [1.0, 0.0]), (2, [0.5, 0.0])], "v long, vec array<double>")
    history = relevance.history_vectors(frame(spark, [(1, 2)], "g long, v long"), items, 2)
    g, v = relevance.augment(relevance.group_side(groups, history, 2), items, frame(spark, [(1, 0.2)], "g long, influence double"), 0.5)
    assert relevance.relevance(g, v.where("v = 1"), 3).first().score == pytest.approx(0.6)


def planted(spark, communities=8, per=12, d=4, seed=2):
    rng = np.random.default_rng(seed)
    centres = rng.normal(size=(communities, d))
    groups = [(c * per + i, (centres[c] + 0.05 * rng.normal(size=d)).tolist()) for c in range(communities) for i in range(per)]
    items = [(c, centres[c].tolist()) for c in range(communities)]
    return frame(spark, groups, "g long, vec array<double>"), frame(spark, items, "v long, vec array<double>")


def test_index_against_the_exhaustive_way(spark):
    groups, items = planted(spark)
    exact = search.batch_match(groups, items, 10, 4)
    index = GroupIndex.build(groups, 4, 3, 3, 6, 0.5, 8, 16)
    n = groups.count()
    whole = index.top_k(items, 10, 2 * n)
    assert sorted(map(tuple, whole.collect())) == sorted(map(tuple, exact.collect()))
    recalls = [measures.recall_at_k(index.top_k(items, 10, b), exact, 10).first().recall for b in (20, 60, 2 * n)]
    assert recalls == sorted(recalls) and recalls[-1] == 1.0
    laid = sorted((r.pos, r.z, r.g) for r in index.blocks.collect())
    assert [p for p, _, _ in laid] == list(range(n)) and [(z, g) for _, z, g in laid] == sorted((z, g) for _, z, g in laid)
    stats = blocks.directory_stats(index.directory, 16).first()
    assert stats["keys"] == len({z for _, z, _ in laid})
    assert sorted(map(tuple, index.tree_top_k(items, 10, 40).collect())) == sorted(map(tuple, index.top_k(items, 10, 40).collect()))


def test_exhaustive_blocks_rank_as_columns_do(spark, monkeypatch):
    """Many ties, more groups than a block and fewer than k in a task: the lists are those of all pairs, and no task sends on more."""
    monkeypatch.setattr(exhaustive, "GROUPS", 64)
    monkeypatch.setattr(exhaustive, "ITEMS", 8)
    rng = np.random.default_rng(5)
    pool = rng.normal(size=(40, 8)).tolist()
    groups = frame(spark, [(i * 7 % 601, pool[i % 40]) for i in range(600)], "g long, vec array<double>").repartition(5)
    items = frame(spark, [(i, rng.normal(size=8).tolist()) for i in range(30)], "v long, vec array<double>")
    want = relevance.top_k(relevance.relevance(groups, items, 8), 20)
    found = search.batch_match(groups, items, 20, 8)
    assert sorted(found.collect()) == sorted(want.collect()) and found.count() == 600
    sent = exhaustive._window(groups, items.collect(), 20).count()
    assert sent <= 5 * 30 * 20 < 600 * 30


def test_item_neighbours_in_passes(spark, monkeypatch):
    """Several passes and parts give what one count of all pairs gives, and no pair is shuffled."""
    rng = np.random.default_rng(2)
    rows = {(int(u), int(v)) for u, v in zip(rng.integers(0, 60, 900), rng.integers(0, 40, 900))} | {(99, 500), (98, 500), (98, 501)}
    n = {}
    for u, v in rows:
        for w, other in rows:
            if u == w and v != other:
                n[v, other] = n.get((v, other), 0) + 1
    want = []
    for v in {v for v, _ in n}:
        ranked = sorted((-c, other) for (x, other), c in n.items() if x == v)[:10]
        want += [(v, i, other, -c) for i, (c, other) in enumerate(ranked, 1)]
    monkeypatch.setattr(aggregate, "PAIRS", 4000)
    monkeypatch.setattr(aggregate, "TOGETHER", 1000)
    found = aggregate.item_neighbours(frame(spark, sorted(rows), "u long, v long"))
    assert sorted(map(tuple, found.collect())) == sorted(want)
    monkeypatch.setattr(aggregate, "PAIRS", 1 << 28)
    whole = aggregate.item_neighbours(frame(spark, sorted(rows), "u long, v long"))
    assert sorted(map(tuple, whole.collect())) == sorted(want)
    assert "hashpartitioning(part" in whole._jdf.queryExecution().toString() and "hashpartitioning(v" not in whole._jdf.queryExecution().toString()


@pytest.mark.parametrize("name", ["next_prime", "relative_change", "synthetic_arrivals"])
def test_queries_read_their_table(spark, small, name):
    assert any("parquet" in f.lower() for f in own.queries()[name](spark, small).inputFiles())


def test_replayed_streams_keep_off_the_driver(spark, small):
    for name in ("stream_sessions", "stream_tumbling", "stream_dedup", "stream_group_state"):
        plan = own.queries()[name](spark, small)._jdf.queryExecution().toString()
        assert "MemoryPlan" not in plan and "replay-" in plan


def test_runs_with_other_rates_share_the_training_rows(spark, small, monkeypatch):
    made = []
    monkeypatch.setattr(interest, "learn", lambda *a, packed=None, **kw: packed)
    monkeypatch.setattr(interest, "packed_slices", lambda *a: made.append(a) or len(made))
    base = Pipeline(spark, small)
    assert [Pipeline(spark, small, base=base, learning={"rate": r}).interest for r in (0.01, 0.1)] == [1, 1]
    assert Pipeline(spark, small, base=base, layers=1).interest == 2 and Pipeline(spark, small, base=base, sampler=False).interest == 3


def test_asof_and_positions(spark, monkeypatch):
    rng = np.random.default_rng(0)
    known, asked = sorted(set(rng.integers(100, 900, 40).tolist())), rng.integers(0, 1000, 60).tolist()
    left, right = frame(spark, [(i, k) for i, k in enumerate(asked)], "i long, z long"), frame(spark, [(k,) for k in known], "key long")
    for nearest, spans in ((False, 4096), (True, 4096), (False, 3), (True, 3)):
        monkeypatch.setattr(joins, "SPANS", spans)
        for r in asof(left, right, "z", "key", 50, nearest).collect():
            before, after = [k for k in known if k <= r.z], [k for k in known if k > r.z]
            want = before[-1] if before else (after[0] if nearest else None)
            assert (r["at"] and r["at"].key) == want
    placed = positions(left, ["z", "i"]).collect()
    assert [(r.z, r.i) for r in sorted(placed, key=lambda r: r.pos)] == sorted((k, i) for i, k in enumerate(asked))


def test_sketches_estimate_reach(spark):
    g = graph(spark, [(i, i + 1, 1.0) for i in range(30)])
    nodes = frame(spark, [(i,) for i in range(31)], "g long")
    got = {r.g: r.reach for r in cascade.sketch_reach(cascade.live_edges(g, 1, mode="fixed", tau=0.5), nodes, 64).collect()}
    assert got[30] == 1 and got[0] == 31


def test_plans_stay_narrow(spark, small):
    from groupstream import queries as own

    plan = own.queries()["index_topk"](spark, small)._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan and "BatchEvalPython" not in plan
    ranks = own.queries()["batch_topk"](spark, small)._jdf.queryExecution().toString()
    assert "WindowGroupLimit" in ranks


def test_streams_restart_and_batches_agree(spark, small, tmp_path):
    from groupstream.sources.tables import Tables
    from groupstream.streaming import jobs

    events = Tables(spark, small).events
    for i in range(3):
        events.where(F.col("event_id") % 3 == i).coalesce(1).write.parquet(f"{tmp_path}/parts/{i}")
    import glob
    import os
    import shutil

    os.makedirs(f"{tmp_path}/in")
    for i in range(3):
        shutil.copy(glob.glob(f"{tmp_path}/parts/{i}/*.parquet")[0], f"{tmp_path}/in/events-{i}.parquet")
    seen = []
    jobs.each_batch(jobs.events_stream(spark, f"{tmp_path}/in"), lambda b, n: seen.append((n, b.count())), f"{tmp_path}/check")
    assert len(seen) == 3 and sum(n for _, n in seen) == events.count()
    jobs.each_batch(jobs.events_stream(spark, f"{tmp_path}/in"), lambda b, n: seen.append((n, b.count())), f"{tmp_path}/check")
    assert len(seen) == 3


def test_purchases_after_views_count_whole_seconds(spark, tmp_path):
    """A purchase in the second of its view, but before it, and one in the last second of the day after it."""
    rows = [(1, "view", "2024-01-01 10:00:00.700"), (1, "purchase", "2024-01-01 10:00:00.200"), (1, "purchase", "2024-01-02 10:00:00.900"), (1, "purchase", "2024-01-02 10:00:01.100"), (1, "purchase", "2024-01-01 09:59:59.900")]
    events = spark.createDataFrame(rows, "user_id long, event_type string, at string")
    events = events.select(F.monotonically_increasing_id().alias("event_id"), F.col("at").cast("timestamp_ntz").alias("ts"), "user_id", "event_type", F.lit(0.0).alias("value"), F.lit("{}").alias("props"))
    events.coalesce(1).write.parquet(f"{tmp_path}/written")
    next((tmp_path / "written").glob("*.parquet")).rename(tmp_path / "events.parquet")
    name = "stream_purchases_after_views"
    sql = own.oracle_sql()[name].replace(" events ", f" '{tmp_path}/events.parquet' ")
    assert own.queries()[name](spark, str(tmp_path)).first().n == duckdb.connect().execute(sql).fetchone()[0] == 2


def test_models_round_trip(spark, tmp_path):
    from groupstream.sources.storage import load_model, save_model

    save_model(spark, f"{tmp_path}/model", {"w": np.arange(6.0).reshape(2, 3), "b": np.zeros(2)}, {"layers": 2})
    weights, meta = load_model(spark, f"{tmp_path}/model")
    assert meta == {"layers": 2} and (weights["w"] == np.arange(6.0).reshape(2, 3)).all()


@pytest.mark.parametrize("dynamic", [False, True])
def test_cascades_of_few_groups_reach_what_joined_rounds_reach(spark, dynamic):
    """Over items, runs, drops, injected groups without vectors, and seed sets of one and of several groups."""
    rng = np.random.default_rng(5)
    groups = frame(spark, [(g, rng.normal(0, 1, 3).tolist()) for g in range(0, 36, 3)], "g long, vec array<double>")
    items = frame(spark, [(v, rng.normal(0, 1, 3).tolist()) for v in range(6)], "v long, vec array<double>")
    ties = {(int(a) * 3, int(b) * 3) for a, b in rng.integers(0, 13, (60, 2)) if a != b}  # group 36 has no vector
    sims = frame(spark, [(a, b, float(rng.uniform(0.5, 1))) for a, b in sorted(ties)], "src long, dst long, sim double")
    act = [frame(spark, [(g, float(rng.uniform())) for g in range(0, 30, 3)], "g long, act double") for _ in range(3)]
    fresh = [frame(spark, [(int(v), int(g) * 3) for v, g in rng.integers(0, (6, 14), (9, 2))], "v long, g long") for _ in range(2)]
    batches = list(zip(fresh, act[1:])) if dynamic else []
    several = frame(spark, [(s, v, int(g) * 3) for s in range(2) for v in range(0, 6, 2) for g in rng.integers(0, 12, 3)], "s long, v long, g long")
    alone = groups.select(F.col("g").alias("s"), "g").join(items.select("v"))
    for weights in ({"drop": "willingness"}, {"g1": 0.3, "g2": 0.6}):
        graph = prop_graph.build(sims, act[0], factors.willingness(items, groups, 3), **weights)
        ids = dense.few(groups, *fresh)
        for seeds in (None, several):
            start = alone if seeds is None else seeds
            active = cascade.run_dynamic(graph, start, batches, 3, weights=weights, scale=prop_graph.by_in_degree) if dynamic else cascade.run(prop_graph.by_in_degree(graph), start, 3)
            want = {(r.s, r.v): r.spread for r in cascade.spread(active, 12, 3).collect()}
            found = dense.spreads(ids, sims, act[0], items, groups, 12, seeds, batches, 3, weights).collect()
            assert {(r.s, r.v): r.spread for r in found} == pytest.approx(want) and len(found) == len(want)
            assert all(r.influence == pytest.approx(r.spread / 12) for r in found)


def test_too_many_groups_are_left_to_joins(spark):
    many = spark.range(dense.FEW + 1).withColumnRenamed("id", "g")
    assert dense.few(many) is None and dense.few(many.where("g > 0")) == list(range(1, dense.FEW + 1))


def test_blocks_are_chosen_without_bringing_promises_together(spark):
    """Each item reads as many of the most promising blocks as its budget has, and all of them where there are fewer."""
    rng = np.random.default_rng(8)
    rows = [(int(i // 4), int(i), rng.normal(0, 1, 3).tolist()) for i in range(800)]
    packs = best.pack(frame(spark, rows, "block long, g long, vec array<double>")).repartition(5).persist()
    items = rng.normal(0, 1, (40, 3))
    held = packs.collect()
    promise = np.array([items @ np.array(r.centre) + best.LEAN * np.sqrt((items**2).sum(1)) * r.radius for r in held])
    bar = best.bars(packs, items, 13)
    assert ((promise >= bar).sum(0) == 13).all() and np.isinf(best.bars(packs, items, 201)).all()
    found = best.top_k(packs, frame(spark, [(v, x.tolist()) for v, x in enumerate(items)], "v long, vec array<double>"), 5, 13 * 4, 4).collect()
    for v, x in enumerate(items):
        near = {int(r.block) for r, p in zip(held, promise[:, v]) if p >= bar[v]}
        want = sorted((-float(np.dot(x, vec)), g) for block, g, vec in rows if block in near)[:5]
        assert [r.g for r in sorted(found, key=lambda r: r["rank"]) if r.v == v] == [g for _, g in want]


def test_gradients_do_not_depend_on_how_triples_are_cut(monkeypatch):
    rng = np.random.default_rng(2)
    w = training.new_weights(3, 4, 4, 2)
    xg, xv, ends = rng.normal(0, 1, (5, 4)), rng.normal(0, 1, (7, 4)), rng.integers(0, 5, (2, 8))
    owner, held, g, pos, neg = (rng.integers(0, n, 20) for n in (5, 7, 5, 7, 7))
    run = lambda: training.loss_and_gradients(w, xg, xv, *ends, np.full(8, 0.5), owner, held, g, pos, neg, 2, 1e-3)
    whole = run()
    monkeypatch.setattr(training, "BLOCK", 3)
    cut = run()
    assert cut[0] == pytest.approx(whole[0])
    for k in w:
        assert cut[1][k] == pytest.approx(whole[1][k])


def test_lines_are_joined_once_where_they_are_kept(spark, small):
    from groupstream.sources.tables import Tables

    t = Tables(spark, small)
    plain = t.lines()
    t.keep_lines()
    assert t.lines() is t.lines() and sorted(t.lines().columns) == sorted(plain.columns)
    assert t.lines().exceptAll(plain).isEmpty() and t.lines().count() == plain.count()


def test_runs_around_places_are_what_scans_read(spark):
    rng, n = np.random.default_rng(5), 300
    vecs, asked = np.round(rng.normal(size=(n, 3)), 1), np.round(rng.normal(size=(40, 3)), 1)
    laid = frame(spark, [(i, i // 16, 1000 - i, vecs[i].tolist()) for i in range(n)], "pos long, block long, g long, vec array<double>").repartition(3)
    items = frame(spark, [(v, v // 2, x.tolist()) for v, x in enumerate(asked)], "v long, z long, vec array<double>")
    probes = frame(spark, [(z, (0, n - 1, 3, n - 4)[z] if z < 4 else int(rng.integers(n))) for z in range(20)], "z long, pos long")
    for budget in (1, 12, 29, n - 5, 2 * n):
        want = search.rank(search.scan(probes, laid, budget, 16), items, 7, 3)
        assert sorted(map(tuple, search.best_around(probes, laid, items, budget, 7).collect())) == sorted(map(tuple, want.collect()))
    index = GroupIndex.build(laid.select("g", "vec"), 3, axes=2, rows_per_block=16)
    for found in (index.top_k(items.select("v", "vec"), 5, 60), index.tree_top_k(items.select("v", "vec"), 5, 60)):
        plan = found._jdf.queryExecution().optimizedPlan().toString()
        assert "Join" not in plan and "Generate" not in plan  # no row for each entry that is read


def test_shards_name_items_by_places_and_grow_in_number(spark, monkeypatch):
    """A training step moves a shard's name, not its rows; items lie in files once; more interactions make more shards."""
    rng = np.random.default_rng(8)
    groups = frame(spark, [(i, rng.normal(size=3).tolist()) for i in range(12)], "g long, vec array<double>")
    items = frame(spark, [(v * 7 - 20, rng.normal(size=4).tolist()) for v in range(50)], "v long, vec array<double>")
    seen = frame(spark, [(g, v * 7 - 20, s) for g in range(12) for v, s in zip(rng.choice(50, 10, replace=False).tolist(), [0, 0, 1, 1, 1] * 2)], "g long, v long, slice int")
    again = seen.unionByName(seen.where("slice = 0").withColumn("slice", F.lit(1)))  # bought once more, later
    graphs = frame(spark, [(t, a, (a + 1) % 12, 0.5) for t in (0, 1) for a in range(12)], "slice int, src long, dst long, lap double")
    triples = relevance.training_triples(again, items.select("v"), keep=("slice",))
    w = training.new_weights(3, 3, 4, 2)
    want = [training.gradients(training.shards(groups, items, graphs, again, triples, 1), w, 2, t, new, b, n) for t, new in ((0, False), (1, False), (1, True)) for b, n in ((0, 1), (1, 3))]
    monkeypatch.setattr(training, "PAIRS", 30)
    packed = training.shards(groups, items, graphs, again, triples, 1)
    got = [training.gradients(packed, w, 2, t, new, b, n) for t, new in ((0, False), (1, False), (1, True)) for b, n in ((0, 1), (1, 3))]
    for (loss, grads, n), (loss1, grads1, n1) in zip(got, want):
        assert n == n1 > 0 and loss == pytest.approx(loss1) and all(grads[k] == pytest.approx(grads1[k]) for k in w)
    rows = packed.collect()
    assert len(rows) == 6 and max(len(r["data"]) for r in rows) < 4000
    owned = [int(training._unpack(r["data"], 1)["own"].sum()) for r in rows]
    assert sum(owned) == 12 and max(owned) == 2  # groups of one size are dealt evenly
    ids = np.concatenate(training._unpack(rows[0]["data"], 1)["items"].ids)
    assert ids.tolist() == [v * 7 - 20 for v in range(50)]
    with pytest.raises(Exception, match="no vector"):
        training.shards(groups, items.where("v > 0"), graphs, again, triples, 1)
