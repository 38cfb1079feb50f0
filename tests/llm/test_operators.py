"""Brute force and edge cases of the training-data operators."""

import collections
import hashlib
import math
import re
import zlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from groupstream.llm import chat, components, decontaminate, mixing, ngram, quality, sharding, simhash, substring, suffixes, topk

DOCS = "doc_id long, text string, source string"
RNG = np.random.default_rng(5)
WORDS = ["".join(RNG.choice(list("abcdefghij"), 5)) for _ in range(300)]


def prose(n, seed):
    return " ".join(np.random.default_rng(seed).choice(WORDS, n))


PASSAGE = prose(70, 99)
LONG = prose(20_000, 7)
ROWS = [
    (1, prose(60, 1) + " " + PASSAGE + " " + prose(40, 2), "a"),
    (2, prose(30, 3) + " " + PASSAGE + " " + prose(80, 4), "a"),
    (3, prose(100, 5), "b"),
    (4, prose(100, 5), "b"),
    (5, None, None),
    (6, "", "a"),
    (7, "Äö ü\u2003ß", "b"),
    (8, LONG, "a"),
    (9, "x" * 5000, "a"),
    (9, "x" * 5000, "a"),
    (None, prose(100, 5), "c"),
    (11, PASSAGE, None),
]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, DOCS).withColumns({"size": F.lit("clash"), "shard": F.lit(1), "id": F.lit(-1), "block": F.lit(0), "key": F.lit("k")}).repartition(3)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


def by_id(rows, key="id"):
    return {r[key]: r for r in rows}


def test_chunks_resist_insertions():
    gear, text = substring.gear_table(), LONG.encode()
    pieces = lambda t: {t[a:b] for a, b in zip([0, *substring.chunk_ends(t, gear)], substring.chunk_ends(t, gear))}
    moved = text[:5000] + b"inserted" + text[5000:]
    assert len(pieces(text) - pieces(moved)) <= 3
    assert b"".join(t for t in [text[a:b] for a, b in zip([0, *substring.chunk_ends(text, gear)], substring.chunk_ends(text, gear))]) == text


def test_substring_dedup(spark, docs, none):
    got = by_id(substring.deduplicate(docs).collect())
    assert len(got) == 11 and got[5].n_bytes == 0 and got[6].kept == b""
    assert got[4].kept == b"" or len(got[4].kept) < 200
    assert got[3].kept == ROWS[2][1].encode()
    assert PASSAGE[100:-100].encode() not in bytes(got[2].kept)
    assert PASSAGE.encode() in bytes(got[1].kept)
    assert len(got[None].kept) < 200
    assert bytes(got[8].kept) == LONG.encode()
    assert substring.deduplicate(none).collect() == []


def test_repeated_passages_and_short_copies_go(spark):
    rows, short = [], [prose(4, 900), "one line", "x"]
    for seed in range(400):  # 51 words, every tenth passage of two words repeated, in contexts of their own
        passage = prose(51, 2_000 + seed) if seed % 10 else " ".join([WORDS[seed % 300]] * 30 + [WORDS[(seed + 7) % 300]] * 21)
        rows += [(1_000 * at + seed, " ".join([prose(40, 10_000 * at + seed), passage, prose(40, 20_000 * at + seed)]), "a") for at in (1, 2)]
    rows += [(10 * n + i, text, "a") for n, text in enumerate(short) for i in range(3)] + [(80, "one line more", "a"), (81, "one", "a"), (82, "y", "a"), (82, "y", "a"), (None, "x", "a")]
    found = substring.deduplicate(spark.createDataFrame(rows, DOCS)).collect()
    got = by_id(found)
    assert sum(len(got[2_000 + seed].kept) == got[2_000 + seed].n_bytes for seed in range(400)) == 0
    for n, text in enumerate(short):
        assert [bytes(got[10 * n + i].kept) for i in range(3)] == [text.encode(), b"", b""]
    assert bytes(got[80].kept) == b"one line more" and bytes(got[81].kept) == b"one" and got[None].kept == b""
    assert [bytes(r.kept) for r in found if r.id == 82] == [b"y", b"y"]


def brute_strings(rows, depth=50):
    first, out = {}, {}
    texts = [((1 << 63) - 1 if i is None else i, (t or "").encode()) for i, t, _ in rows]
    for i, t in sorted(texts):
        for p in range(len(t) - depth + 1):
            first.setdefault(t[p : p + depth], i)
    for (i, t), (own, _, _) in zip(texts, rows):
        mask = np.zeros(len(t), bool)
        for p in range(len(t) - depth + 1):
            if first[t[p : p + depth]] < i:
                mask[p : p + depth] = True
        out[own] = np.frombuffer(t, np.uint8)[~mask].tobytes()
    return out


def test_suffix_dedup_is_exact(spark, docs, none):
    want = brute_strings(ROWS)
    got = suffixes.deduplicate(docs).collect()
    assert len(got) == len(ROWS)
    assert all(bytes(r.kept) == want[r.id] for r in got)
    assert suffixes.deduplicate(none).collect() == []
    with pytest.raises(ValueError):
        suffixes.deduplicate(docs, 8)


def test_suffix_passes_find_equal_strings():
    text = np.frombuffer(b"abcdefghijklmnopqrstuvwx" * 6 + bytes(range(60)), np.uint8)
    start = np.arange(len(text) - 49)
    left, group = suffixes.equal_strings(text, start, np.zeros(len(start), np.int64), 50)
    want = collections.Counter(text[s : s + 50].tobytes() for s in start)
    assert {int(s) for s in left} == {int(s) for s in start if want[text[s : s + 50].tobytes()] > 1}
    for g in set(group.tolist()):
        assert len({text[start[s] : start[s] + 50].tobytes() for s in left[group == g]}) == 1


def test_simhash(spark, docs, none):
    got = by_id(simhash.near_duplicates(docs).collect())
    assert got[5].fingerprint == got[6].fingerprint == "0" * 16 and got[6].component_id == 5
    assert got[4].component_id == 3 == got[None].component_id and got[8].component_id == 8

    def brute(text):
        w = (text or "").encode().lower().split()
        k = min(4, len(w))
        hs = [xxhash.xxh64_intdigest(b" ".join(w[i : i + k]), 42) for i in range(len(w) - k + 1)] if w else []
        return f"{sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs)):016x}"

    assert all(got[i].fingerprint == brute(t) for i, t, _ in ROWS)
    assert simhash.near_duplicates(none).collect() == []
    kept = simhash.keep_one_of_each(docs)
    assert sorted(-1 if r.doc_id is None else r.doc_id for r in kept.collect()) == [-1, 1, 2, 3, 5, 7, 8, 9, 11] and kept.columns == docs.columns
    assert simhash.keep_one_of_each(none).collect() == []


def test_near_copies_go_and_others_stay(spark):
    rows, original = [], prose(250, 31).split()
    for i in range(40):  # copies of one original, each with two edits of its own
        words = list(original)
        for at in np.random.default_rng(i).integers(0, 250, 2):
            words[at] = f"edit{i}"
        rows.append((100 + i, " ".join(words), "a"))
    rows += [(50, " ".join(original), "a"), (51, " ".join(original[:130] + prose(120, 32).split()), "a"), (52, prose(250, 33), "a"), (53, "", "a"), (54, None, "a")]
    kept = simhash.keep_one_of_each(spark.createDataFrame(rows, DOCS)).collect()
    assert sorted(r.doc_id for r in kept) == [50, 51, 52, 53]


def test_groups_of_many_families(spark, monkeypatch):
    monkeypatch.setattr(simhash, "TILE_SHINGLES", 2_000)
    shared, rows = prose(200, 70), []
    for f in range(9):  # nine families that share much: each has its text, an exact copy, and one with an edit
        text = shared + " " + prose(70, 71 + f)
        rows += [(10 * f, text, "a"), (10 * f + 1, text, "a"), (10 * f + 2, text + f" edit{f}", "a")]
    # Of a chain, each is similar to the next only; the one in the middle leads, and both ends stay with it.
    chain = prose(460, 90).split()
    rows += [(200 + i, " ".join(chain[22 * i : 22 * i + 250]), "a") for i in range(8)]
    docs = spark.createDataFrame(rows, DOCS)
    wide = simhash.near_duplicates(docs, 5, 128, 40).collect()
    assert max(collections.Counter(r.component_id for r in wide).values()) >= 27

    def shingles(text):
        w = text.split()
        return {" ".join(w[i : i + 5]) for i in range(len(w) - 4)}

    sets = {i: shingles(t) for i, t, _ in rows}
    group = {r.id: r.component_id for r in wide}
    up = {i: i for i in sets}
    find = lambda i: i if up[i] == i else find(up[i])
    for i in sets:
        for j in sets:
            if i < j and group[i] == group[j] and len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
                up[max(find(i), find(j))] = min(find(i), find(j))
    kept = sorted(r.doc_id for r in simhash.keep_one_of_each(docs, radius=40).collect())
    assert kept == sorted(i for i in sets if find(i) == i) and len(kept) == 10


def test_tiles_join_what_brute_force_links():
    rng = np.random.default_rng(1)
    base = rng.integers(0, 1 << 63, 40, dtype=np.uint64)
    fps = np.unique(np.concatenate([base] + [base ^ (np.uint64(1) << rng.integers(0, 64, 40).astype(np.uint64)) for _ in range(12)]))
    ids = np.arange(len(fps), dtype=np.uint64)
    pack = lambda s: np.stack([ids[s], fps[s]], 1).tobytes()
    half = slice(0, len(fps) // 2), slice(len(fps) // 2, len(fps))
    edges = simhash.forest(pack(half[0]), None, 64, 4) + simhash.forest(pack(half[1]), None, 64, 4) + simhash.forest(pack(half[0]), pack(half[1]), 64, 4)

    def roots(pairs):
        up = list(range(len(fps)))
        find = lambda i: i if up[i] == i else find(up[i])
        for a, b in pairs:
            up[max(find(a), find(b))] = min(find(a), find(b))
        return [find(i) for i in range(len(fps))]

    x, y = np.nonzero(np.bitwise_count(fps[:, None] ^ fps[None, :]) <= 4)
    assert roots(edges) == roots(zip(x.tolist(), y.tolist())) and len(edges) < 2 * len(fps)


def test_near_duplicates_over_many_tiles(spark, monkeypatch):
    monkeypatch.setattr(simhash, "TILE", 64)
    monkeypatch.setattr(simhash, "TILES", 1 << 30)
    rows = []
    for i in range(250):  # texts with copies that differ in a few words
        text = prose(60, 40_000 + i).split()
        for c in range(3):
            text[(7 * c) % 60] = f"c{c}x"
            rows.append((3 * i + c, " ".join(text), "a"))
    got = simhash.near_duplicates(spark.createDataFrame(rows, DOCS)).collect()
    ids = np.array([r.id for r in got])
    prints = np.array([int(r.fingerprint, 16) for r in got], np.uint64)
    up = {int(i): int(i) for i in ids}

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for x, y in zip(*np.nonzero(np.bitwise_count(prints[:, None] ^ prints[None, :]) <= 4)):
        a, b = find(int(ids[x])), find(int(ids[y]))
        up[max(a, b)] = min(a, b)
    assert all(r.component_id == find(r.id) for r in got) and len({r.component_id for r in got}) < len(got)


def test_rows_that_an_id_cannot_name_stay(spark):
    text, other = prose(80, 1), prose(80, 2)
    rows = [(None, text, "a"), (None, text, "a"), (None, text, "b"), (1, text, "a"), (1, text, "b"), (2, text, "a"), (3, other, "a"), (3, text, "a"), (4, other, "a")]
    kept = simhash.keep_one_of_each(spark.createDataFrame(rows, DOCS)).collect()
    assert collections.Counter(r.doc_id for r in kept) == {None: 3, 1: 1, 3: 2, 4: 1}
    again = simhash.keep_one_of_each(spark.createDataFrame(rows, DOCS).repartition(5)).collect()
    assert sorted(map(repr, kept)) == sorted(map(repr, again))


def test_ids_are_checked_and_the_largest_is_kept(spark):
    named = spark.createDataFrame([("a", "x y z", "s")], "doc_id string, text string, source string")
    for run in (substring.deduplicate, suffixes.deduplicate, simhash.near_duplicates, quality.measured):
        with pytest.raises(TypeError):
            run(named)
    last = spark.createDataFrame([((1 << 63) - 1, prose(30, 1), "a"), (None, prose(30, 2), "a")], DOCS)
    for run in (substring.deduplicate, suffixes.deduplicate):
        assert {r.id for r in run(last).collect()} == {(1 << 63) - 1, None}


def test_substring_dedup_against_a_dictionary(spark, docs):
    """What goes is exactly the runs of chunks whose bytes occur earlier, and short whole copies."""
    gear, first, want = substring.gear_table(), {}, {}
    texts = sorted(((1 << 63) - 1 if i is None else i, (t or "").encode()) for i, t, _ in ROWS)
    cut = lambda t: list(zip([0, *substring.chunk_ends(t, gear)], substring.chunk_ends(t, gear))) if t else []
    whole = {}
    for i, t in texts:
        whole.setdefault(t, i)
        for n, (a, b) in enumerate(cut(t)):
            first.setdefault(t[a:b], (i, n))
    for i, t in texts:
        mask, spans = np.zeros(len(t), bool), cut(t)
        again = [first[t[a:b]][0] < i or first[t[a:b]][1] < n for n, (a, b) in enumerate(spans)]
        start = 0
        while start < len(spans):
            stop = start
            while stop < len(spans) and again[stop]:
                stop += 1
            if stop > start and spans[stop - 1][1] - spans[start][0] >= substring.MIN_BYTES:
                mask[spans[start][0] : spans[stop - 1][1]] = True
            start = max(stop, start + 1)
        if 0 < len(t) < substring.MIN_BYTES and whole[t] < i:
            mask[:] = True
        want[i] = np.frombuffer(t, np.uint8)[~mask].tobytes()
    got = substring.deduplicate(docs).collect()
    assert all(bytes(r.kept) == want[(1 << 63) - 1 if r.id is None else r.id] for r in got) and len(got) == len(ROWS)


def test_components(spark):
    rng = np.random.default_rng(3)
    pairs = [(int(a), int(b)) for a, b in rng.integers(0, 300, (220, 2))] + [(i, i + 1) for i in range(1000, 1060)]
    got = {r.node: r.root for r in components.connected_components(spark.createDataFrame(pairs, "a long, b long")).collect()}
    up = {n: n for p in pairs for n in p}

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for a, b in pairs:
        up[max(find(a), find(b))] = min(find(a), find(b))
    assert all(got.get(n, n) == find(n) for n in up)


def test_the_trees_skip_most_pairs_of_clustered_vectors():
    rng = np.random.default_rng(0)
    points = rng.normal(size=(40, 16))[rng.integers(0, 40, 8000)] * 4 + 0.05 * rng.normal(size=(8000, 16))
    one, q, d = topk.Search(points[:300], np.arange(300), 10), topk.Tree(points[:300], 12), topk.Tree(points)
    one.run(q, d, points[d.order], d.order, np.zeros(8000, int))
    assert one.scored < 0.1 * 300 * 8000
    for i in range(0, 300, 29):
        score = points @ points[i]
        score[i] = -np.inf
        assert one.found[i].tolist() == np.lexsort((np.arange(8000), -score))[:10].tolist()


def test_top_k_over_many_blocks_and_repeated_rows(spark, monkeypatch):
    for name, value in (("BLOCK", 64), ("QUERY_BLOCK", 8), ("LEAF", 8), ("ASKS", 2)):
        monkeypatch.setattr(topk, name, value)
    rng = np.random.default_rng(0)
    rows = [(i, rng.normal(size=6).astype(np.float32).tolist()) for i in range(900)] + [(100, [0.5] * 6)] * 3 + [(i, [0.25] * 6) for i in range(900, 1300)]
    rows += [(200, [0.1] * 6), (200, [0.2] * 6)] + [(7, [9.0] * 6)] * 40 + [(1500, [9.0] * 6)] * 15
    whole, want = [(i, np.floor(1024 * np.array(v, np.float32).astype(np.float64))) for i, v in rows], []
    for a, (i, q) in enumerate(whole):
        if i % 100 == 0:
            best = sorted((-float(q @ v), j) for b, (j, v) in enumerate(whole) if b != a)[:10]
            want += [(i, n + 1, j, -s) for n, (s, j) in enumerate(best)]
    table = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumns({"score": F.lit("clash"), "n": F.lit(0), "cell": F.lit(1)})
    found = topk.top_k(topk.integer_vectors(table), F.pmod(F.col("id"), F.lit(100)) == 0)
    assert sorted((r.query_id, r["rank"], r.id, r.score) for r in found.collect()) == sorted(want)


def test_block_pairs_are_ruled_out_before_vectors_are_sent(spark):
    at = lambda i: [100.0 if j == i else 0.0 for j in range(8)]
    blocks = spark.createDataFrame([(8, c, s, at(c), 1.0) for c in range(8) for s in range(4)], "dim long, cell long, sub long, centre array<double>, radius double")
    asks = spark.createDataFrame([(8, c, c, at(c), 1.0, 9_000.0) for c in range(8)], "dim long, ask long, home long, q_centre array<double>, q_radius double, worst double")
    assert sorted((r.ask, r.cell, r["sub"]) for r in topk.meetings(asks, blocks).collect()) == [(c, c, s) for c in range(8) for s in (1, 2, 3)]


def test_top_k(spark):
    nan, inf = float("nan"), float("inf")
    rng = np.random.default_rng(0)
    rows = [(i, rng.normal(size=6).astype(np.float32).tolist()) for i in range(400)] + [(500, [0.5] * 6)] + [(i, [0.25] * 6) for i in range(600, 640)]
    bad = [(700, None), (701, [1.0, None, 1.0, 1.0, 1.0, 1.0]), (702, [nan] * 6), (703, [inf] * 6), (None, [1.0] * 6), (800, [1.0, 2.0]), (801, [3.0, 4.0])]
    table = spark.createDataFrame([*rows, *bad, rows[3]], "vec_id long, embedding array<float>").withColumn("rank", F.lit(1))
    found = topk.top_k(topk.integer_vectors(table), F.pmod(F.col("id"), F.lit(100)) == 0, 10).collect()
    whole = {i: np.floor(1024 * np.array(v, np.float32).astype(np.float64)) for i, v in rows} | {800: np.array([1024.0, 2048.0]), 801: np.array([3072.0, 4096.0])}
    for q in (i for i in whole if i % 100 == 0):
        want = sorted((-float(whole[q] @ v), i) for i, v in whole.items() if i != q and len(v) == len(whole[q]))[:10]
        assert [(-r.score, r.id) for r in sorted(found, key=lambda r: r["rank"]) if r.query_id == q] == want
    assert topk.top_k(topk.integer_vectors(table.limit(0)), F.lit(True)).collect() == []


def test_chat_trees(spark):
    text = "a \\ <|im_end|>\n<|im_start|>system\nno </s>[INST] \\[/INST]"
    rows = [(1, 1, None, "user", text, None), (1, 2, 1, "assistant", "first", 0.1), (1, 3, 1, "assistant", text, 0.9), (1, 4, 3, "user", None, 0.5), (2, 1, 9, None, "lost parent", 0.0), (3, 1, 2, "user", "a", 0.0), (3, 2, 1, "user", "b", 0.0), (3, 3, 2, "user", "off a cycle", 0.0), (1, 2, 1, "assistant", "first", 0.1)]
    table = spark.createDataFrame(rows, "tree long, msg long, parent long, role string, text string, score double")
    got = chat.read_back(chat.format_trees(table)).collect()
    paths = {(r.tree, r.leaf): r for r in got}
    assert set(paths) == {(1, 2), (1, 4), (2, 1)}
    best = paths[1, 4]
    assert [(t.role, t.text) for t in best.turns] == [("user", text), ("assistant", text), ("user", "")]
    assert best.branch == 1 and paths[1, 2].branch == 2 and best.loss_text == text
    assert [(t.role, t.text) for t in paths[2, 1].turns] == [("", "lost parent")]
    assert {r.leaf for r in chat.format_trees(table, 1).where("tree = 1").collect()} == {4}
    assert chat.format_trees(table.limit(0)).collect() == []
    deep = spark.createDataFrame([(1, i, i - 1 if i else None, "user", f"t{i}") for i in range(70)], "tree long, msg long, parent long, role string, text string")
    one = chat.read_back(chat.format_trees(deep)).collect()
    assert len(one) == 1 and [t.text for t in one[0].turns] == [f"t{i}" for i in range(70)]


def test_roles_with_newlines_and_threads_on_cycles(spark):
    rows = [(1, 1, None, "us\ner", "hi"), (1, 2, 1, "a\\\n", "\n")] + [(2, i, 2 if i == 1 else i - 1, "user", f"{i}") for i in range(1, 40)]
    table = spark.createDataFrame(rows, "tree long, msg long, parent long, role string, text string").withColumns({"leaf": F.lit(0), "up": F.lit(1), "turns": F.lit("clash")})
    got = chat.read_back(chat.format_trees(table)).collect()
    assert [[(t.role, t.text) for t in r.turns] for r in got] == [[("us\ner", "hi"), ("a\\\n", "\n")]]
    # One path of three turns and a long tail behind a cycle: nothing is written for the tail.
    assert chat.paths(table.select("tree", "msg", "parent")).count() == 2


def test_sharding(spark, docs, none):
    size = F.octet_length(F.coalesce(F.col("text"), F.lit(""))) + 1
    got = sharding.place(docs, size, n_shards=4, ranges=(4, 64)).collect()
    h = lambda s: int(hashlib.md5(s.encode()).hexdigest()[:15], 16)
    order = sorted(((h(t or ""), h("" if i is None else str(i)), len((t or "").encode()) + 1, i) for i, t, _ in ROWS), key=lambda r: r[:3])
    total, at, want, slots = sum(r[2] for r in order), 0, [], collections.Counter()
    for _, _, n, i in order:
        s = at * 4 // total
        want.append((i, n, s, slots[s]))
        slots[s] += 1
        at += n
    assert sorted(map(repr, want)) == sorted(repr((r.doc_id, r.size, r.shard, r.slot)) for r in got)
    assert sharding.place(none, size).collect() == []


def test_hot_text_is_spread_over_ranges(spark):
    hot = spark.range(3000).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 3 == 0, F.lit("hot " * 40)).otherwise(F.concat(F.lit("text "), F.col("id"))).alias("text"))
    got = sharding.place(hot, F.octet_length("text"), n_shards=4, ranges=(8, 64)).groupBy("shard").agg(F.sum("size").alias("b"), F.count("*").alias("n"), F.max("slot").alias("m")).collect()
    assert max(r.b for r in got) - min(r.b for r in got) <= 400 and all(r.m == r.n - 1 for r in got)


def test_mixing_ties_and_repeated_rows(spark, tmp_path):
    import duckdb

    rng, rows = np.random.default_rng(0), []
    for i in range(1500):
        text = " ".join(rng.choice(WORDS, rng.integers(1, 40))) if i % 5 else "the same text of eight words right here"
        rows.append((None if i % 2 == 0 else 7 if i % 4 == 1 else i, None if i % 97 == 0 else text, None if i % 11 == 0 else "abc"[i % 3], i))
    path = f"{tmp_path}/documents.parquet"
    spark.createDataFrame(rows, "doc_id long, text string, source string, other int").repartition(3).write.parquet(path)
    got = mixing.mix(spark.read.parquet(path)).collect()
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{path}/*.parquet'")
    columns = ["doc_id", "size", "source_size", "target", "taken", "copies"]
    assert sorted(repr(tuple(r[c] for c in columns)) for r in got) == sorted(map(repr, con.execute(mixing.SQL).fetchall()))
    words, target = collections.Counter(), {}
    for r in got:
        words[r.source] += r.taken
        target[r.source] = r.target
    assert len(got) == 1500 and all(abs(words[s] - t) <= 1 for s, t in target.items())


def test_mixing(spark, docs, none):
    got = mixing.mix(docs).collect()
    sizes, names = collections.Counter(), sorted({s for _, _, s in ROWS if s is not None}) + [None]
    for _, t, s in ROWS:
        sizes[s] += len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(names)}
    left, open_, target = sum(sizes.values()), set(names), {}
    while over := [s for s in open_ if left * weight[s] / sum(weight[x] for x in open_) > 3 * sizes[s]]:
        for s in over:
            target[s] = 3 * sizes[s]
        open_ -= set(over)
        left = sum(sizes.values()) - sum(target.values())
    target |= {s: left * weight[s] / sum(weight[x] for x in open_) for s in open_}
    assert {r.source: round(r.target, 6) for r in got} == {s: round(t, 6) for s, t in target.items()}
    assert all(r.taken <= 3 * r["size"] for r in got) and len(got) == len(ROWS)
    assert sorted(map(repr, got)) == sorted(map(repr, mixing.mix(docs.repartition(5)).collect()))
    assert mixing.mix(none).collect() == []
    many = spark.range(6000).select(F.col("id").alias("doc_id"), F.array_join(F.array_repeat(F.lit("w"), (F.col("id") % 37 + 1).cast("int")), " ").alias("text"), F.concat(F.lit("s"), F.col("id") % 5).alias("source"))
    near = mixing.mix(many).groupBy("source").agg(F.first("target").alias("t"), F.sum("taken").alias("k")).collect()
    assert all(abs(r.t - r.k) <= 37 for r in near)
    assert mixing.draw(many).count() == mixing.mix(many).agg(F.sum("copies")).first()[0]


def test_mixing_rounds_join_rows_once(spark):
    """A round's plan stays small: of its tables of keys none is joined with another, only rows with the range that is looked at."""
    rows = [("all", 9, 3, 0.5), ("all", 9, 0, 7.0), ("split", 9, 4, 0.1), ("split", 9, 4, 0.2), ("split", 9, 4, 0.3), ("part", 9, 4, 0.4), ("part", 9, 4, 0.4), ("part", 9, 4, 0.4), ("none", 0, 4, 0.4), ("none", 0, 4, 0.5)]
    found = mixing._prefix(spark.createDataFrame(rows, "key string, room long, size long, q double"))
    got = {r.key: (r.got, r.upto, r.upto_size, r.part and tuple(r.part)) for r in found.collect()}
    assert got == {"all": (3, 7.0, 0, None), "split": (8, 0.2, 4, None), "part": (8, -1.0, 0, (0.4, 4, 2)), "none": (0, -1.0, 0, None)}
    assert found._jdf.queryExecution().optimizedPlan().toString().count("Join ") == 1


def test_ngram_model_sums_to_one_and_scores_like_brute_force(spark, docs, none):
    train = spark.createDataFrame([(i, prose(200, i), "a") for i in range(30)], DOCS)
    model = ngram.train(train)
    tokens = lambda t: [*(t or "").encode().lower().split(), None]
    pairs, words = collections.Counter(), collections.Counter()
    for i in range(30):
        t = tokens(prose(200, i))
        pairs.update(zip([0, *t], t))
        words.update(t)
    assert model.sums["tokens"] == sum(words.values()) and model.sums["words"] == len(words)

    def disc(values):
        n = collections.Counter(values)
        y = n[1] / (n[1] + 2 * n[2]) if n[1] + 2 * n[2] else 0.5
        return [0, *[min(max(k - (k + 1) * y * n[k + 1] / n[k], 0), k) if n[k] else k / 2 for k in (1, 2, 3)]]

    d2, spread = disc(pairs.values()), collections.Counter(b for _, b in pairs)
    d1 = disc(spread.values())
    uniform = sum(d1[min(c, 3)] for c in spread.values()) / len(pairs) / (len(words) + 1)
    follow = collections.defaultdict(list)
    for (a, _), c in pairs.items():
        follow[a].append(c)

    def p(a, b):
        base = uniform + max(spread[b] - d1[min(spread[b], 3)], 0) / len(pairs)
        if a not in follow:
            return base
        total, left = sum(follow[a]), sum(d2[min(c, 3)] for c in follow[a])
        return max(pairs[a, b] - d2[min(pairs[a, b], 3)], 0) / total + left / total * base

    some = [b for b in words][:1] + [None]
    for a in some:
        assert sum(p(a, b) for b in words) + p(a, b"unknown word") == pytest.approx(1)
    got = by_id(ngram.scores(docs, model).collect())
    for i, t, _ in ROWS[:8]:
        want = sum(math.log10(p(a, b)) for a, b in zip([0, *tokens(t)], tokens(t)))
        assert got[i].score == pytest.approx(want, rel=1e-9) and got[i].n_tokens == len(tokens(t))
        assert got[i].n_known == sum(words[b] > 0 for b in tokens(t))
    assert ngram.scores(none, ngram.train(none)).collect() == []
    empty = ngram.scores(docs, ngram.train(none)).collect()
    assert all(r.score == 0 and r.base_score == 0 for r in empty)


def test_long_texts_are_read_whole_in_pieces():
    text = (prose(1000, 1) * 4).encode()
    whole = list(ngram.token_pieces([text, b"", b"end"]))
    keep, ngram.PIECE = ngram.PIECE, 500
    try:
        parts = list(ngram.token_pieces([text, b"", b"end"]))
    finally:
        ngram.PIECE = keep
    assert len(parts) > 10
    for i in range(3):
        assert (np.concatenate([p[i] for p in whole]) == np.concatenate([p[i] for p in parts])).all()


def test_quality(spark, none):
    rows = [(i, prose(60, i) + "." if i % 4 else prose(30, i).upper() + " !!! ### $$$ " * 10, "a") for i in range(400)] + [(1000, "", "a"), (1001, None, "a"), (None, prose(50, 1), "a")]
    docs = spark.createDataFrame(rows, DOCS).withColumn("quality", F.lit("clash"))
    labels = spark.createDataFrame([(i, int(i % 4 > 0)) for i in range(400)] + [(5, None), (None, 1)], "doc_id long, quality int")
    features = quality.measured(docs)
    model = quality.train(features, quality.training_labels(labels))
    got = by_id(quality.scored(features, model).collect())
    held = [i for i in range(400) if zlib.crc32(str(i).encode()) % 5 == 0]
    assert len(got) == 403 and all(0 <= r.score <= 1 for r in got.values())
    assert sum((got[i].score >= 0.3) == (i % 4 > 0) for i in held) >= 0.98 * len(held)
    kept = quality.keep_good(docs, labels)
    assert kept.columns == docs.columns and 290 <= kept.count() <= 310
    assert {r.score for r in quality.scored(features, quality.train(features, quality.training_labels(labels.limit(0)))).collect()} == {0.5}
    assert quality.scored(quality.measured(none), model).collect() == []


def test_the_classifier_solves_what_it_says(spark):
    """Weights and scores against the same regression worked out in one piece."""
    rows = [(i, prose(40, i) + ("." if i % 3 else " ### !!!"), "a") for i in range(240)]
    labels = spark.createDataFrame([(i, int(i % 3 > 0)) for i in range(240)], "id long, label double".replace("double", "int")).select("id", F.col("label").cast("double").alias("label"))
    features = quality.measured(spark.createDataFrame(rows, DOCS))
    model = quality.train(features, labels)
    x = np.array([quality.statistics(t.encode()) for _, t, _ in rows])
    y = np.array([float(i % 3 > 0) for i in range(240)])
    assert model.mean == pytest.approx(x.mean(0)) and model.scale == pytest.approx(np.where(x.std(0) > 1e-9, x.std(0), 1.0))
    z, eye = model.features(x), np.eye(quality.FEATURES)
    eye[-1, -1] = 1e-6
    fits = [np.linalg.solve(z.T @ z + p * 240 * eye / quality.FEATURES * 2, z.T @ y) for p in quality.PENALTIES]
    assert min(np.abs(z @ w - z @ model.weights).max() for w in fits) < 1e-5
    assert (np.diff(model.curve[1]) >= 0).all() and 0 <= model.curve[1].min() and model.curve[1].max() <= 1
    assert quality.bounded(labels, 50).count() == 50


def test_decontamination(spark, docs, none):
    item = prose(40, 77)
    close = item.split()
    close[20] = "changed"
    rows = [(20, prose(50, 8) + " " + item.upper() + ", " + prose(50, 9), "a"), (21, " ".join(prose(20, 10).split() + close), "a"), (22, " ".join(item.split()[:20]) + " " + prose(60, 11), "a"), (23, "tiny", "b")]
    both = docs.unionByName(spark.createDataFrame(rows, DOCS), allowMissingColumns=True)
    bench = spark.createDataFrame([(1, item), (2, None), (3, ""), (4, "tiny"), (5, item), (6, prose(30, 5))], "item_id long, text string")
    got = {(r.id, r.item_id): r.similarity for r in decontaminate.matches(both, bench).collect()}
    assert got.keys() == {(20, 1), (20, 5), (23, 4), (3, 6), (4, 6), (None, 6)} and got[20, 1] == 1.0
    low = {(r.id, r.item_id) for r in decontaminate.matches(both, bench, 0.7).collect()}
    assert {(21, 1), (21, 5)} <= low
    kept = decontaminate.clean(both, bench)
    assert kept.columns == both.columns and kept.count() == both.count() - 5
    assert decontaminate.matches(none, bench).collect() == [] and decontaminate.matches(both, bench.limit(0)).collect() == []


def test_decontamination_against_brute_force():
    few = [f"w{i}" for i in range(40)]
    words = lambda n, seed: " ".join(np.random.default_rng(seed).choice(few, n))
    items = [(i, words(n, 100 + i)) for i, n in enumerate([6, 9, 15, 30, 60, 7, 200])]
    docs = []
    for k in range(60):
        own = items[k % 7][1].split()
        for at in np.random.default_rng(k).integers(0, len(own), k % 3):
            own[at] = f"zz{k}"
        docs.append(" ".join([words(k % 5 * 20, 5000 + k), *own, words(k % 3 * 15, 900 + k)]))
    docs += [items[4][1] + " " + items[4][1], " ".join(items[3][1].split() * 30)]
    found, hits = decontaminate.Items(items), 0
    for text in docs:
        w, want = text.split(), {}
        shingles = [" ".join(w[j : j + 5]) for j in range(len(w) - 4)]
        for i, t in items:
            t = t.split()
            own = collections.Counter(" ".join(t[j : j + 5]) for j in range(len(t) - 4))
            n = sum(own.values())
            wide, best = min(n, len(shingles)), 0
            for s in range(len(shingles) - wide + 1):
                there = collections.Counter(shingles[s : s + wide])
                common = sum(min(c, there[x]) for x, c in own.items())
                best = max(best, common / (wide + n - common))
            if best >= 0.8:
                want[i] = round(best, 9)
        hits += len(want)
        assert {i: round(v, 9) for i, v, _, _ in found.matches(text, 0.8)} == want
    assert hits > 30


def test_items_shorter_than_a_shingle_are_found_inside_documents():
    items = decontaminate.Items([(1, "tiny"), (2, "Four words of it"), (3, "two words"), (4, "two words"), (5, prose(20, 3))])
    got = lambda text: sorted(items.matches(text, 0.8))
    assert got(prose(30, 1) + " four words, of it " + prose(9, 2)) == [(2, 1.0, 30, 4)]
    assert got("a tiny b Two words c tiny") == [(1, 1.0, 1, 1), (3, 1.0, 3, 2), (4, 1.0, 3, 2)]
    assert got("tiny") == [(1, 1.0, 0, 1)] and got("two wordsmiths") == got("") == got("words of it four") == []
    assert got(prose(20, 3)) == [(5, 1.0, 0, 20)]


def test_hamming_blocks_find_all_within_the_radius():
    rng = np.random.default_rng(0)
    items = decontaminate.Items([(i, prose(30, 1000 + i)) for i in range(50)])
    prints = items.prints[rng.integers(0, 50, 60)].copy()
    for k in range(60):
        for b in rng.choice(64, rng.integers(0, 24), replace=False):
            prints[k] ^= np.uint64(1) << np.uint64(b)
    x, y = np.nonzero(np.bitwise_count(prints[:, None] ^ items.prints[None, :]) <= decontaminate.RADIUS)
    assert set(items.candidates(prints)) == set(zip(x.tolist(), y.tolist()))
