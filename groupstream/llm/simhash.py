"""SimHash near-duplicates by tiled exact comparison.

Fingerprints are distinct rows first. They are dealt into tiles by how many bits are set in each part of them: the
difference of those counts, added over the parts, is at most the Hamming distance, so two tiles whose counts differ by
more than the radius are skipped, and inside a pair of tiles the same holds for blocks of rows. What is left is compared
pair by pair with numpy's exclusive or and bit counts. A pair of tiles returns a spanning forest of its links, never all
pairs of a group of near copies, and components join the forests.

Only the histogram of bit counts reaches the driver (at most 17**4 cells for 64 bits, whatever the data), and a box for each
tile leaves it; which tiles meet is decided in Spark.

Cases: null and empty texts have the fingerprint zero and are linked like others; texts shorter than a shingle count as
one shingle; rows without an id get a fingerprint but name no component; repeated rows and ties share one fingerprint;
ids have to be whole numbers; an empty table gives an empty result; other columns are ignored by the query and kept by
`keep_one_of_each`, which lets only documents go whose exact similarity to one that stays, or to one that goes with it, is
high enough. Of rows equal in id and text it keeps the one with the least hash of all columns. Rows without an id, and rows
that share an id but not the text, can't be named by it: they stay, and are no one's copies.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, long_id, slices
from .components import connected_components

TILE, TILES, BLOCK = 16_384, 128, 256
#: Shingles in a tile of documents that are compared exactly, about 4 MB.
TILE_SHINGLES = 1 << 19
SEED = 42


def _spans(words: list[bytes], k: int) -> tuple[bytes, list[int], list[int]]:
    """The words joined by single spaces, and where each run of k of them (or the only, shorter one) starts and ends."""
    lengths = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(lengths + 1) - 1
    starts = ends - lengths
    k = min(k, len(words))
    return b" ".join(words), starts[: len(words) - k + 1].tolist(), ends[k - 1 :].tolist()


def fingerprint(text: bytes | None, k: int, bits: int) -> str:
    words = (text or b"").lower().split()
    if not words:
        return "0" * (bits // 4)
    joined, starts, ends = _spans(words, k)
    out = ""
    for seed in range(SEED, SEED + bits // 64):
        counts = np.zeros(64, np.int64)
        for at in range(0, len(starts), 1 << 15):
            part = [xxhash.xxh64_intdigest(joined[a:b], seed) for a, b in zip(starts[at : at + (1 << 15)], ends[at : at + (1 << 15)])]
            counts += np.unpackbits(np.array(part, ">u8").view(np.uint8)).reshape(-1, 64).sum(0, dtype=np.int32)
        out += np.packbits(2 * counts > len(starts)).tobytes().hex()
    return out


def fingerprints(docs: DataFrame, k: int = 4, bits: int = 64, text: str = "text", id_column: str = "doc_id") -> DataFrame:
    """(id, fingerprint) for every row; the fingerprint in lowercase hexadecimal digits."""

    def run(batches):
        for b in slices(batches):
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array([fingerprint(t, k, bits) for t in b.column("text").to_pylist()], pa.string())], ["id", "fingerprint"])

    return docs.select(long_id(docs, id_column).alias("id"), F.col(text).cast("binary").alias("text")).mapInArrow(run, "id long, fingerprint string")


def _parts(bits: int) -> int:
    return 4 if bits == 64 else 2


def _counts(bits: int):
    """Columns p0, p1, ...: the set bits of each part of the fingerprint."""
    width = bits // 4 // _parts(bits)
    made = []
    for i in range(_parts(bits)):
        pieces = [F.bit_count(F.conv(F.substring("fingerprint", 1 + i * width + j, 8), 16, 10).cast("long")) if width >= 8 else F.bit_count(F.conv(F.substring("fingerprint", 1 + i * width + j, width), 16, 10).cast("long")) for j in range(0, width, 8)]
        made.append(sum(pieces[1:], pieces[0]).cast("int").alias(f"p{i}"))
    return made


def split_cells(cells: np.ndarray, weight: np.ndarray, most: int) -> np.ndarray:
    """A tile for each cell: halves along the widest side until a tile holds at most `most` rows or one cell."""
    tile, todo, n = np.zeros(len(cells), np.int64), [np.arange(len(cells))], 0
    while todo:
        own = todo.pop()
        if weight[own].sum() > most and len(own) > 1:
            at = cells[own]
            axis = int(np.argmax(at.max(0) - at.min(0)))
            own = own[np.argsort(at[:, axis], kind="stable")]
            run = np.cumsum(weight[own])
            half = int(np.clip(np.searchsorted(run, run[-1] / 2), 1, len(own) - 1))
            todo += [own[:half], own[half:]]
        else:
            tile[own] = n
            n += 1
    return tile


def _gap(low_a, high_a, low_b, high_b):
    return np.maximum(0, np.maximum(low_a - high_b, low_b - high_a)).sum(-1)


def _unpack(rows: bytes, bits: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """ids, words and bit counts of the parts, in the tile's order."""
    table = np.frombuffer(rows, np.uint64).reshape(-1, 1 + bits // 64)
    words = table[:, 1:]
    width = bits // _parts(bits)
    if width >= 64:
        counts = np.bitwise_count(words).astype(np.int64)
    else:
        counts = np.bitwise_count((words >> np.arange(64 - width, -1, -width, dtype=np.uint64)) & np.uint64((1 << width) - 1)).astype(np.int64)
    return table[:, 0].view(np.int64), words, counts


def forest(left: bytes, right: bytes | None, bits: int, radius: int) -> list[tuple[int, int]]:
    """Links between two packed tiles (or inside one) that join all that is linked, none of them needless."""
    one = right is None
    parts = [_unpack(x, bits) for x in ((left,) if one else (left, right))]
    ids, offset = np.concatenate([p[0] for p in parts]), 0 if one else len(parts[0][0])
    parent, label, out = np.arange(len(ids)), np.arange(len(ids)), []

    def root(i: int) -> int:
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    def blocks(p):
        return [(i, p[1][i : i + BLOCK], p[2][i : i + BLOCK].min(0), p[2][i : i + BLOCK].max(0)) for i in range(0, len(p[0]), BLOCK)]

    first, second = blocks(parts[0]), blocks(parts[-1])
    low, high = np.array([b[2] for b in second]), np.array([b[3] for b in second])
    for i, a, low_a, high_a in first:
        near = np.flatnonzero(_gap(low_a, high_a, low, high) <= radius)
        for j, b in ((second[n][0], second[n][1]) for n in near if not one or second[n][0] >= i):
            la, lb = label[i : i + len(a)], label[offset + j : offset + j + len(b)]
            if la[0] == lb[0] and (la == la[0]).all() and (lb == lb[0]).all():
                continue
            far = np.bitwise_count(a[:, 0][:, None] ^ b[:, 0][None, :])
            for w in range(1, a.shape[1]):
                far = far + np.bitwise_count(a[:, w][:, None] ^ b[:, w][None, :])
            x, y = np.nonzero(far <= radius)
            x, y = x + i, y + offset + j
            fresh = label[x] != label[y]
            if not fresh.any():
                continue
            _, first_of = np.unique(label[x[fresh]] * len(ids) + label[y[fresh]], return_index=True)
            for u, v in zip(x[fresh][first_of].tolist(), y[fresh][first_of].tolist()):
                if (ru := root(u)) != (rv := root(v)):
                    parent[max(ru, rv)] = min(ru, rv)
                    out.append((int(ids[u]), int(ids[v])))
            label = parent
            while (label != (up := label[label])).any():
                label = up
            parent = label.copy()
    return out


def links(fps: DataFrame, bits: int, radius: int) -> DataFrame:
    """(id, fingerprint), distinct in both -> (a, b): a spanning forest of the links within each pair of tiles."""
    spark = fps.sparkSession
    names = [f"p{i}" for i in range(_parts(bits))]
    counted = fps.select("*", *_counts(bits))
    cells = counted.groupBy(*names).count().toPandas()
    if cells.empty:
        return spark.createDataFrame([], "a long, b long")
    at, weight = cells[names].to_numpy(np.int64), cells["count"].to_numpy(np.int64)
    most = int(np.clip(weight.sum() // TILES, TILE, 1 << 20))
    tile = split_cells(at, weight, most)
    n = int(tile.max()) + 1
    low, high, rows = np.full((n, len(names)), 1 << 20), np.zeros((n, len(names)), np.int64), np.zeros(n, np.int64)
    np.minimum.at(low, tile, at)
    np.maximum.at(high, tile, at)
    np.add.at(rows, tile, weight)
    subs = -(-rows // (2 * most))  # one cell may hold more than a tile should: dealt on by the id
    start = np.cumsum(subs) - subs
    box = np.repeat(np.arange(n), subs)
    of_cell = spark.createDataFrame(pd.DataFrame(at, columns=names).assign(start=start[tile], subs=subs[tile]), ", ".join(f"{c} int" for c in names) + ", start long, subs long")
    boxes = spark.createDataFrame(pd.DataFrame({"tile": np.arange(len(box)), "low": low[box].tolist(), "high": high[box].tolist()}), "tile long, low array<long>, high array<long>")
    other = boxes.select(F.col("tile").alias("t2"), F.col("low").alias("low2"), F.col("high").alias("high2"))
    gap = F.lit(0)
    for i in range(len(names)):
        a, b = (F.get(x, F.lit(i)) - F.get(y, F.lit(i)) for x, y in (("low", "high2"), ("low2", "high")))
        gap = gap + F.greatest(F.lit(0), a, b)
    # One row for each tile, and what is compared with it: the tiles' boxes decide, so this is a condition, not a key.
    near = boxes.join(other, (F.col("tile") <= F.col("t2")) & (gap <= radius)).withColumn("pair", F.col("tile") * len(box) + F.col("t2"))
    sides = cut(near.select("pair", F.explode(F.array_distinct(F.array("tile", "t2"))).alias("tile")), "tile-pairs")
    words = bits // 64

    def pack(key, rows):
        rows = rows.sort_values(names + ["id"])
        table = np.empty((len(rows), 1 + words), np.uint64)
        table[:, 0] = rows["id"].to_numpy(np.int64).view(np.uint64)
        table[:, 1:] = np.frombuffer(bytes.fromhex("".join(rows["fingerprint"])), ">u8").reshape(-1, words)
        return pd.DataFrame({"tile": [key[0]], "rows": [table.tobytes()]})

    def compare(rows):
        packed = rows.sort_values("tile")["rows"].tolist()
        return pd.DataFrame(forest(packed[0], packed[1] if len(packed) > 1 else None, bits, radius), columns=["a", "b"], dtype="int64")

    dealt = counted.join(F.broadcast(of_cell), names).withColumn("tile", F.col("start") + F.pmod(F.xxhash64("id"), F.col("subs")))
    tiles = cut(dealt.groupBy("tile").applyInPandas(pack, "tile long, rows binary"), "tiles")
    return tiles.join(sides, "tile").groupBy("pair").applyInPandas(compare, "a long, b long")


def near_duplicates(docs: DataFrame, k: int = 4, bits: int = 64, radius: int = 4, text: str = "text", id_column: str = "doc_id") -> DataFrame:
    """(id, fingerprint, component_id): component_id is the smallest id that is reachable over links."""
    each = cut(fingerprints(docs, k, bits, text, id_column), "fingerprints")
    distinct = cut(each.groupBy("fingerprint").agg(F.min("id").alias("id")), "fingerprints-distinct")
    roots = connected_components(links(distinct.where("id is not null").select("id", "fingerprint"), bits, radius))
    named = distinct.join(roots.withColumnRenamed("node", "id"), "id", "left").select(F.col("fingerprint").alias("f"), F.coalesce("root", "id").alias("component_id"))
    return each.join(named, F.col("fingerprint") == F.col("f")).select("id", "fingerprint", "component_id")


def shingle_sets(docs: DataFrame, k: int, text: str = "text", id_column: str = "doc_id") -> DataFrame:
    """(id, shingles): the distinct hashes of each text's word shingles."""

    def one(value: bytes | None) -> list[int]:
        words = (value or b"").lower().split()
        if not words:
            return []
        joined, starts, ends = _spans(words, k)
        return np.unique(np.array([xxhash.xxh64_intdigest(joined[a:b], SEED) for a, b in zip(starts, ends)], np.uint64)).view(np.int64).tolist()

    def run(batches):
        for b in slices(batches):
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array([one(t) for t in b.column("text").to_pylist()], pa.list_(pa.int64()))], ["id", "shingles"])

    return docs.select(long_id(docs, id_column).alias("id"), F.col(text).cast("binary").alias("text")).mapInArrow(run, "id long, shingles array<long>")


def _words(bits: int):
    """The fingerprint as numbers of 32 bits."""
    return [F.conv(F.substring("fingerprint", 1 + 8 * i, 8), 16, 10).cast("long") for i in range(bits // 32)]


def verified_links(rows: pd.DataFrame, similarity: float) -> list[tuple[int, int]]:
    """Links of two tiles (or inside one) between labels: every pair of sets that is similar enough is joined by them, none is needless.

    The distance of Jaccard is a metric, so two sets whose distances to the leader differ by more than the limit are
    passed over, like those whose sizes rule the similarity out or whose labels are joined already.
    """
    rows = rows.sort_values(["side", "id"])
    sets, label = [np.asarray(x, np.int64) for x in rows["shingles"]], rows["label"].to_numpy(np.int64)
    size, away, second = np.array([len(x) for x in sets]), rows["away"].to_numpy(float), rows["side"].to_numpy() == 1
    known, codes = np.unique(np.concatenate(sets), return_inverse=True)
    codes = np.split(codes, np.cumsum(size)[:-1])
    mark = np.zeros(len(known), np.int64)
    family = np.unique(label, return_inverse=True)[1]
    own, out = not second.any(), []
    for u in range(len(sets) if own else int((~second).sum())):
        fit = (family != family[u]) & (np.minimum(size, size[u]) >= similarity * np.maximum(size, size[u])) & (np.abs(away - away[u]) <= 1 - similarity + 1e-9)
        fit &= np.arange(len(sets)) > u if own else second
        fit = np.flatnonzero(fit & (size > 0))
        if not len(fit):
            continue
        mark[codes[u]] = 1
        common = np.add.reduceat(mark[np.concatenate([codes[v] for v in fit])], np.cumsum(size[fit]) - size[fit])
        mark[codes[u]] = 0
        for v in fit[common >= similarity * (size[fit] + size[u] - common)]:
            if family[v] != family[u]:
                family[family == family[v]] = family[u]
                out.append((int(label[u]), int(label[v])))
    return out


def verified_copies(docs: DataFrame, k: int = 5, bits: int = 128, radius: int = 28, similarity: float = 0.8, text: str = "text", id_column: str = "doc_id") -> DataFrame:
    """(id): documents that go, all but the smallest id of each group of near copies.

    Linked fingerprints make candidate groups, and in these all pairs of texts whose shingles have an exact Jaccard
    similarity of at least `similarity` are joined; what is joined is a group of near copies. The member nearest to the
    majority of a candidate group's bits, which is the original where copies have edits of their own, leads it and is
    compared with all others, which settles most groups. Those that it is not similar to are dealt into tiles and
    compared with each other and with those settled members that their distances to the leader do not rule out.
    """
    found = near_duplicates(docs, k, bits, radius, text, id_column).where("id is not null")
    unclear = found.groupBy("id").agg(F.min("fingerprint").alias("f1"), F.max("fingerprint").alias("f2")).where("f1 <> f2").select("id")
    found = found.join(unclear, "id", "left_anti")
    groups = found.groupBy("component_id").agg(F.count("*").alias("n")).where("n > 1").select("component_id")
    members = cut(found.join(groups, "component_id").select(F.col("component_id").alias("group"), "id", "fingerprint").distinct(), "members")
    # Neither this list of ids nor that of documents that go has a bound, so texts meet them in a shuffle at every size.
    mine = docs.join(members.select(F.col("id").alias("member")).hint("merge"), F.col(id_column) == F.col("member"), "left_semi")
    left = cut(members.join(shingle_sets(mine, k, text, id_column).groupBy("id").agg(F.min("shingles").alias("shingles")), "id"), "member-shingles")
    bit = [F.sum(F.shiftright(w, j).bitwiseAND(F.lit(1).cast("long"))).alias(f"b{i}_{j}") for i, w in enumerate(_words(bits)) for j in range(32)]
    sums = left.groupBy("group").agg(F.count("*").alias("n"), *bit).where("n > 1")
    majority = [sum((F.shiftleft((2 * F.col(f"b{i}_{j}") > F.col("n")).cast("long"), j) for j in range(1, 32)), (2 * F.col(f"b{i}_0") > F.col("n")).cast("long")).alias(f"m{i}") for i in range(bits // 32)]
    near = left.select("group", "id", *[w.alias(f"w{i}") for i, w in enumerate(_words(bits))]).join(sums.select("group", *majority), "group")
    away = sum((F.bit_count(F.col(f"w{i}").bitwiseXOR(F.col(f"m{i}"))) for i in range(1, bits // 32)), F.bit_count(F.col("w0").bitwiseXOR(F.col("m0"))))
    leaders = near.groupBy("group").agg(F.min(F.struct(away.alias("away"), "id")).alias("best")).select(F.col("best.id").alias("id"))
    first = left.join(leaders, "id", "left_semi").select("group", F.col("id").alias("leader"), F.col("shingles").alias("first"))
    common = F.size(F.array_intersect("shingles", "first"))
    union = F.size("shingles") + F.size("first") - common
    judged = cut(left.join(first, "group").select("group", "id", "leader", F.size("shingles").alias("n"), (common >= F.lit(similarity) * union).alias("close"), F.when(union > 0, 1 - common / union).otherwise(0.0).alias("away")), "judged")
    linked = cut(_links_of_the_rest(left, judged, similarity), "verified-links")
    roots = connected_components(linked).withColumnRenamed("node", "label")
    label = F.when(F.col("close"), F.col("leader")).otherwise(F.col("id"))
    families = judged.select("id", label.alias("label")).join(roots, "label", "left").select("id", F.coalesce("root", "label").alias("family"))
    stays = families.groupBy("family").agg(F.min("id").alias("stays"))
    return cut(families.join(stays, "family").where("id <> stays").select("id"), "gone")


def _links_of_the_rest(left: DataFrame, judged: DataFrame, similarity: float) -> DataFrame:
    """(a, b): links between labels, which are the leader's id for what is close to it, else one's own id.

    Sets of the rest meet by pairs of tiles of TILE_SHINGLES; equal sets meet as one, by a digest of 128 bits.
    """
    rest = judged.where("not close")
    reach = rest.groupBy("group").agg(F.min("away").alias("from"))
    near = judged.where("close").join(reach, "group").where(F.col("away") >= F.col("from") - (1 - similarity) - 1e-9)
    asked = near.select("id", "leader", "close", "away").unionByName(rest.select("id", "leader", "close", "away"))
    digest = F.md5(F.concat_ws(",", F.col("shingles").cast("array<string>")))
    sets = cut(left.select("group", "id", "shingles").join(asked, "id").withColumn("digest", digest), "rest")
    same = sets.groupBy("group", "digest").agg(F.min("id").alias("id"), F.count("*").alias("copies"))
    one = sets.join(same.select("id"), "id", "left_semi").withColumn("label", F.when(F.col("close"), F.col("leader")).otherwise(F.col("id")))
    equal = sets.where("not close").join(same.where("copies > 1").select("group", "digest", F.col("id").alias("least")), ["group", "digest"]).where("id <> least").select(F.col("id").alias("a"), F.col("least").alias("b"))
    weight = F.sum(F.when(F.col("close"), F.size("shingles")).otherwise(0)), F.sum(F.when(F.col("close"), 0).otherwise(F.size("shingles")))
    tiles = one.groupBy("group").agg(*[(1 + F.floor(w / TILE_SHINGLES)).alias(c) for w, c in zip(weight, ("n_near", "n_rest"))])
    dealt = one.join(tiles, "group").withColumn("tile", F.pmod(F.xxhash64("id"), F.when(F.col("close"), F.col("n_near")).otherwise(F.col("n_rest"))))
    other = F.sequence(F.lit(0).cast("long"), F.col("n_rest") - 1)
    pair = lambda i, j, mixed, side: F.struct(i.alias("i"), j.alias("j"), F.lit(mixed).alias("mixed"), side.cast("int").alias("side"))
    with_rest = F.transform(other, lambda j: pair(F.col("tile"), j, True, F.lit(0)))
    with_near = F.transform(F.sequence(F.lit(0).cast("long"), F.col("n_near") - 1), lambda i: pair(i, F.col("tile"), True, F.lit(1)))
    among = F.transform(other, lambda j: pair(F.least("tile", j), F.greatest("tile", j), False, F.col("tile") > j))
    sides = dealt.select("group", "id", "shingles", "away", "label", F.explode(F.when(F.col("close"), with_rest).otherwise(F.concat(with_near, among))).alias("p"))

    def compare(rows):
        return pd.DataFrame(verified_links(rows, similarity), columns=["a", "b"], dtype="int64")

    flat = sides.select("group", "id", "shingles", "away", "label", "p.*")
    return flat.groupBy("group", "mixed", "i", "j").applyInPandas(compare, "a long, b long").unionByName(equal)


def keep_one_of_each(docs: DataFrame, text: str = "text", id_column: str = "doc_id", **kw) -> DataFrame:
    """The documents that stay, unchanged: one of each group of near copies, and of rows equal in id and text one."""
    gone = verified_copies(docs, text=text, id_column=id_column, **kw).select(F.col("id").alias("gone_id")).hint("merge")
    left = docs.join(gone, F.col(id_column) == F.col("gone_id"), "left_anti")
    # Ids that occur once have nothing to compare: only the few others are put in order.
    again = docs.where(F.col(id_column).isNotNull()).groupBy(F.col(id_column).alias("again_id")).count().where("count > 1").select("again_id")
    if again.isEmpty():
        return left
    again = cut(again, "repeated-ids")
    same = F.col(id_column) == F.col("again_id")
    first = Window.partitionBy(id_column, text).orderBy(F.xxhash64(*docs.columns))
    one = left.join(again.hint("merge"), same, "left_semi").withColumn("__n", F.row_number().over(first)).where("__n = 1").drop("__n")
    return left.join(again.hint("merge"), same, "left_anti").unionByName(one)


def query(spark, sf_dir):
    from .common import table

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return near_duplicates(docs).select(F.col("id").alias("doc_id"), "fingerprint", "component_id")
