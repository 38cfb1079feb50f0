"""Training of the group graph encoder with Adam: distributed forward pass and partial gradients, weights on the driver.

Groups are dealt into shards by a hash. A shard owns its groups' triples and holds copies of all inputs within as many hops
as there are layers, so the sum of the shards' gradients is the gradient of the undivided graph. Rows know their time slice:
one packed table serves the encoders of all slices, on all interactions so far or on new ones only. Weights are a few small
matrices; only their summed gradients reach the driver.

The items' inputs are written once, to files in the shared folder that all shards map: shards name items by their places there
and have no copies of them. Shards are such files as well, so neither moves through Spark's rows in a training step. There are as
many shards as the interactions need, so that one fits beside others in a worker.
"""

from __future__ import annotations

import json
import math
import time
import uuid

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators.joins import WINDOW_ROWS
from ..sources.storage import file_system, mapped, new_folder, settle


def sigmoid(x):
    return 1 / (1 + np.exp(-np.clip(x, -60, 60)))


class Adam:
    def __init__(self, rate: float, beta1: float = 0.9, beta2: float = 0.999):
        self.rate, self.beta1, self.beta2, self.t, self.m, self.v = rate, beta1, beta2, 0, {}, {}

    def step(self, weights: dict[str, np.ndarray], grads: dict[str, np.ndarray]) -> None:
        self.t += 1
        for k, g in grads.items():
            self.m[k] = self.beta1 * self.m.get(k, 0) + (1 - self.beta1) * g
            self.v[k] = self.beta2 * self.v.get(k, 0) + (1 - self.beta2) * g * g
            m, v = self.m[k] / (1 - self.beta1**self.t), self.v[k] / (1 - self.beta2**self.t)
            weights[k] = weights[k] - self.rate * m / (np.sqrt(v) + 1e-8)


def new_weights(d: int, d_in_group: int, d_in_item: int, layers: int, seed: int = 0) -> dict[str, np.ndarray]:
    rng = np.random.default_rng(seed)
    made = {"wg": rng.normal(0, 0.3, (d, d_in_group)), "bg": np.zeros(d), "wv": rng.normal(0, 0.3, (d, d_in_item)), "bv": np.zeros(d)}
    return made | {f"w{i}": rng.normal(0, 0.3, (d, 2 * d)) for i in range(1, layers + 1)} | {f"b{i}": np.zeros(d) for i in range(1, layers + 1)}


#: Triples whose gaps are worked out together, and items whose inputs are in memory together.
BLOCK, ITEMS = 1 << 18, 1 << 16


def summed(at: np.ndarray, rows: np.ndarray, n: int) -> np.ndarray:
    """(n, d): the sums of rows by their places, added in their order."""
    out = np.empty((n, rows.shape[1]))
    for j in range(rows.shape[1]):
        out[:, j] = np.bincount(at, weights=rows[:, j], minlength=n)
    return out


def forward(weights: dict, x_groups: np.ndarray, src: np.ndarray, dst: np.ndarray, lap: np.ndarray, layers: int) -> list[np.ndarray]:
    """All layers' group vectors."""
    out = [sigmoid(x_groups @ weights["wg"].T + weights["bg"])]
    for i in range(1, layers + 1):
        agg = summed(dst, lap[:, None] * out[-1][src], len(out[-1]))
        out.append(sigmoid(np.hstack([out[-1], agg]) @ weights[f"w{i}"].T + weights[f"b{i}"]))
    return out


def loss_and_gradients(weights: dict, x_groups, x_items, src, dst, lap, owner, held, g, pos, neg, layers: int, penalty: float):
    """Ranking loss of triples of positions (g, pos, neg) and its gradient for every weight.

    owner, held: the positions of groups and of the items in their history. x_items: rows that are read by slices. Vectors of
    items and sides lie by component, so what is as long as triples or the history is one number wide.
    """
    hidden = forward(weights, x_groups, src, dst, lap, layers)
    top, items = hidden[-1], np.empty((len(weights["bv"]), len(x_items)))
    for first in range(0, len(x_items), ITEMS):
        items[:, first : first + ITEMS] = sigmoid(x_items[first : first + ITEMS] @ weights["wv"].T + weights["bv"]).T
    n_groups, n_items, held = len(top), len(x_items), np.asarray(held, np.intp)
    root = np.sqrt(np.maximum(1, np.bincount(owner, minlength=n_groups)))
    side = top.T + np.stack([np.bincount(owner, weights=x[held], minlength=n_groups) for x in items]) / root
    loss, d_side, d_items = 0.0, np.zeros_like(side), np.zeros_like(items)
    for first in range(0, len(g), BLOCK):
        g_, pos_, neg_ = (np.asarray(x[first : first + BLOCK], np.intp) for x in (g, pos, neg))
        gap = np.zeros(len(g_))
        for x, own in zip(items, side):
            gap += (x[pos_] - x[neg_]) * own[g_]
        loss += np.log1p(np.exp(-np.clip(gap, -60, 60))).sum()
        pull = -sigmoid(-gap)
        for x, own, d_x, d_own in zip(items, side, d_items, d_side):
            d_own += np.bincount(g_, weights=pull * (x[pos_] - x[neg_]), minlength=n_groups)
            moved = pull * own[g_]
            d_x += np.bincount(pos_, weights=moved, minlength=n_items)
            d_x -= np.bincount(neg_, weights=moved, minlength=n_items)
    loss += penalty * sum((w * w).sum() for w in weights.values())
    for d_x, d_own in zip(d_items, d_side / root):
        d_x += np.bincount(held, weights=d_own[owner], minlength=n_items)
    grads = {k: 2 * penalty * w for k, w in weights.items()}
    for first in range(0, n_items, ITEMS):
        x = items[:, first : first + ITEMS]
        d_pre = d_items[:, first : first + ITEMS] * x * (1 - x)
        grads["wv"], grads["bv"] = grads["wv"] + d_pre @ x_items[first : first + ITEMS], grads["bv"] + d_pre.sum(1)
    d_top, d = d_side.T, top.shape[1]
    for i in range(layers, 0, -1):
        below = hidden[i - 1]
        agg = summed(dst, lap[:, None] * below[src], len(below))
        d_pre = d_top * hidden[i] * (1 - hidden[i])
        grads[f"w{i}"], grads[f"b{i}"] = grads[f"w{i}"] + d_pre.T @ np.hstack([below, agg]), grads[f"b{i}"] + d_pre.sum(0)
        d_in = d_pre @ weights[f"w{i}"]
        d_top = d_in[:, :d] + summed(src, lap[:, None] * d_in[:, d:][dst], len(below))
    d_pre = d_top * hidden[0] * (1 - hidden[0])
    grads["wg"], grads["bg"] = grads["wg"] + d_pre.T @ x_groups, grads["bg"] + d_pre.sum(0)
    return loss, grads


class Items:
    """The items of the files (path, number) in order of their ids: an item's place counts the rows of all files."""

    def __init__(self, files: list[tuple[str, int]]):
        self.ids = [mapped(f"{path}.v", np.int64) for path, _ in files]
        self.rows = [mapped(f"{path}.x", np.float64).reshape(n, -1) for path, n in files]
        self.starts = np.cumsum([0] + [n for _, n in files])
        self.least = np.array([ids[0] for ids in self.ids], np.int64)

    def find(self, v: np.ndarray) -> np.ndarray:
        """The places of ids."""
        out, of = np.empty(len(v), np.int32), np.searchsorted(self.least, v, "right") - 1
        for i in np.unique(of):
            here = of == i
            at = np.searchsorted(self.ids[i], v[here]) if i >= 0 else None
            if i < 0 or (self.ids[i][np.minimum(at, len(self.ids[i]) - 1)] != v[here]).any():
                raise ValueError("interactions or triples name an item that has no vector")
            out[here] = self.starts[i] + at
        return out

    def take(self, kept: list[np.ndarray], places: np.ndarray) -> np.ndarray:
        """What the files keep of sorted places; kept: self.ids or self.rows."""
        cut = np.searchsorted(places, self.starts)
        return np.concatenate([x[places[a:b] - start] for x, a, b, start in zip(kept, cut[:-1], cut[1:], self.starts)])


class Used:
    """The inputs of a shard's items, read from the files slice by slice."""

    def __init__(self, items: Items, places: np.ndarray):
        self.items, self.places = items, places

    def __len__(self) -> int:
        return len(self.places)

    def __getitem__(self, some: slice) -> np.ndarray:
        return self.items.take(self.items.rows, self.places[some])


def item_files(items: DataFrame) -> list[tuple[str, int]]:
    """items (v, vec) as files of ids and of inputs, in order of ids: (path, number) of each; a row per file reaches the driver."""
    folder = new_folder(items.sparkSession, "items")

    def write(batches):
        files, at = file_system(f"{folder}/{uuid.uuid4().hex}")
        least, n = None, 0
        files.create_dir(at.rsplit("/", 1)[0], recursive=True)
        with files.open_output_stream(f"{at}.v") as ids, files.open_output_stream(f"{at}.x") as rows:
            for batch in batches:
                if len(batch):
                    least, n = batch["v"][0].as_py() if least is None else least, n + len(batch)
                    ids.write(batch["v"].to_numpy().tobytes())
                    rows.write(batch["vec"].flatten().to_numpy().tobytes())
        if n:
            yield pa.RecordBatch.from_pydict({"least": pa.array([least], pa.int64()), "name": [at.rsplit("/", 1)[1]], "n": pa.array([n], pa.int64())})

    ranged = items.select("v", "vec").repartitionByRange("v").sortWithinPartitions("v")
    return [(f"{folder}/{r['name']}", r["n"]) for r in sorted(ranged.mapInArrow(write, "least long, name string, n long").collect())]


#: Interactions of a shard on average, at most.
PAIRS = 1 << 18


def shards(groups: DataFrame, items: DataFrame, edges: DataFrame, interactions: DataFrame, triples: DataFrame, n: int, hops: int = 2) -> DataFrame:
    """(shard, data): for each of n shards, or of more where interactions are many, its own groups, what lies within `hops` of
    them, and its triples, packed in a file that data describes.

    edges (src, dst, lap), interactions (g, v) and triples (g, pos, neg) may have a column slice; without it all is of slice
    0. An interaction's slice is the one in which it is new, an edge's the one whose graph has it.
    """
    tagged = lambda df: df if "slice" in df.columns else df.withColumn("slice", F.lit(0))
    edges, interactions, triples = tagged(edges), tagged(interactions), tagged(triples)
    col, needed, files = F.col, math.ceil(interactions.count() / PAIRS), item_files(items)
    place, n = _places(groups, interactions, n, needed), max(n, needed)
    reach, into = place, edges.limit(0).withColumn("shard", F.lit(0))
    for _ in range(hops):
        into = edges.join(reach.select(col("g").alias("dst"), "shard"), "dst")
        reach = reach.unionByName(into.select(col("src").alias("g"), "shard")).distinct()
    mine = reach.join(groups, "g").join(place.select("g", col("shard").alias("home")), "g").select("shard", "g", (col("home") == col("shard")).cast("long").alias("own"), "vec")
    pieces = [
        _pieces(mine, "group", files),
        _pieces(into.select("shard", "src", "dst", "slice", "lap"), "edge", files),
        _pieces(interactions.join(place, "g").select("shard", "g", "v", "slice"), "seen", files),
        _pieces(triples.join(place, "g").select("shard", "g", "pos", "neg", "slice"), "triple", files),
    ]
    rows = pieces[0]
    for p in pieces[1:]:
        rows = rows.unionByName(p)
    folder = new_folder(groups.sparkSession, "packed")
    return settle(rows.repartitionById(n, "shard").groupBy("shard").applyInArrow(lambda part: _pack(part, files, folder), "shard int, data string"), "shards")


def _places(groups: DataFrame, interactions: DataFrame, n: int, needed: int) -> DataFrame:
    """(g, shard): groups are dealt by a hash; where more than n shards are needed and groups are few, by their numbers of
    interactions, so that shards are alike."""
    if needed <= n or groups.count() > WINDOW_ROWS:
        return groups.select("g", F.pmod(F.xxhash64("g"), F.lit(max(n, needed))).cast("int").alias("shard"))
    sizes = groups.select("g").join(interactions.groupBy("g").agg(F.count("*").alias("size")), "g", "left")
    at = F.row_number().over(Window.orderBy(F.desc_nulls_last("size"), "g")) - 1  # WINDOW_ROWS at most
    return F.broadcast(settle(sizes.select("g", F.pmod(at, F.lit(needed)).cast("int").alias("shard")), "places"))


#: The columns of each kind of rows as they are packed, after the shard; the keys come first. An item's id turns into its place.
KINDS = {
    "group": {"g": np.int64, "own": np.int8, "vec": np.float64},
    "edge": {"src": np.int64, "dst": np.int64, "slice": np.int16, "lap": np.float64},
    "seen": {"g": np.int64, "v": np.int32, "slice": np.int16},
    "triple": {"g": np.int64, "pos": np.int32, "neg": np.int32, "slice": np.int16},
}
#: Columns that hold items, columns that rows are not sorted by, and the rows that a task brings together in pieces.
NAMED, FREE, ROWS = ("v", "pos", "neg"), ("own", "vec", "lap"), 1 << 20


def _pieces(rows: DataFrame, kind: str, files: list[tuple[str, int]]) -> DataFrame:
    """(shard, kind, n, columns): rows of one kind as bytes of whole columns, so that few rows have to be brought together."""
    types = KINDS[kind]

    def run(batches):
        held, n, items = [], 0, Items(files)

        def flush():
            shard = np.concatenate([h[0] for h in held])
            order = np.argsort(shard, kind="stable")
            ends = np.flatnonzero(np.diff(shard[order])) + 1
            cuts = list(zip([0, *ends], [*ends, len(shard)]))
            columns = [np.concatenate([h[i] for h in held])[order] for i in range(1, len(types) + 1)]
            found = [[c[a:b].tobytes() for c in columns] for a, b in cuts]
            return pa.RecordBatch.from_arrays(
                [pa.array([shard[order[a]] for a, _ in cuts], pa.int32()), pa.array([kind] * len(cuts)), pa.array([b - a for a, b in cuts], pa.int64()), pa.array(found, pa.list_(pa.binary()))], ["shard", "kind", "n", "columns"]
            )

        for batch in batches:
            if not len(batch):
                continue
            plain = [batch["shard"].to_numpy()]
            for c, kept in types.items():
                x = batch[c].flatten().to_numpy().reshape(len(batch), -1) if c == "vec" else batch[c].to_numpy()
                plain.append(items.find(x) if c in NAMED else x.astype(kept))
            held.append(plain)
            n += len(batch)
            if n >= ROWS:
                yield flush()
                held, n = [], 0
        if held:
            yield flush()

    return rows.mapInArrow(run, "shard int, kind string, n long, columns array<binary>")


def _pack(rows: pa.Table, files: list[tuple[str, int]], folder: str) -> pa.Table:
    """A shard's pieces as a file of sorted arrays; no row becomes an object."""
    pieces = list(zip(rows["kind"].to_pylist(), rows["n"].to_pylist(), rows["columns"]))

    def part(kind: str) -> list[np.ndarray]:
        """The columns of one kind, in order of its keys."""
        own, plain = [(n, c) for k, n, c in pieces if k == kind], []
        total = sum(n for n, _ in own)
        for i, (name, kept) in enumerate(KINDS[kind].items()):
            column = np.frombuffer(b"".join(c.values[i].as_buffer() for _, c in own), kept)
            plain.append(column.reshape(total, total and -1) if name == "vec" else column)
        order = np.lexsort([c for c, name in zip(plain, KINDS[kind]) if name not in FREE][::-1])
        return [c[order] for c in plain]

    def find(known: np.ndarray, x: np.ndarray) -> np.ndarray:
        at = np.searchsorted(known, x)
        if len(x) and (not len(known) or (known[np.minimum(at, len(known) - 1)] != x).any()):
            raise ValueError("a shard lacks a group that its rows name")
        return at.astype(np.int32)

    groups, own, xg = part("group")
    src, dst, edge_slice, lap = part("edge")
    owner, held, seen_slice = part("seen")
    g, pos, neg, slices = part("triple")
    shard = rows["shard"][0].as_py()
    del rows, pieces
    new = np.ones(len(owner), bool)
    new[1:] = (owner[1:] != owner[:-1]) | (held[1:] != held[:-1])  # an interaction counts from its first slice on
    owner, held, seen_slice, g = find(groups, owner[new]), held[new], seen_slice[new], find(groups, g)
    used = np.unique(np.concatenate([held, pos, neg]))
    held, pos, neg = (find(used, x) for x in (held, pos, neg))
    pairs, asked = owner * np.int64(len(used)) + held, g * np.int64(len(used)) + pos
    at = np.minimum(np.searchsorted(pairs, asked), len(pairs) - 1)
    first = (pairs[at] != asked) | (seen_slice[at] == slices) if len(pairs) else np.ones(len(g), bool)
    arrays = dict(
        ids=groups, own=own > 0, xg=xg, src=find(groups, src), dst=find(groups, dst), lap=lap, edge_slice=edge_slice,
        owner=owner, held=held, seen_slice=seen_slice, g=g, pos=pos, neg=neg, first=first, slice=slices, used=used,
    )
    name, starts, at = f"{folder}/{uuid.uuid4().hex}", {}, 0
    where, path = file_system(name)
    where.create_dir(path.rsplit("/", 1)[0], recursive=True)
    with where.open_output_stream(path) as out:
        for k, x in arrays.items():
            starts[k] = (x.dtype.str, x.shape, at)
            out.write(np.ascontiguousarray(x).tobytes() + bytes(-x.nbytes % 64))
            at += x.nbytes + -x.nbytes % 64
    return pa.table({"shard": pa.array([shard], pa.int32()), "data": [json.dumps({"path": name, "arrays": starts, "items": files})]})


def _unpack(data: str, t: int) -> dict[str, np.ndarray]:
    """A shard as of slice t: its graph and the history until then. Its arrays are mapped from its file."""
    held = json.loads(data)
    whole, s = mapped(held["path"], np.uint8), {}
    for k, (kind, shape, at) in held["arrays"].items():
        size = math.prod(shape) * np.dtype(kind).itemsize
        s[k] = whole[at : at + size].view(kind).reshape(shape)
    here, until = s["edge_slice"] == t, s["seen_slice"] <= t
    s |= {k: s[k][here] for k in ("src", "dst", "lap")} | {k: s[k][until] for k in ("owner", "held")}
    s["items"] = Items(held["items"])
    return s | {"xv": Used(s["items"], s["used"])}


def gradients(packed: DataFrame, weights: dict[str, np.ndarray], layers: int, t: int = 0, new_only: bool = False, batch: int = 0, batches: int = 1, steps: int = 1, rate: float = 1e-1) -> tuple[float, dict[str, np.ndarray], int]:
    """Loss and gradients, without the penalty, summed over the triples of one batch, and their number.

    new_only takes the triples of slice t alone, else each triple of a slice up to t once. steps > 1 lets each shard take
    steps of its own first.
    """

    def run(parts):
        sums, n = {}, 0
        for part in parts:
            for data in part["data"]:
                s = _unpack(data, t)
                chosen = (s["slice"] == t) if new_only else (s["slice"] <= t) & s["first"]
                if batches > 1 and len(s["used"]):
                    names = s["items"].take(s["items"].ids, s["used"])
                    chosen &= (s["ids"][s["g"]] * 1_000_003 + names[s["pos"]] * 97 + names[s["neg"]]) % batches == batch
                g, pos, neg = s["g"][chosen], s["pos"][chosen], s["neg"][chosen]
                if not len(g):
                    continue
                local, own = dict(weights), Adam(rate)
                for step in range(steps):
                    loss, grads = loss_and_gradients(local, s["xg"], s["xv"], s["src"], s["dst"], s["lap"], s["owner"], s["held"], g, pos, neg, layers, 0.0)
                    if step + 1 < steps:
                        own.step(local, {k: v / len(g) for k, v in grads.items()})
                n += len(g)
                for k, v in (("loss", np.array([loss])), *grads.items()):
                    sums[k] = sums.get(k, 0) + v
        yield pd.DataFrame([(k, np.ravel(v).tolist(), n) for k, v in sums.items()], columns=["name", "value", "n"])

    def total(rows):
        return pd.DataFrame({"name": [rows["name"].iloc[0]], "value": [np.sum(rows["value"].tolist(), axis=0)], "n": [int(rows["n"].sum())]})

    partial = packed.select("data").mapInPandas(run, "name string, value array<double>, n long")
    found = partial.groupBy("name").applyInPandas(total, "name string, value array<double>, n long").collect()  # a row per weight matrix
    sums = {r["name"]: np.array(r["value"]) for r in found}
    if not sums:
        return 0.0, {}, 0
    return float(sums["loss"][0]), {k: sums[k].reshape(w.shape) for k, w in weights.items()}, found[0]["n"]


def train(packed: DataFrame, weights: dict[str, np.ndarray], layers: int = 2, rate: float = 1e-1, penalty: float = 1e-6, epochs: int = 20, tolerance: float = 1e-3, sync_every: int = 1, batches: int = 1, t: int = 0, new_only: bool = False) -> tuple[dict, list[dict]]:
    """Adam over mini-batches of triples; returns the weights and a log of (epoch, loss, seconds).

    packed comes from shards(). An epoch goes through all batches; it ends once the loss changes by less than `tolerance`.
    sync_every > 1 lets each shard take that many steps of its own before gradients are summed, as decentralised trainers
    skip broadcasts.
    """
    adam, log, began = Adam(rate), [], time.time()
    weights = dict(weights)
    for epoch in range(epochs):
        loss, n = 0.0, 0
        for batch in range(batches):
            part, grads, m = gradients(packed, weights, layers, t, new_only, batch, batches, sync_every, rate)
            if m:
                squares = sum(float((w * w).sum()) for w in weights.values())
                loss, n = loss + part + m * penalty * squares, n + m
                adam.step(weights, {k: grads[k] / m + 2 * penalty * w for k, w in weights.items()})
        if not n:
            break
        log.append({"epoch": epoch, "loss": loss / n, "seconds": time.time() - began})
        if len(log) > 1 and abs(log[-2]["loss"] - log[-1]["loss"]) < tolerance * abs(log[-2]["loss"]):
            break
    return weights, log


def encode(packed: DataFrame, weights: dict[str, np.ndarray], layers: int, t: int = 0) -> DataFrame:
    """(g, vec): the top layer of every group in the graph of slice t."""

    def run(parts):
        for part in parts:
            for data in part["data"]:
                s = _unpack(data, t)
                top = forward(weights, s["xg"], s["src"], s["dst"], s["lap"], layers)[-1]
                yield pd.DataFrame({"g": s["ids"][s["own"]], "vec": list(top[s["own"]])})

    return packed.select("data").mapInPandas(run, "g long, vec array<double>")
