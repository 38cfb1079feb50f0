r"""Benchmark decontamination by SimHash of item-sized windows.

Every document is read as windows of as many words as each benchmark item has (the whole text, if it is shorter). A
window's 64-bit SimHash weighs its five-word shingles by how often they occur. Fingerprints are cut into four blocks of
16 bits: two fingerprints within RADIUS = 19 bits have a block within 4, which both sides meet halfway, the items listed
under every value within 2 bits of their block, the window asking for every value within 2 bits of its own. Each
candidate's weighted Jaccard similarity is then computed from the shingles themselves.

Windows that cannot reach the similarity are skipped before they are fingerprinted: a similarity t between n and m
shingles needs t / (1 + t) * (n + m) of them in common, and prefix sums count how many of a window's shingles occur in
items of its size. That bound loses nothing.

Words are runs of letters, digits and underscores, in lower case. Items are held by every task, ITEMS at a time; a larger
benchmark takes more passes.

Cases: null and empty texts and items have no words and match nothing; texts shorter than a shingle count as one
shingle, and items shorter than a shingle are sought in runs of as many words; repeated items count once each; an item may match a document at several places, of which the most similar
counts (the first of these, on ties); empty tables give empty results; other columns are kept by `clean`.
"""

from __future__ import annotations

import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import long_id, slices

SHINGLE, SIMILARITY, RADIUS, ITEMS, ITEM_CHARS = 5, 0.8, 19, 5_000, 1 << 24
BASE, MIX = 0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9
BACK = pow(BASE, -1, 1 << 64)
PART, SPAN = 1 << 20, 1 << 15
SIEVE = 20


def shingle_hashes(words: list[str], most: int = SHINGLE) -> np.ndarray:
    """A 64-bit hash of each run of `most` words (of the whole, if there are fewer)."""
    if not words:
        return np.zeros(0, np.uint64)
    raw = np.frombuffer(" ".join(words).encode("utf-8", "surrogatepass"), np.uint8)
    gaps = np.flatnonzero(raw == 32)
    starts, ends = np.concatenate(([0], gaps + 1)), np.append(gaps, len(raw))
    k = min(most, len(words))
    starts, ends = starts[: len(words) - k + 1], ends[k - 1 :]
    out = np.empty(len(starts), np.uint64)
    # Sums start anew for each part, so that memory has a bound whatever the text's length.
    for a in range(0, len(starts), PART):
        s, e = starts[a : a + PART], ends[a : a + PART]
        lo = s[0]
        piece = raw[lo : e[-1]]
        up = np.full(len(piece) + 1, BASE, np.uint64)
        up[0] = 1
        down = np.full(len(piece) + 1, BACK, np.uint64)
        down[0] = 1
        up, down = np.cumprod(up, dtype=np.uint64), np.cumprod(down, dtype=np.uint64)
        total = np.zeros(len(piece) + 1, np.uint64)
        np.cumsum((piece.astype(np.uint64) + np.uint64(1)) * up[:-1], out=total[1:])
        h = (total[e - lo] - total[s - lo]) * down[s - lo]
        h = (h ^ (h >> np.uint64(31))) * np.uint64(MIX)
        out[a : a + PART] = h ^ (h >> np.uint64(29))
    return out


def words_of(text: str) -> list[str]:
    return re.findall(r"\w+", text.lower())


def _signs(h: np.ndarray) -> np.ndarray:
    """+1 and -1 for the 64 bits of each hash."""
    bits = np.unpackbits(np.ascontiguousarray(h).view(np.uint8), bitorder="little").reshape(-1, 64)
    return 2 * bits.astype(np.int32) - 1


def window_prints(h: np.ndarray, starts: np.ndarray, size: int) -> np.ndarray:
    """The SimHash of the windows of `size` shingles at these starts, from prefix sums."""
    lo = int(starts.min())
    total = np.zeros((int(starts.max()) - lo + size + 1, 64), np.int32)
    np.cumsum(_signs(h[lo : int(starts.max()) + size]), axis=0, out=total[1:])
    at = starts - lo
    return np.packbits(total[at + size] - total[at] > 0, axis=1, bitorder="little").view(np.uint64).ravel()


def _near(bits: int) -> np.ndarray:
    """All 16-bit patterns with at most so many bits."""
    every = np.arange(1 << 16, dtype=np.uint16)
    return every[np.bitwise_count(every) <= bits]


def _common(h: np.ndarray, starts: list[int], wide: int, counts: Counter):
    """(start, shingles in common with `counts`) of windows in order; a window that overlaps the one before moves on from it,
    so the work grows with the text that they cover, not with the windows' sizes added up."""
    inside: Counter = Counter()
    common, before = 0, None
    for s in starts:
        if before is None or s - before >= wide:
            inside = Counter(h[s : s + wide].tolist())
            common = sum(min(c, inside[x]) for x, c in counts.items())
        else:
            for x in h[before:s].tolist():
                common -= inside[x] <= counts.get(x, 0)
                inside[x] -= 1
            for x in h[before + wide : s + wide].tolist():
                inside[x] += 1
                common += inside[x] <= counts.get(x, 0)
        before = s
        yield s, common


class Items:
    """What a task needs of the benchmark: shingles, fingerprints, and their blocks by value."""

    def __init__(self, items: list[tuple[int, str]]):
        kept = [(i, shingle_hashes(words_of(t)), len(words_of(t))) for i, t in items if t and words_of(t)]
        self.ids = [i for i, _, _ in kept]
        self.words = np.array([n for _, _, n in kept], np.int64)
        self.sizes = np.array([len(h) for _, h, _ in kept], np.int64)
        # Items shorter than a shingle, by their words and their only hash: documents are read in runs of as many words for them.
        self.short: dict[int, dict[int, list[int]]] = {}
        for at, (_, h, n) in enumerate(kept):
            if n < SHINGLE:
                self.short.setdefault(n, {}).setdefault(int(h[0]), []).append(at)
        self.counts = [Counter(h.tolist()) for _, h, _ in kept]
        all_h = np.concatenate([h for _, h, _ in kept]) if kept else np.zeros(0, np.uint64)
        self.known, of = np.unique(all_h, return_inverse=True)
        # For each known shingle, the sizes of the items that have it.
        both = np.unique(np.stack([of, np.repeat(self.sizes, self.sizes)], 1), axis=0) if kept else np.zeros((0, 2), np.int64)
        self.size_of, self.edge = both[:, 1], np.searchsorted(both[:, 0], np.arange(len(self.known) + 1))
        self.sieve = np.zeros(1 << SIEVE, bool)
        self.sieve[(self.known & np.uint64((1 << SIEVE) - 1)).astype(np.int64)] = True
        self.prints = np.array([window_prints(h, np.array([0]), len(h))[0] for _, h, _ in kept], np.uint64)
        near = _near(2)
        self.blocks = []
        for b in range(4):
            value = ((self.prints >> np.uint64(16 * b)) & np.uint64(0xFFFF)).astype(np.uint16)
            under = (value[:, None] ^ near[None, :]).ravel()
            order = np.argsort(under, kind="stable")
            edge = np.searchsorted(under[order], np.arange((1 << 16) + 1))
            self.blocks.append((edge, np.repeat(np.arange(len(value)), len(near))[order].astype(np.int32)))

    def candidates(self, prints: np.ndarray) -> list[tuple[int, int]]:
        """(window, item) for all fingerprints within RADIUS."""
        near, found = _near(2), []
        for b, (edge, items) in enumerate(self.blocks):
            asked = (((prints >> np.uint64(16 * b)) & np.uint64(0xFFFF)).astype(np.uint16)[:, None] ^ near[None, :]).astype(np.int64)
            first, many = edge[asked].ravel(), (edge[asked + 1] - edge[asked]).ravel()
            listed = items[np.arange(many.sum()) + np.repeat(first - (np.cumsum(many) - many), many)]
            found.append(np.repeat(np.repeat(np.arange(len(prints)), len(near)), many) * len(self.prints) + listed)
        w, i = np.divmod(np.unique(np.concatenate(found)), len(self.prints))
        close = np.bitwise_count(prints[w] ^ self.prints[i]) <= RADIUS
        return list(zip(w[close].tolist(), i[close].tolist()))

    def matches(self, text: str, similarity: float) -> list[tuple[int, float, int, int]]:
        """(item id, similarity, first word, words) of each item that a window of the text repeats."""
        words = words_of(text)
        best = self._short_matches(words)
        best.update({i: m for i, m in self._matches(words, similarity).items() if i not in best})
        return [(self.ids[i], v, s, n) for i, (v, s, n) in best.items()]

    def _short_matches(self, words: list[str]) -> dict[int, tuple[float, int, int]]:
        best = {}
        for n, known in self.short.items():
            if len(words) >= n:
                h = shingle_hashes(words, n)
                found, first = np.unique(h, return_index=True)
                for x, s in zip(found.tolist(), first.tolist()):
                    best.update({i: (1.0, s, n) for i in known.get(x, ())})
        return best

    def _matches(self, words: list[str], similarity: float) -> dict[int, tuple[float, int, int]]:
        h = shingle_hashes(words)
        maybe = np.flatnonzero(self.sieve[(h & np.uint64((1 << SIEVE) - 1)).astype(np.int64)]) if len(h) else h
        if not len(maybe) or not len(self.known):
            return {}
        at = np.minimum(np.searchsorted(self.known, h[maybe]), len(self.known) - 1)
        true = self.known[at] == h[maybe]
        at, hits = at[true], maybe[true]
        if not len(hits):
            return {}
        many = self.edge[at + 1] - self.edge[at]
        place = np.repeat(hits, many)
        size_at = self.size_of[np.arange(many.sum()) + np.repeat(self.edge[at] - (np.cumsum(many) - many), many)]
        best: dict[int, tuple[float, int, int]] = {}
        for size in np.unique(size_at).tolist():
            wide, hits = min(size, len(h)), place[size_at == size]
            if len(hits) < similarity / (1 + similarity) * (wide + size) - 1e-9:
                continue
            total = np.zeros(len(h) + 1, np.int32)
            total[hits + 1] = 1
            np.cumsum(total, out=total)
            begins = np.flatnonzero(total[wide:] - total[: len(total) - wide] >= similarity / (1 + similarity) * (wide + size) - 1e-9)
            asked: dict[int, list[int]] = {}
            # A few thousand windows at a time, and no further apart than SPAN, so that memory has a bound.
            edge = [0, *(np.flatnonzero(np.diff(begins // SPAN)) + 1).tolist(), len(begins)]
            for lo, hi in zip(edge[:-1], edge[1:]):
                for a in range(lo, hi, 4096):
                    part = begins[a : min(a + 4096, hi)]
                    for w, i in self.candidates(window_prints(h, part, wide)):
                        if self.sizes[i] == size:
                            asked.setdefault(i, []).append(int(part[w]))
            for i, starts in asked.items():
                for s, common in _common(h, sorted(starts), wide, self.counts[i]):
                    value = common / (wide + size - common)
                    if value >= similarity and (i not in best or value > best[i][0]):
                        best[i] = (value, s, min(int(self.words[i]), len(words)))
        return best


def item_batches(benchmark: DataFrame, id_column: str = "item_id", text: str = "text"):
    """The items, ITEMS or ITEM_CHARS at a time; a benchmark is read once per pass and never held whole."""
    held, chars = [], 0
    for row in benchmark.select(long_id(benchmark, id_column).alias("id"), F.col(text).cast("string").alias("text")).toLocalIterator():
        held.append((row["id"], row["text"]))
        chars += len(row["text"] or "")
        if len(held) == ITEMS or chars >= ITEM_CHARS:
            yield held
            held, chars = [], 0
    if held:
        yield held


def matches(docs: DataFrame, benchmark: DataFrame, similarity: float = SIMILARITY, text: str = "text", id_column: str = "doc_id") -> DataFrame:
    """(id, item_id, similarity, first_word, n_words) of every item that a document repeats."""
    spark = docs.sparkSession
    slim = docs.select(long_id(docs, id_column).alias("id"), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("text"))
    layout = "id long, item_id long, similarity double, first_word long, n_words long"
    columns = [("id", pa.int64()), ("item_id", pa.int64()), ("similarity", pa.float64()), ("first_word", pa.int64()), ("n_words", pa.int64())]
    out = spark.createDataFrame([], layout)
    for held in item_batches(benchmark):
        shared = spark.sparkContext.broadcast(held)

        def run(batches, shared=shared):
            items = Items(shared.value)
            for b in slices(batches):
                rows = [(i, *m) for i, t in zip(b.column("id").to_pylist(), b.column("text").to_pylist()) for m in items.matches(t, similarity)]
                yield pa.RecordBatch.from_pydict({n: pa.array([r[k] for r in rows], kind) for k, (n, kind) in enumerate(columns)})

        out = out.unionByName(slim.mapInArrow(run, layout))
    return out


def clean(docs: DataFrame, benchmark: DataFrame, similarity: float = SIMILARITY, text: str = "text") -> DataFrame:
    """The documents that repeat no item, unchanged."""
    for held in item_batches(benchmark):
        shared = docs.sparkSession.sparkContext.broadcast(held)

        def run(batches, shared=shared):
            items = Items(shared.value)
            for b in slices(batches):
                yield b.filter(pa.array([not items.matches(t or "", similarity) for t in b.column(text).to_pylist()], pa.bool_()))

        docs = docs.mapInArrow(run, docs.schema)
    return docs


def query(spark, sf_dir):
    from .common import table

    found = matches(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark").select("item_id", "text"))
    return found.withColumnRenamed("id", "doc_id")
