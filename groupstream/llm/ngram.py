"""An interpolated modified Kneser-Ney model, counted in Spark and read by workers from memory-mapped hash arrays.

The model is of order two. Pairs of tokens are counted by context in buckets of a hash of the first word, those of frequent
first words in several, by the second; each bucket sums
its contexts (total, and how many words follow once, twice or more often) and passes each second word's count and number
of distinct contexts on to that word's bucket. Buckets write two kinds of files into the shared folder: pairs as one
sorted array of 64-bit entries (48 bits of the pair's hash, 16 of its count, larger counts apart), and words as sorted
hashes with their counts. Workers map the files and look all pairs of a piece of text up by bisection, so a model of any
size costs a worker no memory of its own.

Probabilities: pairs are discounted by D1, D2 or D3 from the counts of counts, what is discounted goes to the word's share
of all distinct pairs, discounted alike, and what that leaves goes to the uniform distribution over the known words and
one unknown word.

The shared folder must be a path that driver and executors can open (a mounted file system), since files are mapped.

Cases: null and empty texts consist of the end token; texts of any length are read whole, in pieces cut at white space;
an empty training set gives every token probability one; null ids are scored and never held out; an empty table gives an
empty result; other columns are ignored.
"""

from __future__ import annotations

import math
import os
import uuid

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .blocks import dealt, joined
from .common import long_id, new_folder, partitions, share_of

PIECE, BUCKET_BYTES = 2 << 20, 16 << 20
BASE, MIX, DEAL = 0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB
BACK = pow(BASE, -1, 1 << 64)
END, BEGIN = np.uint64(1), np.uint64(2)
TOP = 0xFFFF
SPACE = np.zeros(256, bool)
SPACE[[0x20, 9, 10, 11, 12, 13]] = True


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(MIX)
    return x ^ (x >> np.uint64(29))


def _bucket(word: np.ndarray, n: int) -> np.ndarray:
    return (((word * np.uint64(DEAL)) >> np.uint64(33)) % np.uint64(n)).astype(np.int64)


#: Documents that the words' shares are estimated from, which decide how many buckets a frequent first word is dealt over.
SHARES_FROM, SHARES_CHARS = 2_000, 4 << 20


class Deal:
    """Which bucket a pair goes to: that of its first word; pairs of a frequent first word go on by the second over `many`
    buckets from there. The estimate behind it decides how work is dealt, never a count."""

    def __init__(self, buckets: int, word: np.ndarray, many: np.ndarray):
        order = np.argsort(word)
        self.buckets, self.word, self.many = buckets, word[order], many[order]

    @staticmethod
    def of_sample(texts: list[bytes], buckets: int) -> "Deal":
        found = [_short(previous) for _, _, previous in token_pieces(texts)]
        word, count = np.unique(np.concatenate(found), return_counts=True) if found else (np.zeros(0, np.uint64), np.zeros(0, np.int64))
        many = np.minimum(buckets, np.ceil(2.0 * count / max(1, count.sum()) * buckets)).astype(np.int64)
        return Deal(buckets, word[many > 2], many[many > 2])

    def spread(self, first: np.ndarray) -> np.ndarray:
        """Over how many buckets each first word is dealt."""
        if not len(self.word):
            return np.ones(len(first), np.int64)
        at = np.minimum(np.searchsorted(self.word, first), len(self.word) - 1)
        return np.where(self.word[at] == first, self.many[at], 1)

    def bucket(self, first: np.ndarray, second: np.ndarray) -> np.ndarray:
        shift = _mix(second) % self.spread(first).astype(np.uint64)
        return (_bucket(first, self.buckets) + shift.astype(np.int64)) % self.buckets


def _pair(first: np.ndarray, second: np.ndarray) -> np.ndarray:
    """The upper 48 bits of a hash of both words; the lower 16 are free."""
    return _mix(first * np.uint64(BASE) + second) & ~np.uint64(TOP)


def word_hashes(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Start and hash of each word of a buffer."""
    n = len(raw)
    gap = np.concatenate(([True], SPACE[raw], [True]))
    starts = np.flatnonzero(gap[:-1] & ~gap[1:])
    ends = np.flatnonzero(~gap[:-1] & gap[1:])
    up, down = np.full(n + 1, BASE, np.uint64), np.full(n + 1, BACK, np.uint64)
    up[0] = down[0] = 1
    up, down = np.cumprod(up, dtype=np.uint64), np.cumprod(down, dtype=np.uint64)
    total = np.zeros(n + 1, np.uint64)
    np.cumsum((raw.astype(np.uint64) + np.uint64(1)) * up[:-1], out=total[1:])
    h = _mix(_mix((total[ends] - total[starts]) * down[starts]) + (ends - starts).astype(np.uint64))
    return starts, np.where(h <= BEGIN, h + np.uint64(8), h)


def token_pieces(texts: list[bytes]):
    """(document number, token, token before it) of all tokens, in pieces of about PIECE bytes of text."""
    held, size, before = [], 0, None
    for n, text in enumerate(texts):
        at = 0
        while True:
            stop = at + PIECE
            while stop < len(text) and not SPACE[text[stop]]:
                stop += 1
            last = stop >= len(text)
            held.append((n, text[at:stop], at == 0, last))
            size += min(stop, len(text)) - at
            if size >= PIECE:
                made = _tokens(held, before)
                before = made[1][-1] if len(made[1]) else before
                yield made
                held, size = [], 0
            if last:
                break
            at = stop
    if held:
        yield _tokens(held, before)


def _tokens(held, before):
    raw = np.frombuffer(b"\n".join(p for _, p, _, _ in held).lower(), np.uint8)
    starts, words = word_hashes(raw)
    lengths = np.array([len(p) + 1 for _, p, _, _ in held])
    part = np.searchsorted(np.cumsum(lengths), starts, side="right")
    count = np.bincount(part, minlength=len(held))
    closes = np.array([last for _, _, _, last in held])
    opens = np.array([first for _, _, first, _ in held])
    sizes = count + closes
    first = np.cumsum(sizes) - sizes
    token = np.empty(sizes.sum(), np.uint64)
    token[(first + sizes - 1)[closes]] = END
    token[np.arange(len(words)) + (first - (np.cumsum(count) - count))[part]] = words
    previous = np.empty_like(token)
    previous[1:] = token[:-1]
    if len(token) and before is not None:
        previous[0] = before
    begins = first[opens & (sizes > 0)]
    previous[begins[begins < len(token)]] = BEGIN
    return np.repeat(np.array([n for n, _, _, _ in held]), sizes), token, previous


def _six(x: np.ndarray) -> bytes:
    """Numbers of 48 bits, packed."""
    return np.ascontiguousarray(x).view(np.uint8).reshape(-1, 8)[:, :6].tobytes()


def _from_six(packed: bytes) -> np.ndarray:
    out = np.zeros((len(packed) // 6, 8), np.uint8)
    out[:, :6] = np.frombuffer(packed, np.uint8).reshape(-1, 6)
    return out.view(np.uint64).ravel()


def _short(word: np.ndarray) -> np.ndarray:
    return word & np.uint64((1 << 48) - 1)


def _new(*columns: np.ndarray) -> np.ndarray:
    out = np.zeros(len(columns[0]), bool)
    out[:1] = True
    for c in columns:
        out[1:] |= c[1:] != c[:-1]
    return out


def _write(folder: str, name: str, data: bytes) -> None:
    """Whole or not at all: a task that runs twice replaces a file by the same one."""
    part = f"{folder}/.{name}-{uuid.uuid4().hex}"
    with open(part, "wb") as f:
        f.write(data)
    os.replace(part, f"{folder}/{name}")


def _pairs_sent(texts: list[bytes], deal: Deal):
    """The distinct pairs of each piece of text, by bucket."""
    for _, token, previous in token_pieces(texts):
        first, second = _short(previous), _short(token)
        order = np.lexsort((second, first))
        first, second = first[order], second[order]
        at = np.flatnonzero(_new(first, second))
        count = np.diff(np.append(at, len(first)))
        first, second = first[at], second[at]
        order, parts = dealt(deal.bucket(first, second), deal.buckets)
        first, second, count = first[order], second[order], count[order]
        for b, s in parts:
            head = np.flatnonzero(_new(first[s]))
            many = np.diff(np.append(head, s.stop - s.start)).astype(np.uint32)
            yield b, _six(first[s][head]), many.tobytes(), _six(second[s]), count[s].astype(np.uint32).tobytes()


def train(docs: DataFrame, text: str = "text") -> "Model":
    """A model of all texts of docs."""
    spark = docs.sparkSession
    folder = new_folder(spark, "ngram")
    where = folder.removeprefix("file:")
    where = "/" + where.lstrip("/")
    if "://" in folder.removeprefix("file://") or (":" in folder.split("/")[0] and not folder.startswith("file:")):
        raise ValueError(f"{folder} can't be mapped into memory: name a mounted folder as spark.checkpoint.dir")
    os.makedirs(where, exist_ok=True)
    slim = docs.select(F.coalesce(F.col(text).cast("binary"), F.lit(b"")).alias("text"))
    total, rows = slim.agg(F.sum(F.octet_length("text")), F.count(F.lit(1))).first()
    total = total or 0
    buckets = max(partitions(spark), math.ceil(total / BUCKET_BYTES))
    few = slim.where(share_of(rows, 1.5 * SHARES_FROM, F.xxhash64(F.octet_length("text"), F.crc32("text"))))
    sample = few.select(F.substring("text", 1, SHARES_CHARS // SHARES_FROM).alias("text")).limit(SHARES_FROM).collect()
    deal = Deal.of_sample([bytes(r["text"]) for r in sample], buckets)

    def send(batches):
        for b in batches:
            for row in _pairs_sent(b["text"].tolist(), deal):
                yield pd.DataFrame([row], columns=["bucket", "contexts", "many", "words", "counts"])

    def settle(rows):
        bucket = int(rows["bucket"].iloc[0])
        first = np.repeat(_from_six(b"".join(rows["contexts"])), joined(rows, "many", np.uint32))
        second, count = _from_six(b"".join(rows["words"])), joined(rows, "counts", np.uint32).astype(np.int64)
        order = np.lexsort((second, first))
        first, second, count = first[order], second[order], count[order]
        at = np.flatnonzero(_new(first, second))
        count, first, second = np.add.reduceat(count, at), first[at], second[at]
        entry = _pair(first, second) | np.minimum(count, TOP).astype(np.uint64)
        large = np.flatnonzero(count >= TOP)
        _write(where, f"pairs-{bucket}", np.sort(entry).tobytes())
        _write(where, f"large-{bucket}", np.stack([entry[large], count[large].astype(np.uint64)], 1).tobytes())
        head = np.flatnonzero(_new(first))
        sums = [np.add.reduceat(x.astype(np.int64), head) for x in (count, count == 1, count == 2, count > 2)]
        _write(where, f"contexts-{bucket}", np.stack([first[head], *[x.astype(np.uint64) for x in sums]], 1).tobytes())
        order = np.argsort(second, kind="stable")
        second, count = second[order], count[order]
        head = np.flatnonzero(_new(second))
        uses, distinct = np.add.reduceat(count, head), np.diff(np.append(head, len(second)))
        word = second[head]
        of = _bucket(word, buckets)
        order, parts = dealt(of, buckets)
        word, uses, distinct = word[order], uses[order], distinct[order]
        tally = np.bincount(np.minimum(count, 5), minlength=6)[1:5].astype(np.int64)
        return pd.DataFrame([(b, _six(word[s]), uses[s].tobytes(), distinct[s].astype(np.uint32).tobytes(), tally.tobytes() if n == 0 else b"") for n, (b, s) in enumerate(parts)], columns=["bucket", "words", "uses", "distinct", "tally"])

    def gather(rows):
        bucket = int(rows["bucket"].iloc[0])
        word, uses, distinct = _from_six(b"".join(rows["words"])), joined(rows, "uses", np.int64), joined(rows, "distinct", np.uint32).astype(np.int64)
        order = np.argsort(word, kind="stable")
        word, uses, distinct = word[order], uses[order], distinct[order]
        at = np.flatnonzero(_new(word))
        word, uses, distinct = word[at], np.add.reduceat(uses, at), np.add.reduceat(distinct, at)
        _write(where, f"words-{bucket}", np.stack([word, uses.astype(np.uint64), distinct.astype(np.uint64)], 1).tobytes())
        pairs = joined(rows, "tally", np.int64).reshape(-1, 4).sum(0).tolist()
        words = np.bincount(np.minimum(distinct, 5), minlength=6)[1:5].tolist()
        return pd.DataFrame([(int(uses.sum()), len(word), int(distinct.sum()), *pairs, *words)], columns=["tokens", "words", "pairs", *[f"p{i}" for i in range(1, 5)], *[f"w{i}" for i in range(1, 5)]])

    sent = slim.mapInPandas(send, "bucket int, contexts binary, many binary, words binary, counts binary")
    passed = sent.groupBy("bucket").applyInPandas(settle, "bucket int, words binary, uses binary, distinct binary, tally binary")
    sums = passed.groupBy("bucket").applyInPandas(gather, "tokens long, words long, pairs long, " + ", ".join(f"{c}{i} long" for c in "pw" for i in range(1, 5)))
    row = sums.agg(*[F.sum(c).alias(c) for c in sums.columns]).first()
    return Model(where, deal, {c: row[c] or 0 for c in sums.columns})


def discounts(counts: list[int]) -> np.ndarray:
    """No discount for 0, then those of counts 1, 2 and more, from how many things have the counts 1 to 4."""
    n1, n2, n3, n4 = (float(c) for c in counts)
    y = n1 / (n1 + 2 * n2) if n1 + 2 * n2 > 0 else 0.5
    follow = ((1, n1, n2), (2, n2, n3), (3, n3, n4))
    return np.array([0.0, *[float(np.clip(k - (k + 1) * y * b / a if a > 0 else 0.5 * k, 0.0, k)) for k, a, b in follow]])


class Model:
    """Where the files are, and the sums over all of them."""

    def __init__(self, folder: str, deal: Deal, sums: dict[str, int]):
        self.folder, self.deal, self.buckets, self.sums = folder, deal, deal.buckets, sums
        self.pair_discounts = discounts([sums[f"p{i}"] for i in range(1, 5)])
        self.word_discounts = discounts([sums[f"w{i}"] for i in range(1, 5)])
        single, double, more = sums["w1"], sums["w2"], sums["words"] - sums["w1"] - sums["w2"]
        held = float(self.word_discounts[1:] @ [single, double, more])
        self.uniform = (held / sums["pairs"] if sums["pairs"] else 1.0) / (sums["words"] + 1)
        self.files: dict[str, np.ndarray] = {}
        self.frequent: dict[int, np.ndarray] = {}

    def _map(self, kind: str, bucket: int, columns: int) -> np.ndarray:
        name = f"{self.folder}/{kind}-{bucket}"
        if name not in self.files:
            there = os.path.exists(name) and os.path.getsize(name) > 0
            self.files[name] = np.memmap(name, np.uint64, "r").reshape(-1, columns) if there else np.zeros((0, columns), np.uint64)
        return self.files[name]

    def _lookup(self, kind: str, words: np.ndarray, columns: int) -> np.ndarray:
        """The numbers beside each of these distinct words, zero where there is none."""
        out = np.zeros((len(words), columns - 1), np.int64)
        order, parts = dealt(_bucket(words, self.buckets), self.buckets)
        for b, s in parts:
            table, own = self._map(kind, b, columns), order[s]
            if len(table):
                at = np.minimum(np.searchsorted(table[:, 0], words[own]), len(table) - 1)
                hit = table[at, 0] == words[own]
                out[own[hit]] = table[at[hit], 1:].astype(np.int64)
        return out

    def _contexts(self, words: np.ndarray) -> np.ndarray:
        """The sums of these distinct first words, those of frequent ones added up over their buckets."""
        out, spread = self._lookup("contexts", words, 5), self.deal.spread(words)
        for i in np.flatnonzero(spread > 1).tolist():
            if (word := int(words[i])) not in self.frequent:
                total = np.zeros(4, np.int64)
                for b in range(int(spread[i])):
                    table = self._map("contexts", (int(_bucket(words[i : i + 1], self.buckets)[0]) + b) % self.buckets, 5)
                    at = int(np.searchsorted(table[:, 0], words[i]))
                    if at < len(table) and table[at, 0] == words[i]:
                        total += table[at, 1:].astype(np.int64)
                self.frequent[word] = total
            out[i] = self.frequent[word]
        return out

    def pair_counts(self, first: np.ndarray, second: np.ndarray) -> np.ndarray:
        entry, out = _pair(first, second), np.zeros(len(first), np.int64)
        order, parts = dealt(self.deal.bucket(first, second), self.buckets)
        for b, s in parts:
            table = self._map("pairs", b, 1)[:, 0]
            if not len(table):
                continue
            own = order[s]
            own = own[np.argsort(entry[own])]  # neighbours in the file are asked for together
            at = np.minimum(np.searchsorted(table, entry[own]), len(table) - 1)
            hit = (table[at] & ~np.uint64(TOP)) == entry[own]
            out[own[hit]] = (table[at[hit]] & np.uint64(TOP)).astype(np.int64)
            top = own[hit][out[own[hit]] == TOP]
            if len(top):
                large = {int(e): int(c) for e, c in self._map("large", b, 2)}
                out[top] = [large[int(e) | TOP] for e in entry[top]]
        return out

    def score(self, token: np.ndarray, previous: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """log10 probability of each token after the one before it, and the token's count in training."""
        token, previous = _short(token), _short(previous)
        words, of = np.unique(token, return_inverse=True)
        uses, distinct = self._lookup("words", words, 3).T
        base = self.uniform + np.maximum(distinct - self.word_discounts[np.minimum(distinct, 3)], 0) / max(1, self.sums["pairs"])
        contexts, where = np.unique(previous, return_inverse=True)
        total, n1, n2, n3 = self._contexts(contexts).T
        left = np.where(total > 0, (np.stack([n1, n2, n3], 1) @ self.pair_discounts[1:]) / np.maximum(total, 1), 1.0)
        order = np.lexsort((of, where))
        new = _new(where[order], of[order])
        number = np.empty(len(token), np.int64)
        number[order] = np.cumsum(new) - 1
        one = order[new]
        count = self.pair_counts(previous[one], token[one])
        kept = np.maximum(count - self.pair_discounts[np.minimum(count, 3)], 0) / np.maximum(total[where[one]], 1)
        p = kept + left[where[one]] * base[of[one]]
        return np.log10(p)[number], uses[of]

    def __getstate__(self):
        return self.__dict__ | {"files": {}, "frequent": {}}


def scores(docs: DataFrame, model: Model, text: str = "text", id_column: str = "doc_id") -> DataFrame:
    """(id, n_tokens, n_known, base_score, score) of every text."""

    def run(batches):
        reader = Model(model.folder, model.deal, model.sums)
        tokens, words = reader.sums["tokens"], reader.sums["words"]
        for b in batches:
            n = len(b)
            sums = np.zeros((4, n))
            for doc, token, previous in token_pieces(b["text"].tolist()):
                value, uses = reader.score(token, previous)
                base = np.log10((uses + 1) / (tokens + 1 * (words + 1)))
                for i, x in enumerate((np.ones(len(doc)), uses > 0, base, value)):
                    sums[i] += np.bincount(doc, x, minlength=n)
            yield pd.DataFrame({"id": b["id"].astype("Int64"), "n_tokens": sums[0].astype(np.int64), "n_known": sums[1].astype(np.int64), "base_score": sums[2], "score": sums[3]})

    slim = docs.select(long_id(docs, id_column).alias("id"), F.coalesce(F.col(text).cast("binary"), F.lit(b"")).alias("text"))
    return slim.mapInPandas(run, "id long, n_tokens long, n_known long, base_score double, score double")


def held_out(id_column: str) -> Column:
    return F.coalesce(F.pmod(F.crc32(F.col(id_column).cast("string")), F.lit(7)) == 2, F.lit(False))


def query(spark, sf_dir):
    from .common import table

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = train(docs.where(~held_out("doc_id")))
    return scores(docs, model).select(F.col("id").alias("doc_id"), held_out("id").alias("held_out"), "n_tokens", "n_known", F.lit(model.sums["tokens"]).cast("long").alias("train_tokens"), "base_score", "score")
