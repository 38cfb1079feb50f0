"""Exact removal of repeated byte strings by a depth-limited radix sort of suffixes.

A suffix matters only through its first `depth` bytes. Suffixes are first dealt by the least hash (minimizer) among the
short strings inside those bytes: equal strings have equal minimizers, so nothing is lost, and minimizers that occur in
one document alone are dropped before any text moves. Neighbouring suffixes with one minimizer travel as one piece of
text. Each bucket then sorts its suffixes by most-significant-digit passes of eight bytes; after each pass suffixes alone
in their group are done, and the groups left after the last pass are exactly the repeated strings. Every string's least
document id goes back to the blocks, and each document drops the bytes that a string from an earlier document covers.

Pieces of text travel under 96 bits of hashes (64 of the content, 32 of the minimizer), and pieces that agree in all of them
count as equal before the sort; strings of different pieces are compared byte by byte.

Cases: null texts count as empty, and texts shorter than `depth` stay whole; long texts are cut into overlapping parts,
so memory has a bound; rows with one id take nothing from each other; null ids sort last and come back null; an empty
table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import zlib

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blocks import CUT_LAYOUT, cut_out, dealt, finish, into_blocks, joined, round_trip

DEPTH, PART, LONGEST = 50, 1 << 20, 256
#: Multipliers of the rolling hash, of its inverse, and of the mixing steps.
BASE = 0x9E3779B97F4A7C15
BACK = pow(BASE, -1, 1 << 64)
MIX, DEAL = 0xBF58476D1CE4E5B9, 0x94D049BB133111EB
LOW = (1 << 40) - 1


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n + 1, base, np.uint64)
    out[0] = 1
    return np.cumprod(out, dtype=np.uint64)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(MIX)
    return x ^ (x >> np.uint64(29))


def minimizer_runs(buffer: np.ndarray, ends: np.ndarray, depth: int, up: np.ndarray, down: np.ndarray):
    """For a buffer of texts that end at `ends`: start, count, key and content hash of each run of suffixes.

    A run is neighbouring starts of whole depth-byte strings with one minimizer; its content is the text they cover.
    """
    n, none = len(buffer), np.zeros(0, np.int64)
    if n < depth:
        return none, none, none.astype(np.uint64), none.astype(np.uint64)
    k = 2 * depth // 5
    w = depth - k + 1
    total = np.zeros(n + 1, np.uint64)
    np.cumsum((buffer.astype(np.uint64) + np.uint64(1)) * up[:n], out=total[1:])
    least = _mix((total[k:] - total[:-k]) * down[: n - k + 1])
    span = 1
    while 2 * span <= w:
        least = np.minimum(least[:-span], least[span:])
        span *= 2
    if span < w:
        least = np.minimum(least[: n - depth + 1], least[w - span :])
    whole = np.ones(n, bool)
    starts_of = np.concatenate(([0], ends[:-1]))
    tail = np.maximum(starts_of, ends - depth + 1)
    edges = np.zeros(n + 1, np.int8)
    np.add.at(edges, tail, 1)
    np.add.at(edges, ends, -1)
    whole = (np.cumsum(edges[:-1], dtype=np.int8) == 0)[: n - depth + 1]
    new = whole.copy()
    new[1:] &= ~whole[:-1] | (least[1:] != least[:-1])
    start = np.flatnonzero(new)
    stop = np.flatnonzero(whole & ~np.concatenate((whole[1:] & ~new[1:], [False]))) + 1
    count = stop - start
    if (count > LONGEST).any():
        pieces = -(-count // LONGEST)
        step = np.arange(pieces.sum()) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        start, stop = np.repeat(start, pieces) + step * LONGEST, np.repeat(stop, pieces)
        count = np.minimum(stop - start, LONGEST)
    content = _mix((total[start + count + depth - 1] - total[start]) * down[start] + count.astype(np.uint64))
    return start, count, least[start], content


def parts_of(texts: list[bytes], depth: int):
    """Buffers of about PART bytes: (buffer, ends, document number and offset of each text in it)."""
    held, size = [], 0
    for n, text in enumerate(texts):
        for at in range(0, max(1, len(text) - depth + 1), PART):
            piece = text[at : at + PART + depth - 1]
            if held and size + len(piece) > PART:
                yield _buffer(held)
                held, size = [], 0
            if len(piece) >= depth:
                held.append((n, at, piece))
                size += len(piece)
    if held:
        yield _buffer(held)


def _buffer(held):
    ends = np.cumsum([len(p) for _, _, p in held])
    return np.frombuffer(b"".join(p for _, _, p in held), np.uint8), ends, np.array([n for n, _, _ in held]), np.array([at for _, at, _ in held])


def _bucket(key: np.ndarray, buckets: int) -> np.ndarray:
    return (((key * np.uint64(DEAL)) >> np.uint64(33)) % np.uint64(buckets)).astype(np.int64)


def _short(key: np.ndarray) -> bytes:
    """The low 40 bits of each key."""
    return np.ascontiguousarray(key).view(np.uint8).reshape(-1, 8)[:, :5].tobytes()


def _long(packed: bytes) -> np.ndarray:
    out = np.zeros((len(packed) // 5, 8), np.uint8)
    out[:, :5] = np.frombuffer(packed, np.uint8).reshape(-1, 5)
    return out.view(np.uint64).ravel()


def _tag(key: np.ndarray) -> np.ndarray:
    """32 bits of each key, which stand beside the 64 bits of a content's hash."""
    return ((key * np.uint64(DEAL)) >> np.uint64(32)).astype(np.uint32)


def _groups(*sorted_columns: np.ndarray) -> np.ndarray:
    """True where a new group starts in sorted rows."""
    n = len(sorted_columns[0])
    new = np.zeros(n, bool)
    new[:1] = True
    for c in sorted_columns:
        new[1:] |= c[1:] != c[:-1]
    return new


def equal_strings(text: np.ndarray, start: np.ndarray, group: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """Suffixes that share their first depth bytes with another of their group: their numbers, by equal string, and the
    string's number. One pass per digit of eight bytes; what is alone after a pass leaves the sort."""
    digit = np.ndarray((max(0, len(text) - 7),), ">u8", text, strides=(1,))
    left = np.arange(len(start))
    for at in [*range(0, depth - 7, 8), *([depth - 8] if depth % 8 else [])]:
        value = digit[start[left] + at].astype(np.uint64)
        order = np.lexsort((value, group))
        left, group, value = left[order], group[order], value[order]
        number = np.cumsum(_groups(group, value)) - 1
        shared = np.bincount(number, minlength=1)[number] > 1 if len(number) else np.zeros(0, bool)
        left, group = left[shared], number[shared]
    return left, group


def deduplicate(docs: DataFrame, depth: int = DEPTH, text: str = "text", id_column: str = "doc_id") -> DataFrame:
    """(id, n_bytes, kept, spans): the bytes of each text that no string from an earlier document covers."""
    if depth < 16:
        raise ValueError("depth must be 16 bytes or more")
    blocks, buckets = into_blocks(docs, id_column, text)

    def each(rows):
        up, down = _powers(BASE, PART + 2 * depth), _powers(BACK, PART + 2 * depth)
        for buffer, ends, doc, offset in parts_of(rows["text"].tolist(), depth):
            start, count, key, content = minimizer_runs(buffer, ends, depth, up, down)
            piece = np.searchsorted(ends, start, side="right")
            yield buffer, start, count, key, content, doc[piece], offset[piece] + start - np.concatenate(([0], ends[:-1]))[piece]

    def send_keys(rows):
        ids, keys, owner = rows["id"].to_numpy(np.int64), [], []
        for _, _, _, key, _, doc, _ in each(rows):
            keys.append(key)
            owner.append(ids[doc])
        if not keys:
            return pd.DataFrame(columns=["bucket", "block", "keys", "many"])
        key, owner = np.concatenate(keys), np.concatenate(owner)
        order = np.argsort(key, kind="stable")
        key, owner = key[order], owner[order]
        at = np.flatnonzero(_groups(key))
        many = np.minimum.reduceat(owner, at) != np.maximum.reduceat(owner, at) if len(at) else np.zeros(0, bool)
        key = key[at]
        order, parts = dealt(_bucket(key, buckets), buckets)
        key, many, block = key[order], many[order], int(rows["block"].iloc[0])
        return pd.DataFrame([(b, block, _short(key[s]), many[s].tobytes()) for b, s in parts], columns=["bucket", "block", "keys", "many"])

    def settle_keys(rows):
        key, many = _long(b"".join(rows["keys"])), joined(rows, "many", bool)
        block = np.repeat(rows["block"].to_numpy(np.int64), [len(x) for x in rows["many"]])
        order = np.argsort(key, kind="stable")
        new = _groups(key[order])
        number = np.cumsum(new) - 1
        shared = (np.bincount(number, minlength=1) > 1) | (np.bincount(number, many[order], minlength=1) > 0) if len(number) else new
        chosen = order[shared[number]] if len(number) else order
        chosen = chosen[np.argsort(block[chosen], kind="stable")]
        edge = [*np.flatnonzero(_groups(block[chosen])).tolist(), len(chosen)]
        bucket = int(rows["bucket"].iloc[0])
        return pd.DataFrame([(int(block[chosen[a]]), bucket, _short(key[chosen[a:b]])) for a, b in zip(edge[:-1], edge[1:])], columns=["block", "bucket", "keys"])

    def send_strings(rows, answers):
        if rows.empty or answers.empty:
            return pd.DataFrame(columns=["bucket", "block", "counts", "least", "most", "keys", "contents", "texts"])
        wanted = np.sort(np.concatenate([_long(k) | np.uint64(b << 40) for b, k in zip(answers["bucket"].tolist(), answers["keys"])]))
        ids, found = rows["id"].to_numpy(np.int64), []
        for buffer, start, count, key, content, doc, _ in each(rows):
            asked = (key & np.uint64(LOW)) | (_bucket(key, buckets).astype(np.uint64) << np.uint64(40))
            at = np.minimum(np.searchsorted(wanted, asked), len(wanted) - 1)
            hit = np.flatnonzero(wanted[at] == asked)
            owner = ids[doc[hit]]
            order = np.lexsort((owner, content[hit], key[hit]))
            hit, owner = hit[order], owner[order]
            first = np.flatnonzero(_groups(key[hit], content[hit]))
            if len(first):
                one, raw = hit[first], buffer.tobytes()
                texts = [raw[a:b] for a, b in zip(start[one].tolist(), (start[one] + count[one] + depth - 1).tolist())]
                found.append((key[one], content[one], count[one], np.minimum.reduceat(owner, first), np.maximum.reduceat(owner, first), texts))
        if not found:
            return pd.DataFrame(columns=["bucket", "block", "counts", "least", "most", "keys", "contents", "texts"])
        key, content, count, least, most = (np.concatenate([f[i] for f in found]) for i in range(5))
        texts = [t for f in found for t in f[5]]
        order = np.lexsort((content, key))
        at = np.flatnonzero(_groups(key[order], content[order]))
        least, most, one = np.minimum.reduceat(least[order], at), np.maximum.reduceat(most[order], at), order[at]
        key, content, count = key[one], content[one], count[one]
        order, parts = dealt(_bucket(key, buckets), buckets)
        block, out = int(rows["block"].iloc[0]), []
        for b, s in parts:
            o = order[s]
            out.append((b, block, count[o].astype(np.uint16).tobytes(), least[o].tobytes(), most[o].tobytes(), _tag(key[o]).tobytes(), content[o].tobytes(), zlib.compress(b"".join(texts[i] for i in one[o].tolist()), 1)))
        return pd.DataFrame(out, columns=["bucket", "block", "counts", "least", "most", "keys", "contents", "texts"])

    def settle_strings(rows):
        count, least, most = joined(rows, "counts", np.uint16).astype(np.int64), joined(rows, "least", np.int64), joined(rows, "most", np.int64)
        key, content = joined(rows, "keys", np.uint32), joined(rows, "contents", np.uint64)
        text = np.frombuffer(b"".join(map(zlib.decompress, rows["texts"])), np.uint8)
        block = np.repeat(rows["block"].to_numpy(np.int64), [len(x) // 4 for x in rows["keys"]])
        place = np.cumsum(count + depth - 1) - (count + depth - 1)
        order = np.lexsort((content, key))
        new = _groups(key[order], content[order])
        number = np.empty(len(key), np.int64)
        number[order] = np.cumsum(new) - 1
        at = np.flatnonzero(new)
        one, first = order[at], np.minimum.reduceat(least[order], at)
        n = count[one]
        begin = np.cumsum(n) - n
        inside = np.arange(n.sum()) - np.repeat(begin, n)
        owner = np.repeat(first, n)
        of_key = np.cumsum(_groups(key[one])) - 1
        several = np.bincount(of_key)[of_key] > 1
        checked = np.flatnonzero(np.repeat(several, n))
        left, string = equal_strings(text, (np.repeat(place[one], n) + inside)[checked], np.repeat(of_key, n)[checked], depth)
        if len(left):
            edge = np.flatnonzero(_groups(string))
            low = np.minimum.reduceat(owner[checked[left]], edge)
            owner[checked[left]] = np.repeat(low, np.diff(np.append(edge, len(left))))
        piece = np.repeat(np.arange(len(one)), n)
        cut = np.flatnonzero(_groups(piece, owner))
        seg_piece, seg_lo, seg_owner = piece[cut], inside[cut], owner[cut]
        seg_hi = seg_lo + np.diff(np.append(cut, len(piece)))
        per = np.bincount(seg_piece, minlength=len(one))
        seg_at = np.cumsum(per) - per
        sent = np.repeat(np.arange(len(key)), per[number])
        seg = np.repeat(seg_at[number] - (np.cumsum(per[number]) - per[number]), per[number]) + np.arange(len(sent))
        need = np.flatnonzero(seg_owner[seg] < most[sent])
        need = need[np.argsort(block[sent[need]], kind="stable")]
        sent, seg = sent[need], seg[need]
        edge = [*np.flatnonzero(_groups(block[sent])).tolist(), len(sent)]
        out = []
        for a, b in zip(edge[:-1], edge[1:]):
            s, g = sent[a:b], seg[a:b]
            out.append((int(block[s[0]]), key[s].tobytes(), content[s].tobytes(), seg_lo[g].astype(np.uint16).tobytes(), seg_hi[g].astype(np.uint16).tobytes(), seg_owner[g].tobytes()))
        return pd.DataFrame(out, columns=["block", "keys", "contents", "lows", "highs", "ids"])

    def remove(rows, answers):
        if rows.empty:
            return pd.DataFrame(columns=["id", "n_bytes", "kept", "spans"])
        ids, texts = rows["id"].to_numpy(np.int64), rows["text"].tolist()
        masks = [np.zeros(len(t), bool) for t in texts]
        key, content, low, high, owner = (joined(answers, c, t) for c, t in (("keys", np.uint32), ("contents", np.uint64), ("lows", np.uint16), ("highs", np.uint16), ("ids", np.int64)))
        order = np.argsort(content, kind="stable")
        key, content, low, high, owner = key[order], content[order], low[order].astype(np.int64), high[order].astype(np.int64), owner[order]
        for _, _, _, run_key, run_content, doc, at in each(rows) if len(key) else ():
            a, b = np.searchsorted(content, run_content, "left"), np.searchsorted(content, run_content, "right")
            run = np.repeat(np.arange(len(a)), b - a)
            seg = np.arange(len(run)) - np.repeat(np.cumsum(b - a) - (b - a), b - a) + a[run]
            hit = (key[seg] == _tag(run_key[run])) & (owner[seg] < ids[doc[run]])
            run, seg = run[hit], seg[hit]
            for d, x, y in zip(doc[run].tolist(), (at[run] + low[seg]).tolist(), (at[run] + high[seg] + depth - 1).tolist()):
                masks[d][x:y] = True
        return cut_out(ids.tolist(), rows["named"].to_numpy(bool), texts, masks)

    asked = round_trip(blocks, send_keys, settle_keys, "keys binary, many binary", "bucket int, keys binary")
    told = round_trip(blocks, send_strings, settle_strings, "counts binary, least binary, most binary, keys binary, contents binary, texts binary", "keys binary, contents binary, lows binary, highs binary, ids binary", asked)
    return finish(blocks, told, remove, CUT_LAYOUT)


def query(spark, sf_dir):
    from .common import table

    found = deduplicate(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select(
        F.col("id").alias("doc_id"),
        "n_bytes",
        (F.col("n_bytes") - F.octet_length("kept")).cast("long").alias("n_removed"),
        F.size("spans").cast("long").alias("n_spans"),
        F.sha2("kept", 256).alias("kept_sha256"),
    )
