"""Substring deduplication by content-defined chunking.

A gear rolling hash over the last 16 bytes ends a chunk wherever four of its bits are zero, so chunks follow the content
(16 bytes on average) and an insertion moves no boundary but those next to it. A chunk of more than LONG bytes, as
repeated words make, is cut on where fewer of the bits are zero. A chunk is a duplicate if its digest occurs earlier, in
a document with a smaller id or before it in the same one. A run of duplicate chunks is removed if it spans at least
MIN_BYTES; shorter ones are common phrases and stay, but for a document that is shorter as a whole: it goes if its whole
text is that of a document with a smaller id.

Cases: null and empty texts have no chunks; texts of any length are chunked whole, with chunks of 1024 bytes at most;
rows that share an id keep what they share; null ids sort last and come back null; an empty table gives an empty result;
other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blocks import CUT_LAYOUT, cut_out, dealt, finish, into_blocks, joined, round_trip, runs_of

REACH, SHIFT, MASK, MOST = 16, 12, 15, 1024
LONG = 64
MIN_BYTES = 128
#: The seed of whole texts' digests, which keeps them apart from those of chunks.
WHOLE = 1


def gear_table() -> np.ndarray:
    """A random 32-bit number for each byte, from a hash of it."""
    return np.array([xxhash.xxh32_intdigest(bytes([b]), 1) for b in range(256)], np.uint32)


def chunk_ends(text: bytes, gear: np.ndarray) -> np.ndarray:
    """Where the chunks of a text end."""
    h = gear[np.frombuffer(text, np.uint8)]
    reach = 1
    while reach < REACH:
        h[reach:] = h[reach:] + (h[:-reach] << np.uint32(reach))
        reach *= 2
    h >>= np.uint32(SHIFT)
    ends = np.flatnonzero(h & np.uint32(MASK) == 0) + 1
    if not len(ends) or ends[-1] != len(text):
        ends = np.append(ends, len(text))
    sizes, mask = np.diff(ends, prepend=0), MASK >> 1
    while mask and (sizes > LONG).any():
        more = np.flatnonzero(h & np.uint32(mask) == 0) + 1
        ends = np.union1d(ends, more[sizes[np.searchsorted(ends, more)] > LONG])
        sizes, mask = np.diff(ends, prepend=0), mask >> 1
    if (sizes > MOST).any():
        ends = np.concatenate([[*range(int(e - s) + MOST, int(e), MOST), int(e)] for e, s in zip(ends, sizes)])
    return ends


def chunk_rows(texts: list[bytes], min_bytes: int) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
    """For all chunks in order: digest (two words), document number; and each document's chunk ends.

    A text of fewer than `min_bytes` has one more digest after those of its chunks, of the whole.
    """
    gear, digests, owner, ends_of = gear_table(), [], [], []
    for n, text in enumerate(texts):
        ends = chunk_ends(text, gear) if text else np.zeros(0, np.int64)
        at = 0
        for end in ends.tolist():
            digests.append(xxhash.xxh3_128_digest(text[at:end]))
            at = end
        if 0 < len(text) < min_bytes:
            digests.append(xxhash.xxh3_128_digest(text, WHOLE))
        owner.append(np.full(len(ends) + (0 < len(text) < min_bytes), n))
        ends_of.append(ends)
    return np.frombuffer(b"".join(digests), np.uint64).reshape(-1, 2), np.concatenate(owner or [np.zeros(0, np.int64)]), ends_of


def _first(words: np.ndarray, value: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct digests, the least value of each, and where each row's digest is among them."""
    order = np.lexsort((value, words[:, 1], words[:, 0]))
    w = words[order]
    new = np.concatenate(([True], (w[1:] != w[:-1]).any(1))) if len(w) else np.zeros(0, bool)
    at = np.empty(len(w), np.int64)
    at[order] = np.cumsum(new) - 1
    return w[new], value[order][new], at


def deduplicate(docs: DataFrame, min_bytes: int = MIN_BYTES, text: str = "text", id_column: str = "doc_id") -> DataFrame:
    """(id, n_bytes, kept, spans, n_chunks, n_duplicate_chunks): kept is what is left of the text, as bytes."""
    blocks, buckets = into_blocks(docs, id_column, text)

    def send(rows):
        ids = rows["id"].to_numpy(np.int64)
        words, owner, _ = chunk_rows(rows["text"].tolist(), min_bytes)
        distinct, first, _ = _first(words, ids[owner])
        order, parts = dealt((distinct[:, 0] % np.uint64(buckets)).astype(np.int64), buckets)
        distinct, first, block = distinct[order], first[order], int(rows["block"].iloc[0])
        return pd.DataFrame([(b, block, distinct[s].tobytes(), first[s].tobytes()) for b, s in parts], columns=["bucket", "block", "digests", "ids"])

    def settle(rows):
        words, ids = joined(rows, "digests", np.uint64).reshape(-1, 2), joined(rows, "ids", np.int64)
        block = np.repeat(rows["block"].to_numpy(), [len(x) // 8 for x in rows["ids"]])
        _, first, at = _first(words, ids)
        earlier = first[at]
        late = np.flatnonzero(earlier < ids)
        late = late[np.argsort(block[late], kind="stable")]
        edge = np.flatnonzero(np.diff(block[late], prepend=-1, append=-1)) if len(late) else [0]
        return pd.DataFrame([(int(block[late[a]]), words[late[a:b]].tobytes(), earlier[late[a:b]].tobytes()) for a, b in zip(edge[:-1], edge[1:])], columns=["block", "digests", "ids"])

    def remove(rows, answers):
        if rows.empty:
            return pd.DataFrame(columns=["id", "n_bytes", "kept", "spans", "n_chunks", "n_duplicate_chunks"])
        ids, texts = rows["id"].to_numpy(np.int64), rows["text"].tolist()
        words, owner, ends_of = chunk_rows(texts, min_bytes)
        told, told_ids = joined(answers, "digests", np.uint64).reshape(-1, 2), joined(answers, "ids", np.int64)
        _, first, at = _first(np.concatenate([words, told]), np.concatenate([ids[owner], told_ids]))
        at = at[: len(words)]
        place = np.concatenate([np.arange(len(e) + (0 < len(t) < min_bytes)) for t, e in zip(texts, ends_of)] or [np.zeros(0, np.int64)])
        own = ids[owner]
        home = first[at] == own
        least = np.full(len(first), np.iinfo(np.int64).max)
        np.minimum.at(least, at[home], place[home])
        again = ~home | (place > least[at])  # rows with one id have a whole text at one place and keep it
        masks, made, start = [], [], 0
        for n, (text, ends) in enumerate(zip(texts, ends_of)):
            dup = again[start : start + len(ends)]
            mask = np.zeros(len(text), bool)
            if dup.any():
                begins = np.concatenate(([0], ends[:-1]))
                for a, b in zip(*(x.tolist() for x in runs_of(dup))):
                    if ends[b - 1] - begins[a] >= min_bytes:
                        mask[begins[a] : ends[b - 1]] = True
            masks.append(mask)
            made.append((len(ends), int(dup.sum())))
            start += len(ends)
            if 0 < len(text) < min_bytes:
                mask |= again[start]
                start += 1
        out = cut_out(ids.tolist(), rows["named"].to_numpy(bool), texts, masks)
        out["n_chunks"], out["n_duplicate_chunks"] = [m[0] for m in made], [m[1] for m in made]
        return out

    answers = round_trip(blocks, send, settle, "digests binary, ids binary", "digests binary, ids binary")
    return finish(blocks, answers, remove, f"{CUT_LAYOUT}, n_chunks long, n_duplicate_chunks long")


def query(spark, sf_dir):
    """Every document with what the deduplication took from it."""
    from .common import table

    found = deduplicate(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select(
        F.col("id").alias("doc_id"),
        "n_bytes",
        "n_chunks",
        "n_duplicate_chunks",
        (F.col("n_bytes") - F.octet_length("kept")).cast("long").alias("n_removed"),
        F.size("spans").cast("long").alias("n_spans"),
        F.sha2("kept", 256).alias("kept_sha256"),
    )
