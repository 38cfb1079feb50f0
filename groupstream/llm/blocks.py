"""An exchange between blocks of documents and buckets of keys, in packed rows.

Documents are dealt into blocks by a hash of their id, a few MB each. A block's kernel sends each bucket one row of packed
arrays; a bucket's kernel sees all that was sent under its keys, and answers each block with one row. A key that a third
of all documents share thus reaches its bucket once per block, not once per document. Blocks and buckets grow in number
with the data, their size does not.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import long_id, partitions

BLOCK_BYTES, BUCKET_BYTES = 4 << 20, 16 << 20
#: Stands for a null id: as large as any, so it takes nothing from other documents; `named` tells whether it does.
NO_ID = (1 << 63) - 1


def into_blocks(docs: DataFrame, id_column: str, text: str) -> tuple[DataFrame, int]:
    """(block, id, named, text as bytes) of every row, and the number of buckets that suits their size."""
    own = long_id(docs, id_column)
    slim = docs.select(F.coalesce(own, F.lit(NO_ID)).alias("id"), own.isNotNull().alias("named"), F.coalesce(F.col(text).cast("binary"), F.lit(b"")).alias("text"))
    total = slim.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    least = partitions(docs.sparkSession)
    blocks = max(2 * least, math.ceil(total / BLOCK_BYTES))
    return slim.select(F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int").alias("block"), "id", "named", "text"), max(least, math.ceil(total / BUCKET_BYTES))


def round_trip(blocks: DataFrame, send: Callable, settle: Callable, layout: str, answers: str, extra: DataFrame | None = None) -> DataFrame:
    """One exchange: send(documents[, answers before]) -> rows by bucket; settle(rows of a bucket) -> rows by block."""
    if extra is None:
        sent = blocks.groupBy("block").applyInPandas(send, f"bucket int, block int, {layout}")
    else:
        sent = blocks.groupBy("block").cogroup(extra.groupBy("block")).applyInPandas(send, f"bucket int, block int, {layout}")
    return sent.groupBy("bucket").applyInPandas(settle, f"block int, {answers}")


def finish(blocks: DataFrame, answers: DataFrame, kernel: Callable, layout: str) -> DataFrame:
    return blocks.groupBy("block").cogroup(answers.groupBy("block")).applyInPandas(kernel, layout)


def dealt(bucket: np.ndarray, n: int) -> tuple[np.ndarray, Iterator[tuple[int, slice]]]:
    """The order that brings rows of a bucket together, and each bucket with its part of that order."""
    order = np.argsort(bucket, kind="stable")
    edge = np.searchsorted(bucket[order], np.arange(n + 1))
    return order, ((b, slice(int(edge[b]), int(edge[b + 1]))) for b in range(n) if edge[b] < edge[b + 1])


def joined(rows: pd.DataFrame, column: str, dtype) -> np.ndarray:
    """The packed arrays of a column as one array."""
    return np.frombuffer(b"".join(rows[column]), dtype)


def runs_of(mask: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the runs of True."""
    edge = np.flatnonzero(np.diff(np.concatenate(([False], mask, [False])).astype(np.int8)))
    return edge[::2], edge[1::2]


def cut_out(ids: list[int], named: np.ndarray, texts: list[bytes], masks: list[np.ndarray]) -> pd.DataFrame:
    """What is left of each text where its mask is not set, with the spans that went."""
    rows = []
    for i, text, mask in zip(ids, texts, masks):
        if mask.any():
            starts, ends = runs_of(mask)
            left = np.frombuffer(text, np.uint8)[~mask].tobytes()
            rows.append((i, len(text), left, np.stack([starts, ends], 1).tolist()))
        else:
            rows.append((i, len(text), text, []))
    out = pd.DataFrame(rows, columns=["id", "n_bytes", "kept", "spans"])
    out["id"] = out["id"].astype("Int64").mask(~named)
    return out


CUT_LAYOUT = "id long, n_bytes long, kept binary, spans array<array<long>>"
