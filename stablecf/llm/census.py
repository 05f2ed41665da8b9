"""Corpus-wide counts of hashed items, gathered by owners and answered to every chunk.

A chunk of documents sends the different items it holds, each once, to the
owners of their key ranges, as sorted compressed arrays.  An owner merges what
all chunks sent and answers, for every chunk, one number per item in the order
sent.  Nothing is broadcast or collected, an item that every document has costs
one entry per chunk, and the answer is joined to its chunk by the chunk's number.

Items are 64-bit hashes reduced to (bucket, 32 bits).  Two different items may
fall together; that raises a count, which users of this module must tolerate
(they do: counts only order items or admit candidates that are then verified).
"""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from stablecf.llm import kernels as K

BLOB = "bucket int, chunk int, body binary"
_LOW = np.uint64(0xFFFFFFFF)


def sizes(total_bytes: int, bytes_per_item: float) -> tuple[int, int]:
    """(bytes of a chunk, number of buckets): both grow with the root of the input until a chunk is 32 MB and a bucket 4 M items, so that bodies stay long."""
    s = math.sqrt(max(1.0, total_bytes / 1e9))
    chunk = int(min(32 << 20, (4 << 20) * s))
    items = min(4 << 20, (128 << 10) * s)
    return chunk, max(1, math.ceil(total_bytes / bytes_per_item / items))


def reduced(h: np.ndarray, buckets: int) -> np.ndarray:
    """Key of an item: its bucket in the upper half, 32 bits of its hash in the lower."""
    return (((h >> np.uint64(32)) % np.uint64(buckets)) << np.uint64(32)) | (h & _LOW)


def by_bucket(sorted_keys: np.ndarray):
    """(bucket, first, last) of sorted reduced keys."""
    if not len(sorted_keys):
        return
    b = (sorted_keys >> np.uint64(32)).astype(np.int64)
    edge = np.flatnonzero(np.diff(b)) + 1
    for a, z in zip(np.concatenate([[0], edge]).tolist(), np.concatenate([edge, [len(b)]]).tolist(), strict=True):
        yield int(b[a]), a, z


def blob_rows(rows: list[tuple[int, int, bytes]]) -> pa.Table:
    b, c, d = zip(*rows, strict=True) if rows else ((), (), ())
    return pa.table({"bucket": pa.array(b, pa.int32()), "chunk": pa.array(c, pa.int32()), "body": pa.array(d, pa.binary())})


def sent(chunk: int, keys: np.ndarray, *extra: np.ndarray) -> list[tuple[int, int, bytes]]:
    """Rows of one chunk: sorted different reduced ``keys`` with aligned ``extra`` arrays."""
    return [(b, chunk, K.squeeze(K.deltas((keys[a:z] & _LOW).astype(np.uint32)), *(e[a:z] for e in extra))) for b, a, z in by_bucket(keys)]


def owners(blobs: DataFrame, answer: Callable[[list[np.ndarray], list[list[np.ndarray]]], list[np.ndarray]]) -> DataFrame:
    """``answer`` gets, for a bucket, the chunks' sorted keys and their extra arrays, and gives one array per chunk."""

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by([("chunk", "ascending")])
        parts = [K.unsqueeze(x) for x in t["body"].to_pylist()]
        keys = [K.undelta(p[0]) for p in parts]
        said = answer(keys, [p[1:] for p in parts])
        return pa.table({"bucket": t["bucket"], "chunk": t["chunk"], "body": pa.array([K.squeeze(x) for x in said], pa.binary())})

    return blobs.groupBy("bucket").applyInArrow(run, BLOB)


def answers(t: pa.Table, keys: np.ndarray, dtype) -> np.ndarray:
    """The owners' numbers for a chunk's sorted ``keys``; ``t``: the chunk's answered rows."""
    out = np.zeros(len(keys), dtype=dtype)
    got = dict(zip(t["bucket"].to_pylist(), t["body"].to_pylist(), strict=True))
    for b, a, z in by_bucket(keys):
        out[a:z] = K.unsqueeze(got[b])[0]
    return out


def chunk_counts(keys: list[np.ndarray], extra: list[list[np.ndarray]]) -> list[np.ndarray]:
    """An answer: in how many chunks each key is, or, if counts were sent, their sums; as a class, the bit length (0 to 32)."""
    every = np.concatenate(keys)
    u, back = np.unique(every, return_inverse=True)
    n = np.bincount(back, weights=np.concatenate([e[0] for e in extra]) if extra and extra[0] else None, minlength=len(u))
    cls = np.ceil(np.log2(np.maximum(n, 1))).astype(np.uint8)[back]
    return np.split(cls, np.cumsum([len(k) for k in keys])[:-1])
