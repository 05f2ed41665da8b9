"""Sequence packing: first-fit decreasing with a tournament tree of bin capacities, in randomised groups.

Documents are dealt at random (by a hash, so reproducibly) to groups of about
``group_bytes`` of text; one task tokenises and packs a group.  A document's
full pieces of ``capacity`` ids are sequences of their own; its rest is packed
first-fit decreasing.  With ``top_up`` the emptiest bins are then dissolved:
their pieces are cut to fill the gaps of the others, so that a group leaves at
most one sequence to be padded.

Words between ASCII blanks are tokenised once per worker and remembered (up to
``MEMORY`` words), as no token of the vocabulary crosses a blank.

Defined results: a null or empty text is a document of the end id alone; rows
that repeat an id are packed one by one; an empty table gives no pieces.
"""

from __future__ import annotations

import os
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stablecf.llm import kernels as K
from stablecf.llm.common import NO_ID, chunked, ids_and_texts, ship

VOCABULARY = "word_bpe_49k.json"
END_ID = 1
MEMORY = 2_000_000
SLICE = 1 << 14
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


class TournamentTree:
    """Winner tree over bin capacities: the first bin with room is found in log steps."""

    def __init__(self, bins: int, capacity: int) -> None:
        self.leaves = 1 << max(0, bins - 1).bit_length()
        self.room = [capacity] * (2 * self.leaves)

    def first_with(self, need: int) -> int:
        room, i = self.room, 1
        if room[1] < need:
            return -1
        while i < self.leaves:
            i += i
            if room[i] < need:
                i += 1
        return i - self.leaves

    def take(self, b: int, need: int) -> None:
        room, i = self.room, b + self.leaves
        room[i] -= need
        while i > 1:
            i >>= 1
            room[i] = max(room[2 * i], room[2 * i + 1])


def first_fit_decreasing(sizes: list[int], capacity: int) -> list[list[int]]:
    """Bins of item indices; ties keep the items' order."""
    if not sizes:
        return []
    tree = TournamentTree(len(sizes), capacity)
    bins: list[list[int]] = []
    for i in sorted(range(len(sizes)), key=lambda i: -sizes[i]):
        b = tree.first_with(sizes[i])
        if b < 0:
            raise ValueError("an item is larger than a bin")
        tree.take(b, sizes[i])
        if b == len(bins):
            bins.append([])
        bins[b].append(i)
    return bins


def pack(lengths: list[int], capacity: int, top_up: bool) -> list[list[tuple[int, int, int]]]:
    """Sequences of (document, start, length) that together hold every id of every document once."""
    full = [[(d, s * capacity, capacity)] for d, n in enumerate(lengths) for s in range(n // capacity)]
    rest = [(d, n // capacity * capacity, n % capacity) for d, n in enumerate(lengths) if n % capacity]
    bins = [[rest[i] for i in b] for b in first_fit_decreasing([r[2] for r in rest], capacity)]
    if top_up and len(bins) > 1:
        fill = [sum(p[2] for p in b) for b in bins]
        order = sorted(range(len(bins)), key=lambda b: -fill[b])  # the fullest are topped up first, the emptiest dissolved first
        lo, hi = 0, len(order) - 1
        while lo < hi:
            gap, src = capacity - fill[order[lo]], order[hi]
            if not gap:
                lo += 1
            elif not bins[src]:
                hi -= 1
            else:
                d, s, n = bins[src].pop()
                cut = min(gap, n)
                bins[order[lo]].append((d, s, cut))
                fill[order[lo]] += cut
                fill[src] -= cut
                if cut < n:
                    bins[src].append((d, s + cut, n - cut))
        bins = [b for b in bins if b]
    return full + bins


class WordTokens:
    """Ids of whole texts through remembered ids of their words."""

    def __init__(self, path: str) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # a task has one core, and threads keep memory of their own
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.clear()

    def clear(self) -> None:
        self.keys, self.at, self.n, self.pool = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint32)

    def learn(self, keys: np.ndarray, words: list[str]) -> None:
        ids = [e.ids for i in range(0, len(words), SLICE) for e in self.tok.encode_batch_fast(words[i : i + SLICE], add_special_tokens=False)]
        n = np.fromiter(map(len, ids), np.int64, len(ids))
        at = len(self.pool) + np.cumsum(n) - n
        self.pool = np.concatenate([self.pool, np.fromiter((x for i in ids for x in i), np.uint32, int(n.sum()))])
        where = np.searchsorted(self.keys, keys)
        self.keys, self.at, self.n = np.insert(self.keys, where, keys), np.insert(self.at, where, at), np.insert(self.n, where, n)

    def texts(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(all ids, each text followed by END_ID; the texts' numbers of ids)."""
        buf, starts, ends = K.spaced(data, starts, ends)
        ws, we = K.word_spans(buf, K.NONBLANK)
        keys, first, back = np.unique(K.word_hashes(buf, ws, we), return_index=True, return_inverse=True)
        if len(self.keys) + len(keys) > MEMORY:
            self.clear()
        where = np.searchsorted(self.keys, keys)
        new = np.ones(len(keys), bool) if not len(self.keys) else self.keys[np.minimum(where, len(self.keys) - 1)] != keys
        if new.any():
            raw, f = buf.tobytes(), first[new]
            self.learn(keys[new], [raw[a:b].decode("utf-8", "replace") for a, b in zip(ws[f].tolist(), we[f].tolist(), strict=True)])
            where = np.searchsorted(self.keys, keys)
        at, n = self.at[where][back], self.n[where][back]
        per_text = np.searchsorted(ws, starts), np.searchsorted(ws, ends)
        total = np.concatenate([[0], np.cumsum(n)])
        counts = total[per_text[1]] - total[per_text[0]]
        flat = self.pool[np.repeat(at - total[:-1], n) + np.arange(total[-1])]
        return np.insert(flat, np.cumsum(counts), END_ID).astype(np.uint32), counts + 1


_loaded: dict[str, WordTokens] = {}


def vocabulary_path(path: str | None) -> str:
    if path:
        return path
    import public_tokenizers

    return str(public_tokenizers.path(VOCABULARY))


def pack_group(group: int, ids: list[int], texts: pa.Array, capacity: int, top_up: bool, path: str | None) -> pa.Table:
    path = vocabulary_path(path)
    tok = _loaded.get(path) or _loaded.setdefault(path, WordTokens(path))
    data, starts, ends = K.as_bytes(texts)
    parts, counts = [], []
    for i, j in K.blocks(starts, ends):
        flat, n = tok.texts(data, starts[i:j], ends[i:j])
        parts.append(flat)
        counts.append(n)
    flat, counts = np.concatenate(parts), np.concatenate(counts)
    base = np.cumsum(counts) - counts
    raw, rows = flat.astype("<u4").tobytes(), []
    lengths = counts.tolist()
    for q, seq in enumerate(pack(lengths, capacity, top_up)):
        offset = 0
        for d, s, n in seq:
            a = 4 * (int(base[d]) + s)
            rows.append((ids[d], s, n, zlib.crc32(raw[a : a + 4 * n]), lengths[d], (group << 32) + q, offset))
            offset += n
    cols = list(zip(*rows, strict=True))
    names = [c.split()[0] for c in SCHEMA.split(", ")]
    return pa.table({n: pa.array([None if n == "doc_id" and x == NO_ID else x for x in c] if n == "doc_id" else c, pa.int64()) for n, c in zip(names, cols, strict=True)})


def pack_documents(
    spark: SparkSession, df: DataFrame, capacity: int = 2048, group_bytes: int = 4 << 20, top_up: bool = True, path: str | None = None, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """One row per piece, as ``SCHEMA`` says; ``path`` is the vocabulary file (default: the public one by name)."""
    ship(spark)
    groups, _, _ = chunked(spark, ids_and_texts(df, id_col, text_col), group_bytes)

    def one(key: tuple, t: pa.Table) -> pa.Table:
        t = t.sort_by([("doc_id", "ascending")])
        return pack_group(key[0].as_py(), t["doc_id"].to_pylist(), t["text"], capacity, top_up, path)

    return groups.groupBy("chunk").applyInArrow(one, SCHEMA)
