"""Prediction by partial matching over bytes, as a language-model score.

A text is its lower-cased words joined by single spaces, then one end byte (0).
The model is a trie of byte contexts of up to ``order`` bytes (five by default,
six at most).  A symbol's
probability starts at the longest context seen in training; with counts c of
the symbols there, their sum n and number q,

    p(symbol) = (2 c - 1) / (2 n),   p(escape) = q / (2 n),

and an escape goes to the context shorter by one byte, from whose counts the
symbols of the longer context are excluded; below order 0 all symbols not yet
excluded are alike.

Distributed form: a chunk sends its different strings of ``order`` + 1 bytes with
their training counts to owners chosen by the two bytes before the symbol, so an
owner holds whole branches of orders 2 and above; orders 1 and 0 are a table of
at most 65536 counts.  Owners answer with each string's log probability.  Words
for the unigram base go the same way.  ``BytePPM`` is the same model as a trie in
memory, which can also adapt while it codes; ``adaptive_documents`` codes each
document so, from an empty trie.

Defined results: null text is the end alone; without any training text every
symbol has probability 1/256 and the base uses counts of 0; a NUL in a text is
coded as byte 255, which UTF-8 lacks, as 0 is the end; rows that repeat
are scored one by one; null ids are training documents.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stablecf.llm import census
from stablecf.llm import kernels as K
from stablecf.llm.common import NO_ID, chunked, ids_and_texts, ship

ORDER = 5
SCHEMA = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double, n_bytes long"


class BytePPM:
    """Trie of byte contexts (newest byte first); each node counts the symbols that followed it."""

    def __init__(self, order: int = ORDER) -> None:
        self.order, self.root = order, ({}, {})

    def _path(self, ctx: bytes) -> list[dict[int, int]]:
        """Counts of the contexts of length 0, 1, ... that exist."""
        node, out = self.root, []
        for k in range(self.order + 1):
            out.append(node[0])
            if k == self.order or k >= len(ctx) or (node := node[1].get(ctx[-1 - k])) is None:
                break
        return out

    def learn(self, ctx: bytes, symbol: int) -> None:
        node = self.root
        for k in range(self.order + 1):
            node[0][symbol] = node[0].get(symbol, 0) + 1
            if k < self.order:
                node = node[1].setdefault(ctx[-1 - k], ({}, {}))

    def log10(self, ctx: bytes, symbol: int) -> float:
        out, gone = 0.0, set()
        for counts in reversed(self._path(ctx)):
            left = {s: c for s, c in counts.items() if s not in gone}
            n, q = sum(left.values()), len(left)
            if not n:
                continue
            if symbol in left:
                return out + float(np.log10((2 * left[symbol] - 1) / (2 * n)))
            out += float(np.log10(q / (2 * n)))
            gone |= left.keys()
        return out - float(np.log10(max(1, 256 - len(gone))))

    def code(self, stream: bytes, adapt: bool = False) -> float:
        """log10 probability of a stream; with ``adapt`` the trie learns every symbol after coding it."""
        ctx, total = bytes(self.order), 0.0
        for s in stream:
            total += self.log10(ctx, s)
            if adapt:
                self.learn(ctx, s)
            ctx = (ctx + bytes([s]))[-self.order :]
        return total

    def train(self, stream: bytes) -> None:
        ctx = bytes(self.order)
        for s in stream:
            self.learn(ctx, s)
            ctx = (ctx + bytes([s]))[-self.order :]


def stream_of(text: str) -> bytes:
    """The bytes that the model codes for a text."""
    return b" ".join(w for w in text.encode().translate(_PLAIN).split(b" ") if w) + b"\0"


_PLAIN = bytes(255 if not i else 32 if i in (9, 10, 11, 12, 13) else int(K.LOWER[i]) for i in range(256))


def streams(data: np.ndarray, starts: np.ndarray, ends: np.ndarray):
    """(stream bytes of all texts, their lengths, word hashes, numbers of words)."""
    buf, s, e = K.spaced(data, starts, ends)
    buf = K.LOWER[buf]
    ws, we = K.word_spans(buf, K.NONBLANK)
    words = np.searchsorted(ws, e) - np.searchsorted(ws, s)
    h = K.word_hashes(buf, ws, we)
    keep = K.NONBLANK[buf]
    buf = np.where(keep, buf, np.uint8(32))
    buf[buf == 0] = 255
    keep[we] = True
    last = np.cumsum(words) - 1
    end = np.where(words > 0, we[last] if len(we) else e, e)
    keep[end] = True
    buf[end] = 0
    total = np.concatenate([[0], np.cumsum(keep)])
    n = total[e + 1] - total[s]
    return buf[keep], n, h, words


def strings(stream: np.ndarray, n: np.ndarray, order: int) -> np.ndarray:
    """Each symbol with the ``order`` bytes before it, as a number; zeros stand before a text."""
    first = np.cumsum(n) - n
    b = np.insert(stream, np.repeat(first, order), 0).astype(np.uint64)
    key = np.zeros(len(b), dtype=np.uint64)
    for k in range(order + 1):
        key[k:] |= b[: len(b) - k] << np.uint64(8 * k)
    keep = np.ones(len(b), dtype=bool)
    pad = first + order * np.arange(len(n))
    keep[(pad[:, None] + np.arange(order)).ravel()] = False
    return key[keep]


def _string_bucket(keys: np.ndarray, buckets: int) -> np.ndarray:
    return (K.mix((keys >> np.uint64(8)) & np.uint64(0xFFFF)) % np.uint64(buckets)).astype(np.int64)


def _segment_sum(values: np.ndarray, group: np.ndarray, n: int) -> np.ndarray:
    return np.bincount(group, weights=values, minlength=n)


def log_probabilities(keys: np.ndarray, counts: np.ndarray, table: np.ndarray, order: int = ORDER) -> np.ndarray:
    """log10 of each string's last symbol; ``keys`` sorted and different, with all strings of their two-byte contexts.

    ``table``: 256 x 256 training counts of (byte, next symbol).
    """
    high = range(order, 1, -1)
    sym = (keys & np.uint64(255)).astype(np.int64)
    c = {order: counts.astype(np.float64)}
    here = {order: np.arange(len(keys))}  # each string's (context, symbol) of an order
    ctx, n_ctx = {}, {}
    for k in range(order - 1, 1, -1):
        u, back = np.unique(keys & np.uint64((1 << (8 * (k + 1))) - 1), return_inverse=True)
        here[k] = back
        c[k] = _segment_sum(c[order], back, len(u))
    for k in high:
        u, back = np.unique((keys >> np.uint64(8)) & np.uint64((1 << (8 * k)) - 1), return_inverse=True)
        ctx[k], n_ctx[k] = back, len(u)
    one = ((keys >> np.uint64(8)) & np.uint64(255)).astype(np.int64)
    table = table.astype(np.float64)
    n0 = table.sum(axis=0)
    count_at = {k: c[k][here[k]] for k in high} | {1: table[one, sym], 0: n0[sym]}
    out, done = np.zeros(len(keys)), np.zeros(len(keys), dtype=bool)
    # what is left of a context's counts after the exclusions that its longer context brings
    left_n, left_q = {}, {}
    first = {k: np.unique(here[k], return_index=True)[1] for k in high}
    for k in high:
        f = first[k]
        left_n[k] = _segment_sum(count_at[k][f], ctx[k][f], n_ctx[k])[ctx[k]]
        left_q[k] = _segment_sum((count_at[k][f] > 0).astype(float), ctx[k][f], n_ctx[k])[ctx[k]]
    left_n[1], left_q[1] = table.sum(axis=1)[one], (table > 0).sum(axis=1).astype(float)[one]
    left_n[0], left_q[0] = np.full(len(keys), n0.sum()), np.full(len(keys), float((n0 > 0).sum()))
    for k in range(order - 1, 0, -1):  # exclude the symbols of order k + 1 from order k
        f = first[k + 1]
        seen = count_at[k + 1][f] > 0
        g = ctx[k + 1][f]
        left_n[k] = left_n[k] - _segment_sum(count_at[k][f] * seen, g, n_ctx[k + 1])[ctx[k + 1]]
        left_q[k] = left_q[k] - _segment_sum(seen & (count_at[k][f] > 0), g, n_ctx[k + 1])[ctx[k + 1]]
    seen1 = table > 0
    left_n[0] = left_n[0] - (seen1 * n0).sum(axis=1)[one]
    left_q[0] = left_q[0] - seen1.sum(axis=1)[one]
    for k in range(order, -1, -1):
        n, q = left_n[k], left_q[k]
        live = ~done & (q > 0)
        hit = live & (count_at[k] > 0)
        out[hit] += np.log10((2 * count_at[k][hit] - 1) / (2 * n[hit]))
        done |= hit
        esc = live & ~hit
        out[esc] += np.log10(q[esc] / (2 * n[esc]))
    rest = ~done
    out[rest] -= np.log10(max(1, 256 - int((n0 > 0).sum())))
    return out


def _held(ids: list[int], fold: int, of: int) -> np.ndarray:
    return np.array([x != NO_ID and zlib.crc32(str(x).encode()) % of == fold for x in ids], dtype=bool)


def _items(t: pa.Table, fold: int, of: int, order: int = ORDER):
    """Per block: (first text, last text, strings, lengths, word hashes, numbers of words, held out)."""
    data, starts, ends = K.as_bytes(t["text"])
    held = _held(t["doc_id"].to_pylist(), fold, of)
    for i, j in K.blocks(starts, ends):
        st, n, h, words = streams(data, starts[i:j], ends[i:j])
        yield i, j, strings(st, n, order), n, h, words, held[i:j]


def _counted(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """Different keys of blocks with their counts added up."""
    keys, counts = np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])
    u, back = np.unique(keys, return_inverse=True)
    return u, np.bincount(back, weights=counts, minlength=len(u)).astype(np.int64)


def _tally(keys: np.ndarray, train: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Different keys, and how often each is a training key."""
    u, back = _ranked(keys)
    return u, np.bincount(back[train], minlength=len(u)).astype(np.int64)


def _send(chunk: int, t: pa.Table, word_buckets: int, string_buckets: int, fold: int, of: int, order: int) -> pa.Table:
    K.trim()
    s, w = [], []
    for _, _, keys, n, h, words, held in _items(t, fold, of, order):
        s.append(_tally(keys, np.repeat(~held, n)))
        w.append(_tally(h, np.repeat(~held, words)))
    keys, counts = _counted(w)
    rows = _parcels(chunk, keys, counts, (keys % np.uint64(word_buckets)).astype(np.int64), range(word_buckets))
    keys, counts = _counted(s)
    where = _string_bucket(keys, string_buckets)
    return census.blob_rows(rows + _parcels(chunk, keys, counts, word_buckets + where, np.unique(word_buckets + where).tolist()))


def _parcels(chunk: int, keys: np.ndarray, counts: np.ndarray, bucket: np.ndarray, every) -> list[tuple[int, int, bytes]]:
    order = np.argsort(bucket, kind="stable")
    b = bucket[order]
    lo, hi = np.searchsorted(b, list(every)), np.searchsorted(b, list(every), side="right")
    return [(int(x), chunk, K.squeeze(K.deltas(keys[order[i:j]]), counts[order[i:j]].astype(np.uint32))) for x, i, j in zip(every, lo.tolist(), hi.tolist(), strict=True)]


def _answer(t: pa.Table, word_buckets: int, table: np.ndarray, order: int) -> pa.Table:
    K.trim()
    bucket = t["bucket"][0].as_py()
    t = t.sort_by([("chunk", "ascending")])
    parts = [K.unsqueeze(x) for x in t["body"].to_pylist()]
    keys = np.concatenate([K.undelta(p[0]) for p in parts])
    u, back = np.unique(keys, return_inverse=True)
    n = np.bincount(back, weights=np.concatenate([p[1] for p in parts]), minlength=len(u))
    if bucket < word_buckets:
        tail = [np.array([int(n.sum()), int((n > 0).sum())], dtype=np.int64)]
        said = n.astype(np.int64)
    else:
        tail, said = [], log_probabilities(u, n, table, order).astype(np.float32)
    edge = np.cumsum([len(p[0]) for p in parts])[:-1]
    return pa.table({"bucket": t["bucket"], "chunk": t["chunk"], "body": pa.array([K.squeeze(x, *tail) for x in np.split(said[back], edge)], pa.binary())})


def _values(keys: np.ndarray, bucket: np.ndarray, got: dict[int, list[np.ndarray]], dtype) -> np.ndarray:
    out = np.zeros(len(keys), dtype=dtype)
    order = np.argsort(bucket, kind="stable")
    b = bucket[order]
    for x in np.unique(b).tolist():
        i, j = np.searchsorted(b, x), np.searchsorted(b, x, side="right")
        out[order[i:j]] = got[x][0]
    return out


def _score(t: pa.Table, told: pa.Table, word_buckets: int, string_buckets: int, fold: int, of: int, train_docs: int, order: int) -> pa.Table:
    K.trim()
    blocks = [(i, j, n, words, held, *np.unique(h, return_inverse=True), *_ranked(keys)) for i, j, keys, n, h, words, held in _items(t, fold, of, order)]
    got = {b: K.unsqueeze(x) for b, x in zip(told["bucket"].to_pylist(), told["body"].to_pylist(), strict=True)}
    total = train_docs + sum(int(got[b][1][0]) for b in range(word_buckets))
    different = (train_docs > 0) + sum(int(got[b][1][1]) for b in range(word_buckets))
    wk, sk = (np.unique(np.concatenate([x[k] for x in blocks])) for k in (5, 7))
    wc = _values(wk, (wk % np.uint64(word_buckets)).astype(np.int64), got, np.int64)
    sv = _values(sk, word_buckets + _string_bucket(sk, string_buckets), got, np.float32)
    low = np.log10(total + 0.5 * (different + 1))
    cols: list[list] = [[] for _ in range(7)]
    for _, _, n, words, held, u, back, v, rank in blocks:
        c = wc[np.searchsorted(wk, u)][back]
        logs = _per_text(np.log10(c + 0.5), words) + np.log10(train_docs + 0.5) - (words + 1) * low
        known = _per_text((c > 0).astype(np.int64), words) + (train_docs > 0)
        score = _per_text(sv[np.searchsorted(sk, v)].astype(np.float64)[rank], n)
        for out, x in zip(cols, (held, words + 1, known, np.full(len(n), total), logs, score, n), strict=True):
            out.append(x)
    ids = pa.array([None if x == NO_ID else x for x in t["doc_id"].to_pylist()], pa.int64())
    names = [c.split()[0] for c in SCHEMA.split(", ")]
    kinds = [pa.bool_(), pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.int64()]
    return pa.table([ids, *(pa.array(np.concatenate(c), k) for c, k in zip(cols, kinds, strict=True))], names=names)


def _ranked(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """np.unique with inverse, by one sort of key and place together, the bytes of the key written in as few bits as the block's bytes need."""
    if not len(keys):
        return keys, np.zeros(0, dtype=np.int32)
    parts = keys.view(np.uint8).reshape(-1, 8)[:, : max(1, -(-int(keys.max()).bit_length() // 8))]  # newest byte first
    used = np.unique(parts)
    bits, place = max(1, int(len(used) - 1).bit_length()), int(len(keys) - 1).bit_length()
    if bits * parts.shape[1] + place > 64:
        return np.unique(keys, return_inverse=True)
    rank = np.zeros(256, dtype=np.uint64)
    rank[used] = np.arange(len(used), dtype=np.uint64)
    x = np.zeros(len(keys), dtype=np.uint64)
    for i in range(parts.shape[1]):
        x |= rank[parts[:, i]] << np.uint64(bits * i)
    x = np.sort((x << np.uint64(place)) | np.arange(len(keys), dtype=np.uint64))
    k, at = x >> np.uint64(place), (x & np.uint64((1 << place) - 1)).astype(np.int64)
    new = np.append(True, k[1:] != k[:-1])
    out = np.empty(len(keys), dtype=np.int32)
    out[at] = np.cumsum(new) - 1
    return keys[at[new]], out


def _per_text(values: np.ndarray, n: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0], np.cumsum(values)])
    end = np.cumsum(n)
    return total[end] - total[end - n]


def _bigrams(batches, fold: int, of: int):
    total = np.zeros(1 << 16, dtype=np.int64)
    for b in batches:
        for _, _, keys, n, _, _, held in _items(pa.Table.from_batches([b]), fold, of):
            total += np.bincount((keys & np.uint64(0xFFFF)).astype(np.int64)[np.repeat(~held, n)], minlength=1 << 16)
    i = np.flatnonzero(total)
    yield pa.RecordBatch.from_arrays([pa.array(i, pa.int32()), pa.array(total[i], pa.int64())], ["pair", "n"])


def score_documents(spark: SparkSession, df: DataFrame, fold: int = 1, of: int = 5, order: int = ORDER, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document, as ``SCHEMA`` says; documents whose crc32(id as text) mod ``of`` is ``fold`` are not learnt from."""
    if not 2 <= order <= 6:
        raise ValueError("2 <= order <= 6 is needed")
    ship(spark)
    docs = ids_and_texts(df, id_col, text_col)
    learnt = F.when((F.col("doc_id") == NO_ID) | (F.crc32(F.col("doc_id").cast("string")) % of != fold), 1).otherwise(0)
    first = docs.agg(F.sum(F.octet_length("text")).alias("b"), F.sum(learnt).alias("n")).first()
    total, train_docs = int(first["b"] or 0), int(first["n"] or 0)
    # orders 1 and 0: at most 65536 rows reach the driver, whatever the input
    pairs = docs.mapInArrow(lambda it: _bigrams(it, fold, of), "pair int, n long").groupBy("pair").agg(F.sum("n").alias("n")).collect()
    table = np.zeros(1 << 16, dtype=np.int64)
    for r in pairs:
        table[r["pair"]] = r["n"]
    table = table.reshape(256, 256)
    size, string_buckets = census.sizes(total, 16)
    word_buckets = max(1, string_buckets // 2)
    chunks, _, _ = chunked(spark, docs, size, total)

    def send(key: tuple, t: pa.Table) -> pa.Table:
        return _send(key[0].as_py(), t, word_buckets, string_buckets, fold, of, order)

    def score(t: pa.Table, told: pa.Table) -> pa.Table:
        return _score(t, told, word_buckets, string_buckets, fold, of, train_docs, order)

    told = chunks.groupBy("chunk").applyInArrow(send, census.BLOB).groupBy("bucket").applyInArrow(lambda t: _answer(t, word_buckets, table, order), census.BLOB)
    return chunks.groupBy("chunk").cogroup(told.groupBy("chunk")).applyInArrow(score, SCHEMA)


def adaptive_documents(spark: SparkSession, df: DataFrame, order: int = ORDER, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_bytes, score): each document coded from an empty trie that learns every symbol after coding it."""
    ship(spark)

    def run(batches):
        for b in batches:
            data = [stream_of(t) for t in b.column(1).to_pylist()]
            ids = pa.array([None if x == NO_ID else x for x in b.column(0).to_pylist()], pa.int64())
            score = [BytePPM(order).code(s, adapt=True) for s in data]
            yield pa.RecordBatch.from_arrays([ids, pa.array([len(s) for s in data], pa.int64()), pa.array(score, pa.float64())], ["doc_id", "n_bytes", "score"])

    return ids_and_texts(df, id_col, text_col).mapInArrow(run, "doc_id long, n_bytes long, score double")
