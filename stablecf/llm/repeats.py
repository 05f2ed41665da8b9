"""Removal of long byte passages that a document with a smaller id has too: suffix sorting by deep-shallow sort.

Every ``length``-byte window has an anchor: the place in it whose ``gram``-byte
hash is smallest, leftmost of equals.  Equal windows have equal anchors, so
only windows whose anchor occurs in another document can repeat.  A census of
anchors (see ``census``) finds those; their surroundings, each different one
once per chunk, go to the owner of the anchor, which sorts all suffixes there to
``length`` bytes and keeps the smallest document of each class of equal windows.
The owner answers with one bit per window, and the document's chunk removes the bytes.

Defined results: null text is empty; a text shorter than ``length`` keeps all its
bytes; documents with equal ids don't remove each other's bytes; null ids
count as the largest id; rows come back one for one.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stablecf.llm import census
from stablecf.llm import kernels as K
from stablecf.llm.common import NO_ID, chunked, ids_and_texts, ship, staged, text_bytes
from stablecf.llm.deepshallow import sort_strings

_POS = np.uint64((1 << 24) - 1)
SCHEMA = "doc_id long, n_bytes long, n_removed long, n_spans long, kept binary, kept_sha256 string"


def anchors(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(text, first window, last window, anchor's hash) of each run of windows with one anchor; windows are places in ``data``."""
    out = []
    for i, j, a, z in _segments(starts, ends, length):
        buf = data[a:z]
        if len(buf) < length:
            continue
        e8 = K.eights(buf)
        m = len(buf) - gram + 1
        h = K.mix(e8[:m] ^ (K.mix(e8[gram - 8 : gram - 8 + m]) + np.uint64(0x632BE59BD9B4E019)))
        low = (h & ~_POS) | np.arange(m, dtype=np.uint64)
        w, span = length - gram + 1, 1
        while 2 * span <= w:
            low = np.minimum(low[:-span], low[span:])
            span *= 2
        if span < w:
            low = np.minimum(low[: len(low) - (w - span)], low[w - span :])
        at = (low & _POS).astype(np.int64)
        s, e = np.maximum(starts[i:j], a) - a, np.minimum(ends[i:j], z) - a
        n = np.maximum(0, e - s - length + 1)
        first = np.cumsum(n) - n
        win = np.repeat(s - first, n) + np.arange(int(n.sum()))
        if not len(win):
            continue
        doc, at = np.repeat(np.arange(i, j), n), at[win]
        new = np.ones(len(win), dtype=bool)
        new[1:] = (at[1:] != at[:-1]) | (doc[1:] != doc[:-1])
        f = np.flatnonzero(new)
        last = np.append(f[1:], len(win)) - 1
        out.append((doc[f], win[f] + a, win[last] + a, h[at[f]]))
    if not out:
        z = np.zeros(0, dtype=np.int64)
        return z, z, z, np.zeros(0, dtype=np.uint64)
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def _segments(starts: np.ndarray, ends: np.ndarray, length: int, size: int = 1 << 20, most: int = 1 << 23):
    """Blocks of whole texts; a text above ``most`` bytes in overlapping parts, so that each window lies in one."""
    for i, j in K.blocks(starts, ends, size):
        a, z = int(starts[i]), int(ends[j - 1])
        while z - a > most:
            yield i, j, a, a + most
            a += most - length + 1
        yield i, j, a, z


def _sorted(t: pa.Table) -> pa.Table:
    return t.sort_by([("doc_id", "ascending"), ("text", "ascending")])


def _digests(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """128-bit digest of each text as two numbers."""
    raw = b"".join(hashlib.sha256(data[a:z]).digest()[:16] for a, z in zip(starts.tolist(), ends.tolist(), strict=True))
    return np.frombuffer(raw, dtype=np.uint64).reshape(-1, 2)


def _first_copies(digests: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(order by digest, class of each place, smallest id of each class)."""
    order = np.lexsort((ids, digests[:, 1], digests[:, 0]))
    d = digests[order]
    new = np.append(True, (d[1:] != d[:-1]).any(axis=1))
    return order, np.cumsum(new) - 1, ids[order][new]


def _copy_bucket(digests: np.ndarray, buckets: int) -> np.ndarray:
    """Owners of texts come after the owners of anchors."""
    return buckets + (digests[:, 0] % np.uint64(max(1, buckets // 16))).astype(np.int64)


def send_anchors(chunk: int, t: pa.Table, buckets: int, length: int, gram: int) -> pa.Table:
    """Anchors, each once, to their owners, and the digest and smallest id of each text to the owner of copies."""
    data, starts, ends = K.as_bytes(t["text"])
    h = anchors(data, starts, ends, length, gram)[3]
    rows = census.sent(chunk, np.unique(census.reduced(h, buckets)))
    d = _digests(data, starts, ends)
    order, cls, least = _first_copies(d, t["doc_id"].to_numpy())
    first = order[np.append(True, cls[1:] != cls[:-1])]
    where = _copy_bucket(d[first], buckets)
    for b in np.unique(where).tolist():
        i = np.flatnonzero(where == b)
        rows.append((b, chunk, K.squeeze(d[first[i], 0], d[first[i], 1], least[i])))
    return census.blob_rows(rows)


def answer_all(t: pa.Table, buckets: int) -> pa.Table:
    """The owners of anchors say in how many chunks each is; the owners of copies say the smallest id of each text."""
    bucket = t["bucket"][0].as_py()
    t = t.sort_by([("chunk", "ascending")])
    parts = [K.unsqueeze(x) for x in t["body"].to_pylist()]
    if bucket < buckets:
        said = census.chunk_counts([K.undelta(p[0]) for p in parts], [[] for _ in parts])
    else:
        d = np.stack([np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])], axis=1)
        order, cls, least = _first_copies(d, np.concatenate([p[2] for p in parts]))
        out = np.empty(len(order), dtype=np.int64)
        out[order] = least[cls]
        said = np.split(out, np.cumsum([len(p[0]) for p in parts])[:-1])
    return pa.table({"bucket": t["bucket"], "chunk": t["chunk"], "body": pa.array([K.squeeze(x) for x in said], pa.binary())})


def _later_copies(t: pa.Table, told: pa.Table, buckets: int, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Whether a document with a smaller id has the same text."""
    ids, d = t["doc_id"].to_numpy(), _digests(data, starts, ends)
    order, cls, least = _first_copies(d, ids)
    first = order[np.append(True, cls[1:] != cls[:-1])]
    where = _copy_bucket(d[first], buckets)
    got = dict(zip(told["bucket"].to_pylist(), told["body"].to_pylist(), strict=True))
    for b in np.unique(where).tolist():
        least[where == b] = K.unsqueeze(got[b])[0]
    out = np.zeros(len(ids), dtype=bool)
    out[order] = least[cls] < ids[order]
    return out


def send_contexts(chunk: int, t: pa.Table, told: pa.Table, buckets: int, length: int, gram: int) -> pa.Table:
    """Surroundings of the anchors that other documents have too, each different one once, to the anchors' owners.

    A later copy of a whole text repeats everywhere, so it only tells itself so.
    """
    ids = t["doc_id"].to_numpy()
    data, starts, ends = K.as_bytes(t["text"])
    copy = _later_copies(t, told, buckets, data, starts, ends)
    whole = [(-1 - chunk, chunk, K.squeeze(np.flatnonzero(copy).astype(np.uint32)))] if copy.any() else []
    doc, lo, hi, h = anchors(data, starts, ends, length, gram)
    keys, back = np.unique(census.reduced(h, buckets), return_inverse=True)
    if not len(keys):
        return census.blob_rows(whole)
    who = ids[doc]
    least, most = np.full(len(keys), NO_ID), np.full(len(keys), -(1 << 63))
    np.minimum.at(least, back, who)
    np.maximum.at(most, back, who)
    again = (least < most) | (census.answers(told, keys, np.uint8) > 0)
    use = np.flatnonzero(again[back] & ~copy[doc])
    if not len(use):
        return census.blob_rows(whole)
    doc, lo, hi, who, bucket = doc[use], lo[use], hi[use], who[use], (keys >> np.uint64(32)).astype(np.int64)[back[use]]
    n = hi - lo + length
    flat = _gather(data, lo, n)
    at = np.cumsum(n) - n
    ctx = K.word_hashes(flat, at, at + n) if len(flat) < (8 << 20) else _hashes(flat, at, n)
    order = np.lexsort((who, ctx, bucket))
    new = np.ones(len(order), dtype=bool)
    c, b = ctx[order], bucket[order]
    new[1:] = (c[1:] != c[:-1]) | (b[1:] != b[:-1]) | ~_equal(flat, at[order], n[order])
    group = np.cumsum(new) - 1
    rep = order[new]
    mine = who[order] == who[rep][group]  # of the smallest document in this chunk; the others' windows all repeat
    rows, edge = whole, np.flatnonzero(np.append(True, b[1:] != b[:-1]))
    for a, z in zip(edge.tolist(), np.append(edge[1:], len(b)).tolist(), strict=True):
        g0, g1 = group[a], group[z - 1] + 1
        r, o = rep[g0:g1], order[a:z]
        body = K.squeeze(n[r].astype(np.uint8), who[r], (group[a:z] - g0).astype(np.uint32), mine[a:z].astype(np.uint8), doc[o].astype(np.uint32), (lo[o] - starts[doc[o]]).astype(np.uint64), _gather(flat, at[r], n[r]))
        rows.append((int(b[a]), chunk, body))
    return census.blob_rows(rows)


def _gather(data: np.ndarray, at: np.ndarray, n: np.ndarray) -> np.ndarray:
    total = np.cumsum(n) - n
    return data[np.repeat(at - total, n) + np.arange(int(n.sum()))]


def _hashes(flat: np.ndarray, at: np.ndarray, n: np.ndarray) -> np.ndarray:
    out = []
    for i, j in K.blocks(at, at + n, 4 << 20):
        out.append(K.word_hashes(flat[at[i] : at[j - 1] + n[j - 1]], at[i:j] - at[i], at[i:j] - at[i] + n[i:j]))
    return np.concatenate(out)


def _equal(flat: np.ndarray, at: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Whether each string equals the one before it, byte by byte."""
    same = n[1:] == n[:-1]
    i = np.flatnonzero(same)
    a, b, k = at[1:][i], at[:-1][i], n[1:][i]
    differ = np.zeros(len(i), dtype=np.int64)
    if len(i):
        first = np.cumsum(k) - k
        ne = _gather(flat, a, k) != _gather(flat, b, k)
        differ = np.add.reduceat(ne, first) if len(k) else differ
    same[i] = differ == 0
    return same


def sort_owner(t: pa.Table, length: int) -> pa.Table:
    """(chunk, body) rows: of each answered window run its text's row, its place and one bit per window that a smaller document has."""
    if t["bucket"][0].as_py() < 0:
        return t.select(["bucket", "chunk", "body"])
    t = t.sort_by([("chunk", "ascending")])
    parts = [K.unsqueeze(x) for x in t["body"].to_pylist()]
    n = np.concatenate([p[0] for p in parts]).astype(np.int64)
    who = np.concatenate([p[1] for p in parts])
    flat = np.concatenate([p[6] for p in parts])
    at = np.cumsum(n) - n
    # the same surroundings from several chunks are sorted once, for the smallest document
    ctx = _hashes(flat, at, n)
    o = np.lexsort((who, ctx))
    new = np.append(True, (ctx[o][1:] != ctx[o][:-1]) | ~_equal(flat, at[o], n[o]))
    of = np.empty(len(o), dtype=np.int64)
    of[o] = np.cumsum(new) - 1
    least_here = who[o[new]][of]
    later = who > least_here
    bits, full = _window_bits(flat, at[o[new]], n[o[new]], who[o[new]], length)
    bits, full = bits[of], full[of]
    bits[later] = full[later]
    rows, base = [], 0
    for p, chunk in zip(parts, t["chunk"].to_pylist(), strict=True):
        g = p[2].astype(np.int64) + base
        mask = np.where(p[3] > 0, bits[g], full[g])
        has = mask > 0
        if has.any():
            rows.append((0, chunk, K.squeeze(p[4][has], p[5][has], mask[has])))
        base += len(p[0])
    return census.blob_rows(rows)


def _window_bits(flat: np.ndarray, at: np.ndarray, n: np.ndarray, who: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """For each piece of ``flat``: bits of its windows that a piece of a smaller document has too, and all its windows' bits."""
    wins = n - length + 1
    first = np.cumsum(wins) - wins
    ctx = np.repeat(np.arange(len(n)), wins)
    k = np.arange(int(wins.sum())) - first[ctx]
    starts = at[ctx] + k
    order, cls = sort_strings(np.concatenate([flat, np.zeros(8, np.uint8)]), starts, length)
    owner = who[ctx[order]]
    edge = np.flatnonzero(np.append(True, cls[1:] != cls[:-1]))
    least = np.minimum.reduceat(owner, edge)[cls]
    repeats = np.zeros(len(starts), dtype=bool)
    repeats[order] = least < owner
    bits = np.bitwise_or.reduceat(np.where(repeats, np.uint64(1) << k.astype(np.uint64), np.uint64(0)), first)
    full = (np.uint64(2) << (wins - 1).astype(np.uint64)) - np.uint64(1)
    return bits, full


def cut(t: pa.Table, told: pa.Table, length: int, with_text: bool) -> pa.Table:
    data, starts, ends = K.as_bytes(t["text"])
    base = int(starts[0]) if len(starts) else 0
    edge = np.zeros((int(ends[-1]) - base if len(ends) else 0) + 1, dtype=np.int32)
    for body in told["body"].to_pylist():
        doc, *rest = K.unsqueeze(body)
        if not rest:  # later copies of whole texts
            doc = doc.astype(np.int64)
            doc = doc[ends[doc] - starts[doc] >= length]
            np.add.at(edge, starts[doc] - base, 1)
            np.add.at(edge, ends[doc] - base, -1)
            continue
        lo, mask = rest
        first = starts[doc.astype(np.int64)] + lo.astype(np.int64) - base
        for k in range(int(mask.max()).bit_length()):
            s = first[(mask >> np.uint64(k)) & np.uint64(1) > 0] + k
            np.add.at(edge, s, 1)
            np.add.at(edge, s + length, -1)
    gone = np.cumsum(edge[:-1]) > 0
    total = np.concatenate([[0], np.cumsum(gone)])
    raw, rows = data, []
    for i, (a, z) in enumerate(zip(starts.tolist(), ends.tolist(), strict=True)):
        n = int(total[z - base] - total[a - base])
        if n:
            g = gone[a - base : z - base]
            spans = int(np.count_nonzero(g[1:] & ~g[:-1])) + int(g[0])
            kept = raw[a:z][~g].tobytes()
        else:
            spans, kept = 0, raw[a:z].tobytes()
        rows.append((z - a, n, spans, kept if with_text else None, hashlib.sha256(kept).hexdigest()))
    cols = list(zip(*rows, strict=True)) if rows else [()] * 5
    ids = pa.array([None if x == NO_ID else x for x in t["doc_id"].to_pylist()], pa.int64())
    kinds = (pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.string())
    names = [c.split()[0] for c in SCHEMA.split(", ")]
    return pa.table([ids, *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))], names=names)


def remove_repeats(spark: SparkSession, df: DataFrame, length: int = 50, gram: int = 16, id_col: str = "doc_id", text_col: str = "text", with_text: bool = True) -> DataFrame:
    """One row per document, as ``SCHEMA`` says; ``kept`` (bytes) is null unless ``with_text``."""
    if not 8 <= gram < length <= gram + 63:
        raise ValueError("8 <= gram < length <= gram + 63 is needed")
    ship(spark)
    docs = ids_and_texts(df, id_col, text_col)
    size, buckets = census.sizes(total := text_bytes(docs), (length - gram + 2) / 2)
    chunks, _, _ = chunked(spark, docs, size, total)

    def anchors_of(key: tuple, t: pa.Table) -> pa.Table:
        return send_anchors(key[0].as_py(), t, buckets, length, gram)

    def contexts_of(key: tuple, t: pa.Table, told: pa.Table) -> pa.Table:
        return send_contexts(key[0].as_py(), _sorted(t), told, buckets, length, gram)

    def rest_of(t: pa.Table, told: pa.Table) -> pa.Table:
        return cut(_sorted(t), told, length, with_text)

    told = chunks.groupBy("chunk").applyInArrow(anchors_of, census.BLOB).groupBy("bucket").applyInArrow(lambda t: answer_all(t, buckets), census.BLOB)
    contexts = chunks.groupBy("chunk").cogroup(told.groupBy("chunk")).applyInArrow(contexts_of, census.BLOB)
    repeats = contexts.groupBy("bucket").applyInArrow(lambda t: sort_owner(t, length), census.BLOB)
    repeats = staged(spark, repeats, "repeats")
    return chunks.groupBy("chunk").cogroup(repeats.groupBy("chunk")).applyInArrow(rest_of, SCHEMA)
