"""Vectorised byte kernels shared by the operators of this package.

Every kernel works on one contiguous ``uint8`` buffer that holds many texts, so
the cost is a few numpy passes over the bytes and not a Python loop over words.
Texts are UTF-8; lower-casing touches A-Z only.
"""

from __future__ import annotations

import ctypes

import numpy as np
import pyarrow as pa

U64 = np.uint64
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
#: bytes of words separated by the six ASCII blanks
NONBLANK = np.ones(256, dtype=bool)
NONBLANK[[32, 9, 10, 11, 12, 13]] = False
#: bytes of words made of digits, letters and everything outside ASCII (after LOWER)
ALNUM = np.zeros(256, dtype=bool)
ALNUM[48:58] = ALNUM[97:123] = ALNUM[128:] = True



def trim() -> None:
    """Gives freed memory back to the system: a worker lives for many tasks, and its peak must not stay."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):
        pass


_BASE = 0x9E3779B97F4A7C15 | 1
_BASE_INV = pow(_BASE, -1, 1 << 64)
_powers: dict[int, np.ndarray] = {}


def _power(base: int, n: int) -> np.ndarray:
    have = _powers.get(base)
    if have is None or len(have) < n:
        size = 1 << max(12, int(n - 1).bit_length())
        have = np.full(size, base, dtype=U64)
        have[0] = 1
        np.multiply.accumulate(have, out=have)
        _powers[base] = have
    return have[:n]


def mix(h: np.ndarray) -> np.ndarray:
    """Finaliser of a 64-bit hash (in a new array)."""
    h = h ^ (h >> U64(32))
    h *= U64(0xD6E8FEB86659FD93)
    h ^= h >> U64(32)
    h *= U64(0xD6E8FEB86659FD93)
    h ^= h >> U64(32)
    return h


def one(col) -> pa.Array:
    if isinstance(col, pa.ChunkedArray):
        return col.chunk(0) if col.num_chunks == 1 else pa.concat_arrays(col.chunks) if col.num_chunks else pa.array([], col.type)
    return col


def as_bytes(col) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bytes, starts, ends) of a string or binary column without nulls; no copy."""
    arr = one(col)
    wide = pa.types.is_large_string(arr.type) or pa.types.is_large_binary(arr.type)
    _, off, data = arr.buffers()
    if not len(arr) or off is None:
        z = np.zeros(0, dtype=np.int64)
        return np.zeros(0, dtype=np.uint8), z, z
    off = np.frombuffer(off, dtype=np.int64 if wide else np.int32)[arr.offset : arr.offset + len(arr) + 1].astype(np.int64)
    data = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, dtype=np.uint8)
    return data, off[:-1], off[1:]


def blocks(starts: np.ndarray, ends: np.ndarray, size: int = 1 << 20):
    """Consecutive (first, last) ranges of texts of about ``size`` bytes; a longer text is a block of its own."""
    i, n = 0, len(starts)
    while i < n:
        j = max(i + 1, int(np.searchsorted(ends, starts[i] + size, side="right")))
        yield i, min(j, n)
        i = min(j, n)


def spaced(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """A copy of consecutive texts with one blank after each, so that words never cross texts."""
    if not len(starts):
        return np.zeros(0, dtype=np.uint8), starts, ends
    base, k = starts[0], np.arange(len(starts))
    return np.insert(data[base : ends[-1]], ends - base, 32), starts - base + k, ends - base + k


def word_spans(buf: np.ndarray, inside: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Start and end of each maximal run of bytes for which ``inside`` holds."""
    m = np.zeros(len(buf) + 2, dtype=np.int8)
    m[1:-1] = inside[buf]
    d = np.diff(m)
    return np.flatnonzero(d == 1), np.flatnonzero(d == -1)


def word_hashes(buf: np.ndarray, ws: np.ndarray, we: np.ndarray) -> np.ndarray:
    """64-bit hash of each span; a function of the span's bytes only."""
    if not len(ws):
        return np.zeros(0, dtype=U64)
    n = len(buf)
    c = np.zeros(n + 1, dtype=U64)
    np.cumsum((buf.astype(U64) + U64(1)) * _power(_BASE, n), out=c[1:])
    return mix((c[we] - c[ws]) * _power(_BASE_INV, n)[ws] + (we - ws).astype(U64) * U64(0xA24BAED4963EE407))


def hash_text(s: bytes) -> int:
    """word_hashes() of one word."""
    buf = np.frombuffer(s, dtype=np.uint8)
    return int(word_hashes(buf, np.array([0]), np.array([len(buf)]))[0])


_STEP = [U64(pow(0xC2B2AE3D27D4EB4F, j, 1 << 64)) for j in range(16)]


def shingle_hashes(words: np.ndarray, n: int) -> np.ndarray:
    """Hashes of the n-word shingles of one word-hash sequence; a shorter sequence is one shingle; none gives none."""
    if not len(words):
        return np.zeros(0, dtype=U64)
    if len(words) < n:
        h = (words * _power(0xC2B2AE3D27D4EB4F, len(words))).sum(dtype=U64)
        return mix(np.array([h + U64(len(words))], dtype=U64))
    m = len(words) - n + 1
    h = np.full(m, n, dtype=U64)
    for j in range(n):
        h += words[j : j + m] * _STEP[j]
    return mix(h)


def eights(buf: np.ndarray) -> np.ndarray:
    """For each position, the next eight bytes as one big-endian number (zero beyond the end)."""
    b = np.zeros(len(buf) + 8, dtype=U64)
    b[: len(buf)] = buf
    b = (b[:-1] << U64(8)) | b[1:]
    b = (b[:-2] << U64(16)) | b[2:]
    b = (b[:-4] << U64(32)) | b[4:]
    return b[: len(buf)]


def squeeze(*arrays: np.ndarray) -> bytes:
    """Arrays as one compressed body: count, then dtype, length and bytes of each (byte planes of sorted deltas compress well)."""
    import zstandard

    head, parts = [], []
    for a in arrays:
        raw = np.ascontiguousarray(a)
        size = raw.dtype.itemsize
        planes = raw.view(np.uint8).reshape(-1, size).T.tobytes() if size > 1 and len(raw) else raw.tobytes()
        head.append(f"{raw.dtype.str}:{len(raw)}")
        parts.append(planes)
    h = ",".join(head).encode()
    return zstandard.ZstdCompressor(level=1).compress(len(h).to_bytes(4, "little") + h + b"".join(parts))


def unsqueeze(body: bytes) -> list[np.ndarray]:
    import zstandard

    raw = zstandard.ZstdDecompressor().decompress(body)
    n = int.from_bytes(raw[:4], "little")
    at, out = 4 + n, []
    for item in raw[4:at].decode().split(","):
        kind, count = item.rsplit(":", 1)
        dt, count = np.dtype(kind), int(count)
        size = dt.itemsize * count
        piece = np.frombuffer(raw, dtype=np.uint8, count=size, offset=at)
        out.append(np.ascontiguousarray(piece.reshape(dt.itemsize, count).T).view(dt).ravel() if dt.itemsize > 1 and count else piece.view(dt))
        at += size
    return out


def deltas(sorted_keys: np.ndarray) -> np.ndarray:
    return np.diff(sorted_keys, prepend=sorted_keys.dtype.type(0))


def undelta(d: np.ndarray) -> np.ndarray:
    return np.cumsum(d, dtype=d.dtype)
