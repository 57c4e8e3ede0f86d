"""Vectorised work on whole batches of texts: word spans, hashes, windows.

Texts stay one UTF-8 buffer with offsets; words are maximal runs of bytes other
than the six ASCII blanks. A word stands as a 64-bit hash, so equality below is
equality of 64-bit hashes.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

#: Bytes hashed at once, so that the arrays fit a CPU cache.
PIECE = 1 << 18
#: Bytes of text handled at once, if a single text isn't longer.
SLICE = 1 << 20

BLANK = np.zeros(256, bool)
BLANK[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True

_rng = np.random.Generator(np.random.PCG64(20240101))
_BYTE = _rng.integers(1, 2**63, 256, dtype=np.uint64)
_BASE = 0x9E3779B97F4A7C15


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[0] = 1
    return np.cumprod(out, dtype=np.uint64)


_POW = _powers(_BASE, PIECE)
_INV = _powers(pow(_BASE, -1, 1 << 64), PIECE)


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def span_hashes(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Hash of each byte span; spans are in order and don't overlap."""
    out = np.empty(len(starts), np.uint64)
    i = 0
    while i < len(starts):
        base = int(starts[i])
        j = max(int(np.searchsorted(ends, base + PIECE, "right")), i + 1)
        if int(ends[i]) - base > PIECE:
            digest = hashlib.blake2b(buf[base : int(ends[i])].tobytes(), digest_size=8).digest()
            out[i] = int.from_bytes(digest, "little")
            i += 1
            continue
        seg = buf[base : int(ends[j - 1])]
        sums = np.empty(len(seg) + 1, np.uint64)
        sums[0] = 0
        np.cumsum(_BYTE[seg] * _POW[: len(seg)], out=sums[1:])
        s, e = starts[i:j] - base, ends[i:j] - base
        inv = _INV[np.minimum(s, PIECE - 1)]
        out[i:j] = mix((sums[e] - sums[s]) * inv + (e - s).astype(np.uint64))
        i = j
    return out


@dataclass
class Slice:
    """Some whole texts: rows first..last of the batch, their bytes and offsets."""

    first: int
    last: int
    buf: np.ndarray
    offsets: np.ndarray

    @property
    def n(self) -> int:
        return self.last - self.first


def slices(texts: pa.Array | pa.ChunkedArray, limit: int = SLICE) -> Iterator[Slice]:
    """Cut a column of texts into slices of about `limit` bytes; null counts as empty."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    texts = texts.fill_null("").cast(pa.large_string())
    n = len(texts)
    if not n:
        return
    _, offs, data = texts.buffers()
    offsets = np.frombuffer(offs, np.int64, n + 1, texts.offset * 8)
    whole = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    i = 0
    while i < n:
        j = min(n, max(i + 1, int(np.searchsorted(offsets, offsets[i] + limit, "right")) - 1))
        yield Slice(i, j, whole[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])
        i = j


@dataclass
class Words:
    start: np.ndarray
    end: np.ndarray
    doc: np.ndarray
    #: Of each text, its first word; one more at the end.
    first: np.ndarray
    hash: np.ndarray


def words_of(s: Slice) -> Words:
    solid = ~BLANK[s.buf]
    edge = np.zeros(len(s.buf) + 1, bool)
    edge[s.offsets[:-1]] = True
    opens = solid.copy()
    opens[1:] &= ~solid[:-1] | edge[1:-1]
    closes = solid.copy()
    closes[:-1] &= ~solid[1:] | edge[1:-1]
    start, end = np.flatnonzero(opens), np.flatnonzero(closes) + 1
    first = np.searchsorted(start, s.offsets)
    doc = np.repeat(np.arange(s.n), np.diff(first))
    return Words(start, end, doc, first, span_hashes(s.buf, start, end))


def windows(w: Words, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all windows of n words inside one text, and their first words."""
    count = len(w.hash) - n + 1
    if count <= 0:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    acc = w.hash[:count].copy()
    for k in range(1, n):
        acc *= np.uint64(0xD6E8FEB86659FD93)
        acc += w.hash[k : k + count]
    at = np.flatnonzero(w.doc[:count] == w.doc[n - 1 :])
    return mix(acc[at]), at


def repeated(keys: np.ndarray) -> np.ndarray:
    """Which keys occur twice or more."""
    if len(keys) < 2:
        return np.zeros(len(keys), bool)
    order = np.argsort(keys)
    k = keys[order]
    same = k[1:] == k[:-1]
    hit = np.zeros(len(k), bool)
    hit[1:] |= same
    hit[:-1] |= same
    out = np.zeros(len(k), bool)
    out[order] = hit
    return out


def per_doc(mask: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Sum of a mask over each of the ranges between offsets."""
    sums = np.zeros(len(mask) + 1, np.int64)
    np.cumsum(mask, out=sums[1:])
    return sums[offsets[1:]] - sums[offsets[:-1]]


_BYTES = (_BYTE, _rng.integers(1, 2**63, 256, dtype=np.uint64))
_BASES = (_BASE, 0xC2B2AE3D27D4EB4F)
_POWS = (_POW, _powers(_BASES[1], PIECE))
_INVS = (_INV, _powers(pow(_BASES[1], -1, 1 << 64), PIECE))


def rolling(buf: np.ndarray, k: int, which: int = 0) -> np.ndarray:
    """Hash of every k bytes in a row; which chooses one of two independent hashes."""
    n = len(buf) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = np.empty(n, np.uint64)
    step = PIECE - k
    for a in range(0, n, step):
        m = min(step, n - a)
        seg = buf[a : a + m + k - 1]
        sums = np.empty(len(seg) + 1, np.uint64)
        sums[0] = 0
        np.cumsum(_BYTES[which][seg] * _POWS[which][: len(seg)], out=sums[1:])
        out[a : a + m] = mix((sums[k : k + m] - sums[:m]) * _INVS[which][:m])
    return out


def sliding_min(x: np.ndarray, w: int) -> np.ndarray:
    """Minimum of every w values in a row."""
    n = len(x) - w + 1
    if n <= 0:
        return x[:0]
    rows = -(-len(x) // w)
    full = np.full(rows * w, np.iinfo(x.dtype).max, x.dtype)
    full[: len(x)] = x
    full = full.reshape(rows, w)
    ahead = np.minimum.accumulate(full, axis=1).ravel()
    back = np.minimum.accumulate(full[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(back[:n], ahead[w - 1 : w - 1 + n])


def stretch_hashes(buf: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Hash of each of these short byte stretches; starts ascend, stretches may overlap."""
    out = np.empty(len(starts), np.uint64)
    most = int(lengths.max()) if len(lengths) else 0
    i = 0
    while i < len(starts):
        base = int(starts[i])
        j = max(int(np.searchsorted(starts, base + PIECE - most, "right")), i + 1)
        s, n = starts[i:j] - base, lengths[i:j]
        seg = buf[base : base + int((s + n).max())]
        sums = np.empty(len(seg) + 1, np.uint64)
        sums[0] = 0
        np.cumsum(_BYTE[seg] * _POW[: len(seg)], out=sums[1:])
        out[i:j] = mix((sums[s + n] - sums[s]) * _INV[s] + n.astype(np.uint64))
        i = j
    return out
