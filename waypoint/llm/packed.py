"""Whole columns of texts as one byte buffer, and hashing over it without a Python loop per word.

Every function here works on UTF-8 bytes. A null text is an empty one.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U64 = np.uint64
BASE = 0x9E3779B97F4A7C15 | 1
INVERSE = pow(BASE, -1, 1 << 64)
#: Bytes handled at a time, so that the 8-byte lanes of one step stay in a core's cache.
STEP = 1 << 17

_space = np.zeros(256, dtype=bool)
_space[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
_lower = np.arange(256, dtype=np.uint8)
_lower[65:91] += 32
_powers: dict[int, np.ndarray] = {}


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values."""
    x = x ^ (x >> U64(32))
    x *= U64(0xD6E8FEB86659FD93)
    x ^= x >> U64(29)
    x *= U64(0xC2B2AE3D27D4EB4F)
    x ^= x >> U64(32)
    return x


def scalar_mixed(x: int) -> int:
    return int(mixed(np.array([x & 0xFFFFFFFFFFFFFFFF], dtype=U64))[0])


_letters = mixed(np.arange(1, 257, dtype=U64))


def powers(base: int, n: int) -> np.ndarray:
    """1, base, base^2 ... modulo 2^64, at least n of them; the table grows when a longer text comes."""
    have = _powers.get(base)
    if have is None or len(have) < n:
        size = max(n, STEP + (STEP >> 2))
        have = np.ones(size, dtype=U64)
        have[1:] = U64(base)
        np.multiply.accumulate(have, out=have)
        _powers[base] = have
    return have[:n]


def texts(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of all texts one after another, and where each begins (one more entry than texts)."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_binary()) if not pa.types.is_large_binary(column.type) else column
    if column.null_count:
        column = column.fill_null(b"")
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, dtype=np.uint8)[off[0] : off[-1]] if data is not None else np.zeros(0, np.uint8)
    return raw, off - off[0]


def pieces(off: np.ndarray, step: int = STEP) -> Iterator[tuple[int, int]]:
    """Consecutive runs of texts of about ``step`` bytes; a longer text is a run of its own."""
    i, n = 0, len(off) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(off, off[i] + step, "right")) - 1)
        yield i, min(j, n)
        i = min(j, n)


def prefix_hash(raw: np.ndarray) -> np.ndarray:
    """Running polynomial sums: the hash of [s, e) is (P[e] - P[s]) times the inverse power of s."""
    out = np.zeros(len(raw) + 1, dtype=U64)
    np.cumsum(_letters[raw] * powers(BASE, len(raw)), out=out[1:])
    return out


def span_hash(prefix: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of byte spans; equal strings have equal hashes, whatever their place."""
    inv = powers(INVERSE, len(prefix))
    return mixed((prefix[ends] - prefix[starts]) * inv[starts] + (ends - starts).astype(U64))


def words(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end and text number of every word ``[^\\x20\\x09-\\x0D]+``; none crosses texts."""
    ink = ~_space[raw]
    n = len(raw)
    edge = np.zeros(n + 1, dtype=bool)
    edge[off] = True
    before = np.zeros(n, dtype=bool)
    before[1:] = ink[:-1]
    starts = np.flatnonzero(ink & (~before | edge[:-1]))
    after = np.zeros(n, dtype=bool)
    after[:-1] = ink[1:]
    ends = np.flatnonzero(ink & (~after | edge[1:])) + 1
    return starts, ends, np.searchsorted(off, starts, "right") - 1


def lowered(raw: np.ndarray) -> np.ndarray:
    """A-Z lower-cased, all other bytes as they are."""
    return _lower[raw]


def gram_hashes(prefix: np.ndarray, n: int) -> np.ndarray:
    """:func:`span_hash` of every span of n bytes."""
    m = len(prefix) - n
    out = prefix[n:] - prefix[:m]
    out *= powers(INVERSE, m)
    out += U64(n)
    return mixed(out)


def word_hashes(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash and text number of every lower-cased word."""
    s, e, doc = words(raw, off)
    return span_hash(prefix_hash(lowered(raw)), s, e), doc


def shingles(h: np.ndarray, doc: np.ndarray, n_texts: int, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct k-word shingles of each text: hashes sorted within the text, and where each text's begin.

    A text of fewer than k words has its whole sequence as one shingle; one without words has none.
    """
    count = np.bincount(doc, minlength=n_texts) if len(doc) else np.zeros(n_texts, dtype=np.int64)
    first = np.concatenate([[0], np.cumsum(count)])
    parts, owners = [], []
    if len(h) >= k:
        m = len(h) - k + 1
        s = np.zeros(m, dtype=U64)
        for j in range(k):
            s += h[j : j + m] * U64((BASE * (2 * j + 3)) & 0xFFFFFFFFFFFFFFFF)
            s = mixed(s)
        good = doc[:m] == doc[k - 1 :]
        parts.append(s[good])
        owners.append(doc[:m][good])
    for t in np.flatnonzero((count > 0) & (count < k)):
        v = int(count[t])
        for x in h[first[t] : first[t + 1]]:
            v = scalar_mixed(v * BASE + int(x))
        parts.append(np.array([v], dtype=U64))
        owners.append(np.array([t]))
    if not parts:
        return np.zeros(0, dtype=U64), np.zeros(n_texts + 1, dtype=np.int64)
    s, o = np.concatenate(parts), np.concatenate(owners)
    order = np.lexsort((s, o))
    s, o = s[order], o[order]
    new = np.ones(len(s), dtype=bool)
    new[1:] = (s[1:] != s[:-1]) | (o[1:] != o[:-1])
    s, o = s[new], o[new]
    return s, np.concatenate([[0], np.cumsum(np.bincount(o, minlength=n_texts))]).astype(np.int64)
