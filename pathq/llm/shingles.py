"""Word shingles of whole UTF-8 texts as 64-bit hashes, vectorised over a batch of documents."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

SEGMENT = 1 << 20  # bytes hashed at a time
_rng = np.random.default_rng(20240607)
_BYTE = _rng.integers(0, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_ODD = _rng.integers(0, 2**63, 64, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_BASE = 0x9E3779B97F4A7C15 | 1
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[32, 9, 10, 11, 12, 13]] = True
_POWERS: list[np.ndarray] = []


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd base and of its inverse modulo 2**64, at least n of each."""
    if not _POWERS or len(_POWERS[0]) < n:
        size = max(n, SEGMENT + 1)
        inverse = pow(_BASE, -1, 1 << 64)
        _POWERS[:] = []
        for base in (_BASE, inverse):
            out = np.full(size, base, dtype=np.uint64)
            out[0] = 1
            _POWERS.append(np.cumprod(out, dtype=np.uint64))
    return _POWERS[0], _POWERS[1]


def mix(h: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words that spreads every bit."""
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xFF51AFD7ED558CCD)
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(33))


def word_hashes(data: np.ndarray, breaks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(start, hash) of every word in ``data`` (bytes), lower-casing A-Z; no word crosses a position in ``breaks``."""
    n = len(data)
    if not n:
        return np.empty(0, np.int64), np.empty(0, np.uint64)
    data = _LOWER[data]
    solid = ~_SPACE[data]
    first, last = solid.copy(), solid.copy()
    first[1:] &= ~solid[:-1]
    last[:-1] &= ~solid[1:]
    inner = breaks[(breaks > 0) & (breaks < n)]
    first[inner] = solid[inner]
    last[inner - 1] = solid[inner - 1]
    starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
    up, down = _powers(n + 1)
    running = np.empty(n + 1, dtype=np.uint64)
    running[0] = 0
    np.cumsum(_BYTE[data] * up[:n], out=running[1:])
    h = (running[ends] - running[starts]) * down[starts]
    return starts, mix(h + (ends - starts).astype(np.uint64) * _ODD[0])


def _groups(column: pa.Array) -> Iterator[tuple[int, int]]:
    """Row ranges of about SEGMENT bytes."""
    offsets = np.frombuffer(column.buffers()[1], dtype=np.int32 if pa.types.is_string(column.type) else np.int64)[column.offset : column.offset + len(column) + 1]
    at = 0
    while at < len(column):
        to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + SEGMENT, "right")) - 1)
        yield at, min(to, len(column))
        at = min(to, len(column))


def _long_words(data: np.ndarray) -> np.ndarray:
    """Word hashes of one long text, segment by segment, cut at white space."""
    found, at, n = [], 0, len(data)
    while at < n:
        to = min(n, at + SEGMENT)
        while to < n:
            spaces = np.flatnonzero(_SPACE[data[at:to]])
            if len(spaces):
                to = at + int(spaces[-1]) + 1
                break
            to = min(n, at + 2 * (to - at))
        found.append(word_hashes(data[at:to], np.empty(0, np.int64))[1])
        at = to
    return np.concatenate(found) if found else np.empty(0, np.uint64)


def _shingle(words: np.ndarray, k: int) -> np.ndarray:
    """Hashes of all runs of k words; of the whole sequence, if it is shorter."""
    m = len(words)
    width = min(k, m)
    if not width:
        return words
    out = np.zeros(m - width + 1, dtype=np.uint64)
    for i in range(width):
        out += words[i : m - width + 1 + i] * _ODD[i + 1]
    return mix(out + np.uint64(width * int(_ODD[40]) % (1 << 64)))


def document_sets(column: pa.Array, k: int) -> Iterator[np.ndarray]:
    """For every text of an Arrow column, in order, the sorted distinct shingle hashes; empty for null texts."""
    if pa.types.is_string(column.type) is False and pa.types.is_large_string(column.type) is False:
        column = column.cast(pa.string())
    for at, to in _groups(column):
        part = column.slice(at, to - at)
        offsets = np.frombuffer(part.buffers()[1], dtype=np.int32 if pa.types.is_string(part.type) else np.int64)[part.offset : part.offset + len(part) + 1].astype(np.int64)
        body = part.buffers()[2]
        data = np.frombuffer(body, dtype=np.uint8)[offsets[0] : offsets[-1]] if body is not None else np.empty(0, np.uint8)
        local = offsets - offsets[0]
        valid = np.ones(len(part), bool) if part.null_count == 0 else part.is_valid().to_numpy(zero_copy_only=False)
        if len(part) == 1 and len(data) > SEGMENT:
            yield np.unique(_shingle(_long_words(data), k)) if valid[0] else np.empty(0, np.uint64)
            continue
        starts, hashes = word_hashes(data, local)
        edges = np.searchsorted(starts, local)
        for d in range(len(part)):
            words = hashes[edges[d] : edges[d + 1]]
            yield np.unique(_shingle(words, k)) if valid[d] and len(words) else np.empty(0, np.uint64)


def minhash(h: np.ndarray, t: int) -> np.ndarray:
    """t minwise values of 32 bits of a set of hashes."""
    a, b = minhash_parameters(t)
    out = np.full(t, 0xFFFFFFFF, dtype=np.uint32)
    short = ((h >> np.uint64(32)) ^ h).astype(np.uint32)
    for at in range(0, len(short), 512):
        np.minimum(out, (short[at : at + 512, None] * a + b).min(axis=0), out=out)
    return out


_PARAMETERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def minhash_parameters(t: int) -> tuple[np.ndarray, np.ndarray]:
    if t not in _PARAMETERS:
        rng = np.random.default_rng(977)
        _PARAMETERS[t] = (rng.integers(0, 2**31, t, dtype=np.uint32) * np.uint32(2) + np.uint32(1), rng.integers(0, 2**32, t, dtype=np.uint32))
    return _PARAMETERS[t]
