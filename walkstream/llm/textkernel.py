"""Vectorised text kernels: word splitting, 64-bit word hashes and trie matching over whole Arrow batches.

A batch of texts is one UTF-8 byte buffer with offsets. Words are found with byte tables, hashed by a position-weighted
sum modulo 2^64 (two different words of a batch collide with a chance of about 2^-64 per pair) and reduced to the distinct
ones; costly work is then done once per distinct word of the batch. All working memory is bounded by the batch.
"""

from __future__ import annotations

import functools

import numpy as np
import pandas as pd
import pyarrow as pa

from .common import SPACE_BYTES

_U = np.uint64
#: Multipliers of the hash; odd, so that they can be inverted modulo 2^64 (fixed values).
_BASE = 0x9E3779B97F4A7C15
_STEP = 1 << 17


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, dtype=_U)
    out[0] = 1
    return np.multiply.accumulate(out)


_cache: dict = {}


def _tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    have = _cache.get("pow")
    if have is None or len(have[0]) < n:
        n = max(n, _STEP + (1 << 16))
        _cache["pow"] = have = (_powers(_BASE, n), _powers(pow(_BASE, -1, 1 << 64), n))
    return have


def byte_values(lower: bool) -> np.ndarray:
    """A random 64-bit value for each byte; A-Z take those of a-z if `lower`."""
    out = np.random.default_rng(20240501).integers(1, 1 << 63, size=256, dtype=_U)
    if lower:
        out[65:91] = out[97:123]
    return out


SPACES = np.zeros(256, dtype=bool)
SPACES[list(SPACE_BYTES)] = True


def mix(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> _U(32))
    h = h * _U(0xD6E8FEB86659FD93)
    h ^= h >> _U(32)
    h *= _U(0xD6E8FEB86659FD93)
    h ^= h >> _U(32)
    return h


def text_buffer(column) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of an Arrow or pandas string column; null counts as empty."""
    arr = column if isinstance(column, (pa.Array, pa.ChunkedArray)) else pa.array(column, type=pa.large_string(), from_pandas=True)
    if isinstance(arr, pa.ChunkedArray):
        arr = arr.combine_chunks()
    arr = arr.cast(pa.large_string()).fill_null("")
    if len(arr) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(arr.buffers()[1], dtype=np.int64)[arr.offset : arr.offset + len(arr) + 1]
    data = arr.buffers()[2]
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def split_words(buf: np.ndarray, offsets: np.ndarray, sep: np.ndarray = SPACES) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, length, index of the text) of every maximal run of other bytes than `sep`, in order."""
    if not len(buf):
        z = np.zeros(0, np.int64)
        return z, z, z
    word = ~sep[buf]
    first = np.zeros(len(buf) + 1, dtype=bool)
    first[offsets] = True
    edge = word.copy()
    edge[1:] &= ~word[:-1] | first[1:-1]
    starts = np.flatnonzero(edge)
    edge = word.copy()
    edge[:-1] &= ~word[1:] | first[1:-1]
    ends = np.flatnonzero(edge) + 1
    return starts, ends - starts, np.searchsorted(offsets, starts, side="right") - 1


def hash_spans(buf: np.ndarray, start: np.ndarray, length: np.ndarray, values: np.ndarray) -> np.ndarray:
    """64-bit hash of each span; spans are in order and don't overlap. Works through about `_STEP` bytes at a time."""
    out = np.empty(len(start), dtype=_U)
    at = 0
    while at < len(start):
        to = max(at + 1, int(np.searchsorted(start, start[at] + _STEP)))
        lo, hi = int(start[at]), int(start[to - 1] + length[to - 1])
        power, inverse = _tables(hi - lo + 1)
        run = np.zeros(hi - lo + 1, dtype=_U)
        np.cumsum(values[buf[lo:hi]] * power[: hi - lo], out=run[1:])
        s = start[at:to] - lo
        out[at:to] = (run[s + length[at:to]] - run[s]) * inverse[s] + length[at:to].astype(_U)
        at = to
    return mix(out)


def distinct(hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(code of each item, index of one item per code)."""
    codes, uniques = pd.factorize(hashes)
    rep = np.empty(len(uniques), dtype=np.int64)
    rep[codes[::-1]] = np.arange(len(codes) - 1, -1, -1)
    return codes, rep


def gather_spans(buf: np.ndarray, start: np.ndarray, length: np.ndarray, prefix: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Copies of the spans in one buffer, each after the byte `prefix` if given: (bytes, offsets)."""
    extra = prefix is not None
    size = length + extra
    offsets = np.zeros(len(start) + 1, dtype=np.int64)
    np.cumsum(size, out=offsets[1:])
    pos = np.arange(offsets[-1], dtype=np.int64) - np.repeat(offsets[:-1] - start + extra, size)
    if extra:
        pos[offsets[:-1]] = 0
        out = buf[pos] if len(buf) else np.zeros(len(pos), np.uint8)
        out[offsets[:-1]] = prefix
        return out, offsets
    return buf[pos], offsets


class Trie:
    """Byte trie of a vocabulary. Nodes with children come first, so that the transition table stays small."""

    def __init__(self, pieces: list[bytes], ids: list[int]):
        children: list[dict[int, int]] = [{}]
        piece = [-1]
        for text, i in zip(pieces, ids, strict=True):
            node = 0
            for b in text:
                nxt = children[node].get(b)
                if nxt is None:
                    nxt = children[node][b] = len(children)
                    children.append({})
                    piece.append(-1)
                node = nxt
            if node and piece[node] < 0:
                piece[node] = i
        order = [n for n, c in enumerate(children) if c or not n] + [n for n, c in enumerate(children) if not c and n]
        number = {n: k for k, n in enumerate(order)}
        self.inner = sum(1 for n, c in enumerate(children) if c or not n)
        self.size = len(children)
        self.piece = np.array([piece[n] for n in order], dtype=np.int32)
        self.child = np.full((self.inner, 256), -1, dtype=np.int32)
        for n in order[: self.inner]:
            for b, c in children[n].items():
                self.child[number[n], b] = number[c]
        self.depth = max((len(p) for p in pieces), default=0)

    def matches(self, buf: np.ndarray, end: np.ndarray, start: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """All (position, length, piece id) with a piece of the vocabulary at the position that stays before end[position].

        `start` limits the positions looked at.
        """
        pos = np.arange(len(buf), dtype=np.int64) if start is None else start
        node = np.zeros(len(pos), dtype=np.int32)
        got: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        step = 0
        while len(pos):
            live = (node < self.inner) & (pos + step < end[pos])
            pos, node = pos[live], node[live]
            if not len(pos):
                break
            node = self.child[node, buf[pos + step]]
            live = node >= 0
            pos, node = pos[live], node[live]
            step += 1
            hit = self.piece[node] >= 0
            if hit.any():
                got.append((pos[hit], np.full(int(hit.sum()), step, dtype=np.int32), self.piece[node[hit]]))
        if not got:
            return np.zeros(0, np.int64), np.zeros(0, np.int32), np.zeros(0, np.int32)
        return tuple(np.concatenate(x) for x in zip(*got, strict=True))  # type: ignore[return-value]


def word_blocks(offsets: np.ndarray, most: int = 1 << 20):
    """Ranges of words with about `most` bytes each."""
    at, n = 0, len(offsets) - 1
    while at < n:
        to = min(n, max(at + 1, int(np.searchsorted(offsets, offsets[at] + most, side="right")) - 1))
        yield at, to
        at = to


def slices(size: pd.Series, most: int = 1 << 20):
    """Slices of rows with about `most` each, by their sizes."""
    ends = np.cumsum(size.to_numpy(dtype=np.int64))
    at = 0
    while at < len(size):
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + most, side="right")))
        yield slice(at, to)
        at = to


def give_back() -> None:
    """Return freed memory to the system, so that a reused worker doesn't keep its largest batch."""
    import ctypes

    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


_kept: list = []


def keep_last(build):
    """A cache of the last value made in a worker, which `forget` empties."""
    kept = functools.lru_cache(maxsize=1)(build)
    _kept.append(kept)
    return kept


def forget() -> None:
    """Drop what earlier operators kept in a reused worker (tries, encoders), for operators that need none of it."""
    for kept in _kept:
        kept.cache_clear()
    _cache.clear()
    give_back()
