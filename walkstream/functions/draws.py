"""The portable draws of `rng` on arrays: the same md5 digits, many at once, for walks made inside a task."""

from __future__ import annotations

import hashlib
import math

import numpy as np

#: Messages are hashed in groups of so many, which stay in a core's cache; fewer than FEW go to hashlib one by one.
GROUP, FEW = 1 << 15, 1024
#: Longest message of one md5 block.
LONGEST = 55
_SINES = [int(abs(math.sin(i + 1)) * 2**32) for i in range(64)]
_TURNS = [[7, 12, 17, 22], [5, 9, 14, 20], [4, 11, 16, 23], [6, 10, 15, 21]]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)


def _two_words(text: np.ndarray, length: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The first two words of the md5 of each row of `text` (n x 64 bytes, `length` used, then the byte 128, then zeros)."""
    n = len(text)
    used = (int(length.max()) + 4) // 4
    words = list(np.ascontiguousarray(text.view("<u4")[:, :used].T)) + [None] * (16 - used)
    words[14] = (length * 8).astype(np.uint32)
    a, b, c, d = (np.full(n, v, dtype=np.uint32) for v in _START)
    f, t = np.empty(n, dtype=np.uint32), np.empty(n, dtype=np.uint32)
    for i in range(64):
        part = i // 16
        if part == 0:
            np.bitwise_xor(c, d, out=f)
            np.bitwise_and(f, b, out=f)
            np.bitwise_xor(f, d, out=f)
        elif part == 1:
            np.bitwise_xor(b, c, out=f)
            np.bitwise_and(f, d, out=f)
            np.bitwise_xor(f, c, out=f)
        elif part == 2:
            np.bitwise_xor(b, c, out=f)
            np.bitwise_xor(f, d, out=f)
        else:
            np.invert(d, out=f)
            np.bitwise_or(f, b, out=f)
            np.bitwise_xor(f, c, out=f)
        word = words[(i, 5 * i + 1, 3 * i + 5, 7 * i)[part] % 16]
        np.add(a, f, out=f)
        np.add(f, np.uint32(_SINES[i]), out=f)
        if word is not None:
            np.add(f, word, out=f)
        turn = _TURNS[part][i % 4]
        np.left_shift(f, np.uint32(turn), out=t)
        np.right_shift(f, np.uint32(32 - turn), out=f)
        np.bitwise_or(f, t, out=f)
        np.add(f, b, out=f)
        a, b, c, d, f = d, f, b, c, a
    return a + np.uint32(_START[0]), b + np.uint32(_START[1])


class Texts:
    """Rows of the form purpose:key:key..., each closed by one more key or by nothing."""

    def __init__(self, seed: int, purpose: str, *keys: np.ndarray | int, room: int = 4):
        """room: characters that a last key will take, its colon included."""
        n = max(len(k) for k in keys if not np.isscalar(k))
        head = f"{seed}:{purpose}".encode()
        widest = len(head) + room + sum(1 + (len(str(k)) if np.isscalar(k) else max(len(str(k.max())), len(str(k.min())))) for k in keys)
        self.ok = widest <= LONGEST and all((k if np.isscalar(k) else k.min()) >= 0 for k in keys)
        if not self.ok:
            columns = [[k] * n if np.isscalar(k) else k.tolist() for k in keys]
            self.plain = [":".join([head.decode(), *map(str, row)]) for row in zip(*columns, strict=True)]
            return
        self.text = np.zeros((n, 64), dtype=np.uint8)
        self.text[:, : len(head)] = np.frombuffer(head, dtype=np.uint8)
        self.length = np.full(n, len(head), dtype=np.int64)
        for k in keys:
            self.length = self._write(self.length, k)

    def _write(self, at: np.ndarray, key: np.ndarray | int) -> np.ndarray:
        """A colon and the key's digits, from place `at` of each row on; the places behind them."""
        m = len(at)
        flat, base = self.text.reshape(-1), np.arange(m, dtype=np.int64) * 64 + at
        flat[base] = 58
        if np.isscalar(key):
            for j, c in enumerate(str(key).encode()):
                flat[base + (1 + j)] = c
            return at + 1 + len(str(key))
        v = key.astype(np.uint32 if key.max() < 1 << 32 else np.uint64)
        digits, bound = np.ones(m, dtype=np.int64), 10
        while bound <= int(v.max()):
            digits += v >= v.dtype.type(bound)
            bound *= 10
        ten, least = v.dtype.type(10), int(digits.min())
        for j in range(int(digits.max())):
            rest = v // ten
            digit = (v - rest * ten + 48).astype(np.uint8)
            if j < least:
                flat[base + digits - j] = digit
            else:
                k = np.flatnonzero(digits > j)
                flat[base[k] + digits[k] - j] = digit[k]
            v = rest
        return at + 1 + digits

    def u01(self, m: int, last: int | np.ndarray | None = None) -> np.ndarray:
        """Uniforms of the first m rows, with this key (the same for all, or one each) at their end."""
        if m == 0:
            return np.zeros(0)
        if not self.ok or m < FEW:
            return self._one_by_one(m, last)
        out = np.empty(m, dtype=np.float64)
        at = self.length[:m]
        end = at if last is None else self._write(at, last)
        rows = np.arange(m, dtype=np.int64) * 64 + end
        self.text.reshape(-1)[rows] = 128
        for lo in range(0, m, GROUP):
            q = slice(lo, min(m, lo + GROUP))
            a, b = _two_words(self.text[q], end[q])
            out[q] = (a.byteswap().astype(np.int64) << 20) | (b.byteswap() >> np.uint32(12)).astype(np.int64)
        width = int((end - at).max()) + 1
        for j in range(width):  # the rows end where they did
            self.text.reshape(-1)[np.arange(m, dtype=np.int64) * 64 + at + j] = 0
        return out / float(1 << 52)

    def _one_by_one(self, m: int, last) -> np.ndarray:
        heads = [s.encode() for s in self.plain[:m]] if not self.ok else [self.text[i, : self.length[i]].tobytes() for i in range(m)]
        ends = [b""] * m if last is None else [b":%d" % last] * m if np.isscalar(last) else [b":%d" % k for k in last.tolist()]
        return np.array([int(hashlib.md5(h + e).hexdigest()[:13], 16) for h, e in zip(heads, ends, strict=True)], dtype=np.float64) / float(1 << 52)
