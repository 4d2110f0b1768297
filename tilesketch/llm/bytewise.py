"""Vectorised text kernels over Arrow's byte buffers: words, lines, shingles and 64-bit hashes without per-word Python.

A block of texts is one byte array with offsets.  A byte range's hash is a polynomial over its bytes modulo the prime
2^61 - 1, finished with a 64-bit mixer: two ranges of at most n bytes that differ have equal hashes for at most n of the
2^61 bases.  (Modulo a power of two there are short texts that collide for every base.)  A word never crosses the end of
its text.  Tables of powers have the size of a chunk, however long a text is.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U = np.uint64
PRIME = (1 << 61) - 1
_P, _LOW = U(PRIME), U((1 << 31) - 1)
_BASE, _TURN = 0x0F3779B97F4A7C15, 0xD6E8FEB86659FD93 | 1
CHUNK, STEP = 1 << 20, 1 << 14  # bytes that share a table of powers; numbers that are worked on at a time
_powers: dict[int, np.ndarray] = {}
_malloc_trim = getattr(ctypes.CDLL(None), "malloc_trim", None)


def trim() -> None:
    """Give free memory of this process back to the system: a worker outlives its stage and else holds its peak."""
    pa.default_memory_pool().release_unused()
    if _malloc_trim is not None:
        _malloc_trim(0)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit mixer (xor-shift-multiply)."""
    x = x ^ (x >> U(32))
    x *= U(0xD6E8FEB86659FD93)
    x ^= x >> U(32)
    x *= U(0xD6E8FEB86659FD93)
    x ^= x >> U(32)
    return x


LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
SPACE = np.zeros(256, bool)
SPACE[[32, *range(9, 14)]] = True
LETTER = np.zeros(256, bool)
LETTER[65:91] = LETTER[97:123] = LETTER[128:] = True


def _part(x: np.ndarray) -> np.ndarray:
    """Any 64-bit numbers to congruent ones below 2^61 + 8."""
    out = x >> U(61)
    out += x & _P
    return out


def _fold(x: np.ndarray) -> np.ndarray:
    """Any 64-bit numbers modulo the prime."""
    out = _part(x)
    out -= (out >= _P) * _P
    return out


def _raised(x: np.ndarray) -> np.ndarray:
    """Numbers below 2^61 + 8 times 2^31, congruent and below 2^62."""
    out = x << U(31)
    out &= _P
    out += x >> U(30)
    return out


def _times(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Products of numbers below 2^61 + 8, by halves of 31 bits; congruent and below 2^61 + 8."""
    a1, a0, b1, b0 = a >> U(31), a & _LOW, b >> U(31), b & _LOW
    middle = a1 * b0
    middle += a0 * b1
    a1 *= b1
    a1 += a1
    a0 *= b0
    out = _raised(_part(middle))
    out += a1
    return _part(_part(out) + _part(a0))


def _power(base: int, n: int) -> np.ndarray:
    """The first ``n`` powers of a base, at most a chunk."""
    if len(_powers.get(base, ())) < max(1, n):
        out = np.ones(1, U)
        while len(out) < n:
            out = np.concatenate([out, _fold(_times(out, np.array([pow(base, len(out), PRIME)], U)))])
        _powers[base] = out
    return _powers[base]


def blocks(batches: Iterator[pa.RecordBatch], size: int = 1 << 20) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Slices of the batches of about ``size`` bytes of the column ``text`` (a longer text stands alone), each with its
    bytes and offsets.  Null texts count as empty."""
    for batch in batches:
        text = batch.column(batch.schema.get_field_index("text"))
        if pa.types.is_large_string(text.type) is False:
            text = text.cast(pa.large_string())
        if text.null_count:
            text = text.fill_null("")
        n = len(text)
        if not n:
            continue
        raw = text.buffers()
        offs = np.frombuffer(raw[1], np.int64, n + 1, text.offset * 8)
        data = np.frombuffer(raw[2], np.uint8) if raw[2] is not None else np.zeros(0, np.uint8)
        at = 0
        while at < n:
            to = max(at + 1, int(np.searchsorted(offs, offs[at] + size, "right")) - 1)
            yield batch.slice(at, to - at), data[offs[at] : offs[to]], offs[at : to + 1] - offs[at]
            at = to
        del batch, text, raw, offs, data
        trim()


def mapped(table: np.ndarray, data: np.ndarray) -> np.ndarray:
    """``table[data]`` for a table of 256 bytes or truth values."""
    return np.frombuffer(data.tobytes().translate(table.tobytes()), table.dtype)


def runs(inside: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts, ends and text numbers of the maximal runs of True, cut at the ends of texts."""
    n = len(inside)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    first = inside.copy()
    first[1:] &= ~inside[:-1]
    cut = offs[1:-1]
    cut = cut[cut < n]
    first[cut] = inside[cut]
    last = inside.copy()
    last[:-1] &= ~inside[1:]
    cut = cut[cut > 0]
    last[cut - 1] = inside[cut - 1]
    s, e = np.flatnonzero(first), np.flatnonzero(last) + 1
    return s, e, np.searchsorted(offs, s, "right") - 1


class Sums:
    """Running sums of the hash polynomial over a byte array, chunk by chunk: within a chunk, sums of byte times the low
    and the high half of a power; before each chunk, the value of all that precedes it."""

    def __init__(self, data: np.ndarray):
        self.n = len(data)
        size = min(CHUNK, self.n)
        power = _power(_BASE, size)
        low, high = power & _LOW, power >> U(31)
        self.low, self.high = np.empty(self.n + 1, U), np.empty(self.n + 1, U)
        self.low[0] = self.high[0] = 0
        self.before = [0]
        x, y = np.empty(STEP, U), np.empty(STEP, U)
        for at in range(0, self.n, CHUNK):
            end = min(at + CHUNK, self.n)
            for i in range(at, end, STEP):
                n = min(STEP, end - i)
                np.add(data[i : i + n], U(1), out=x[:n])
                for total, half in ((self.low, low), (self.high, high)):
                    np.multiply(x[:n], half[i - at : i - at + n], out=y[:n])
                    if i > at:
                        y[0] += total[i]
                    np.cumsum(y[:n], out=total[i + 1 : i + 1 + n])
            whole = (int(self.high[end]) << 31) + int(self.low[end])
            self.before.append((self.before[-1] + whole * pow(_BASE, at, PRIME)) % PRIME)
        self.back = _power(pow(_BASE, -1, PRIME), size)

    def _value(self, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        out = _raised(_part(high))
        out += _part(low)
        return _part(out)

    def _prefix(self, at: np.ndarray) -> np.ndarray:
        """The polynomial of the first ``at`` bytes."""
        chunk = np.maximum(at - 1, 0) // CHUNK
        base = np.array([pow(_BASE, int(c) * CHUNK, PRIME) for c in range(len(self.before))], U)
        inside = np.where(at > 0, self._value(self.low[at], self.high[at]), U(0))
        return _fold(np.array(self.before, U)[chunk] + _times(inside, base[chunk]))

    def ranged(self, s: np.ndarray, e: np.ndarray) -> np.ndarray:
        if self.n <= CHUNK:
            value = self._value(self.low[e] - self.low[s], self.high[e] - self.high[s])
            return _fold(_times(value, self.back[np.minimum(s, len(self.back) - 1)])) if len(self.back) else value
        value = _fold(self._prefix(e) + _P - self._prefix(s))
        back = np.array([pow(_BASE, -c * CHUNK, PRIME) for c in range(len(self.before))], U)
        return _fold(_times(_times(value, self.back[s % CHUNK]), back[s // CHUNK]))


def sums(data: np.ndarray) -> Sums:
    """What ``ranged`` reads."""
    return Sums(data)


def ranged(total: Sums, s: np.ndarray, e: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each byte range of the array behind ``total``; that of an empty range is 0."""
    out = np.empty(len(s), U)
    for i in range(0, len(s), STEP):
        out[i : i + STEP] = mix(total.ranged(s[i : i + STEP], e[i : i + STEP]))
    return out


def hashes(data: np.ndarray, s: np.ndarray, e: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each byte range."""
    return ranged(sums(data), s, e)


def words(data: np.ndarray, offs: np.ndarray, lower: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Hashes, starts, ends and text numbers of the words: runs of bytes other than space and \\t to \\r."""
    if lower:
        data = mapped(LOWER, data)
    s, e, doc = runs(~mapped(SPACE, data), offs)
    return hashes(data, s, e), s, e, doc


def windows(h: np.ndarray, doc: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of k items in a row within one text, and the index of the first item of each."""
    n = len(h) - k + 1
    if n <= 0:
        return np.zeros(0, U), np.zeros(0, np.int64)
    whole = np.flatnonzero(doc[:n] == doc[k - 1 :])
    out = np.zeros(n, U)
    q = 1
    for j in range(k):
        out += h[j : j + n] * U(q)
        q = q * _TURN % (1 << 64)
    return mix(out[whole] + U(k)), whole


def shingle_sets(data: np.ndarray, offs: np.ndarray, k: int = 5) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The distinct shingles of each text: (hash, text number) sorted by hash then text, and the set sizes.  A text of
    1 to k - 1 words has its whole word sequence as its one shingle; a text without words has none."""
    n = len(offs) - 1
    h, _, _, doc = words(data, offs)
    tok, at = windows(h, doc, k)
    owner = doc[at]
    count = np.bincount(doc, minlength=n)
    for size in range(1, k):
        few = np.flatnonzero(count == size)
        if len(few):
            first = np.searchsorted(doc, few)
            x = np.zeros(len(few), U)
            q = 1
            for j in range(size):
                x += h[first + j] * U(q)
                q = q * _TURN % (1 << 64)
            tok, owner = np.concatenate([tok, mix(x + U(size))]), np.concatenate([owner, few])
    order = np.argsort(owner, kind="stable")
    tok, owner = tok[order], owner[order]
    order = np.argsort(tok, kind="stable")
    tok, owner = tok[order], owner[order]
    if len(tok):
        new = np.ones(len(tok), bool)
        new[1:] = (tok[1:] != tok[:-1]) | (owner[1:] != owner[:-1])
        tok, owner = tok[new], owner[new]
    return tok, owner, np.bincount(owner, minlength=n)


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64) if x.dtype == U else x


def lists(values: np.ndarray, lens: np.ndarray, kind: pa.DataType | None = None) -> pa.Array:
    """An Arrow list column from concatenated values and lengths."""
    offs = np.zeros(len(lens) + 1, np.int32)
    np.cumsum(lens, out=offs[1:])
    return pa.ListArray.from_arrays(pa.array(offs), pa.array(signed(values), kind))
