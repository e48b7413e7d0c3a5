"""Vectorised views of a batch of texts: one byte buffer, word borders, hashes. All numpy, no per-word objects."""

from __future__ import annotations

import functools

import numpy as np
import pyarrow as pa

U64 = np.uint64
BASE = U64(0x9E3779B97F4A7C15 | 1)
BASE_INVERSE = U64(pow(int(BASE), -1, 2**64))


def buffer(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a large_binary array; nothing is copied."""
    n = len(texts)
    offsets = np.frombuffer(texts.buffers()[1], np.int64, n + 1, texts.offset * 8)
    raw = texts.buffers()[2]
    data = np.frombuffer(raw, np.uint8) if raw is not None and raw.size else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def lowered(data: np.ndarray) -> np.ndarray:
    """A-Z to a-z, all other bytes as they are."""
    return np.where((data >= 65) & (data <= 90), data | 32, data)


def _table(is_word) -> np.ndarray:
    return np.array([is_word(b) for b in range(256)])


#: Words of quality, line and near-duplicate operators: anything but space and 09-0D.
NOT_GAP = _table(lambda b: not (b == 32 or 9 <= b <= 13))
#: Words of decontamination, after lower-casing: digits, a-z and every non-ASCII byte.
ALPHANUMERIC = _table(lambda b: 48 <= b <= 57 or 97 <= b <= 122 or b >= 128)


def words(data: np.ndarray, offsets: np.ndarray, kind: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts, ends and text number of every word; words never cross texts."""
    if not len(data):
        none = np.zeros(0, np.int64)
        return none, none, none
    inside = kind[data]
    starts, ends = inside.copy(), inside.copy()
    starts[1:] &= ~inside[:-1]
    ends[:-1] &= ~inside[1:]
    cut = offsets[1:-1]
    cut = cut[(cut > 0) & (cut < len(data))]
    starts[cut] |= inside[cut]
    ends[cut - 1] |= inside[cut - 1]
    s, e = np.flatnonzero(starts), np.flatnonzero(ends) + 1
    return s, e, np.repeat(np.arange(len(offsets) - 1), np.diff(np.searchsorted(s, offsets)))


@functools.cache
def _powers(size: int) -> tuple[np.ndarray, np.ndarray]:
    one = np.ones(size + 1, U64)
    up, down = one.copy(), one.copy()
    up[1:], down[1:] = BASE, BASE_INVERSE
    return np.multiply.accumulate(up), np.multiply.accumulate(down)


def mixed(h: np.ndarray) -> np.ndarray:
    """A bijection of 64 bits that spreads every bit."""
    h = h ^ (h >> U64(30))
    h = h * U64(0xBF58476D1CE4E5B9)
    h ^= h >> U64(27)
    h *= U64(0x94D049BB133111EB)
    h ^= h >> U64(31)
    return h


_BYTE = mixed(np.arange(1, 257, dtype=U64) * U64(0xD6E8FEB86659FD93))


def _long_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Hashes of stretches by prefix sums over all bytes: the time doesn't depend on their lengths."""
    size = 1 << max(12, int(len(data)).bit_length())
    up, down = _powers(size)
    total = np.zeros(len(data) + 1, U64)
    np.cumsum(_BYTE[data] * up[: len(data)], out=total[1:])
    return mixed((total[ends] - total[starts]) * down[starts] + (ends - starts).astype(U64) * U64(0xA0761D6478BD642F))


#: Bytes of a stretch that is hashed eight by eight; longer ones take prefix sums.
SHORT = 64
_LOW_BYTES = np.array([(1 << 8 * k) - 1 for k in range(9)], U64)


def span_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each stretch of bytes, which depends on its bytes alone; stretches of equal length up to eight bytes never clash."""
    n = ends - starts
    padded = np.zeros(len(data) + 8, np.uint8)
    padded[: len(data)] = data
    eight = np.ndarray((len(data) + 1,), "<u8", padded, strides=(1,))
    out = mixed((eight[starts] & _LOW_BYTES[np.minimum(n, 8)]) + n.astype(U64) * U64(0xA0761D6478BD642F))
    rest = np.flatnonzero((n > 8) & (n <= SHORT))
    k = 8
    while len(rest):
        out[rest] = mixed((out[rest] ^ (eight[starts[rest] + k] & _LOW_BYTES[np.minimum(n[rest] - k, 8)])) * U64(0xE7037ED1A0B428DB))
        k += 8
        rest = rest[n[rest] > k]
    far = np.flatnonzero(n > SHORT)
    if len(far):
        out[far] = _long_hashes(data, starts[far], ends[far])
    return out


def chained(hashes: np.ndarray, count: int) -> np.ndarray:
    """Hash of each run of ``count`` neighbouring hashes, order counted; entry k begins at k."""
    n = len(hashes) - count + 1
    if n <= 0:
        return np.zeros(0, U64)
    out = np.zeros(n, U64)
    for k in range(count):
        out = (out ^ hashes[k : k + n]) * U64(0xE7037ED1A0B428DB)
        out ^= out >> U64(32)
    return mixed(out)


def distinct(line: np.ndarray, h: np.ndarray, mark: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(line, hash) without repeats, each line's hashes by ``mark`` (a byte), then value.

    One sort of a number that holds line, mark and the first bits of the hash; only if two hashes of a line agree in
    all of it is the slice sorted by the whole keys.
    """
    if not len(h):
        return line, h
    room = 64 - max(1, int(line[-1]).bit_length() if np.all(line[:-1] <= line[1:]) else int(line.max()).bit_length())
    whole = line.astype(U64) << U64(room)
    if mark is not None:
        whole |= mark.astype(U64) << U64(room - 8)
        room -= 8
    whole |= h >> U64(64 - room)
    order = np.argsort(whole)
    at, word = whole[order], h[order]
    if np.any((at[1:] == at[:-1]) & (word[1:] != word[:-1])):
        order = np.lexsort((h, line) if mark is None else (h, mark, line))
        word = h[order]
    line = line[order]
    fresh = np.ones(len(line), bool)
    fresh[1:] = (line[1:] != line[:-1]) | (word[1:] != word[:-1])
    return line[fresh], word[fresh]
