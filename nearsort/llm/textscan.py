"""Vectorised scanning of Arrow text batches: words, polynomial hashes, minimizer anchors.

All functions work on the UTF-8 bytes of a group of documents laid end to end. Hashes are
polynomials modulo 2**64 over a table of mixed byte values, so the hash of any run of bytes or
words follows from two prefix sums.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

_BASE = np.uint64(0x9E3779B97F4A7C15)
_BASE_WORD = np.uint64(0xD1342543DE82EF95)
#: UTF-8 bytes handled at once; a longer document is a group of its own, which recurrence.Units scans piece by piece.
GROUP_BYTES = 1 << 19


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: a bijection that spreads every input bit."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


_TABLE = mix((np.arange(256, dtype=np.uint64) + np.uint64(1)) * _BASE)
_powers: dict[int, np.ndarray] = {}


def _power(base: np.uint64, n: int) -> np.ndarray:
    """base ** 0 .. base ** (n - 1) modulo 2**64; kept in the worker, rounded up to a power of two."""
    key = int(base)
    have = _powers.get(key)
    if have is None or len(have) < n:
        size = 1 << max(16, int(n - 1).bit_length())
        have = np.full(size, base, dtype=np.uint64)
        have[0] = 1
        have = np.cumprod(have, dtype=np.uint64)
        _powers[key] = have
    return have[:n]


def forget() -> None:
    """Let go of the power tables; the next task builds its own."""
    _powers.clear()


def _inverse(base: np.uint64) -> np.uint64:
    return np.uint64(pow(int(base), -1, 1 << 64))


class Rolling:
    """Hashes of arbitrary runs [start, end) of a sequence of 64-bit symbols."""

    def __init__(self, symbols: np.ndarray, base: np.uint64 = _BASE):
        n = len(symbols)
        self.base = base
        self.prefix = np.zeros(n + 1, dtype=np.uint64)
        np.cumsum(symbols * _power(base, n), out=self.prefix[1:])

    def runs(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        back = _power(_inverse(self.base), len(self.prefix))
        return mix((self.prefix[end] - self.prefix[start]) * back[start] + (end - start).astype(np.uint64) * np.uint64(0xA0761D6478BD642F))

    def grams(self, k: int) -> np.ndarray:
        n = len(self.prefix) - k
        if n <= 0:
            return np.zeros(0, dtype=np.uint64)
        back = _power(_inverse(self.base), n)
        return mix((self.prefix[k:] - self.prefix[:-k]) * back)

    def grams_at(self, places: np.ndarray, k: int) -> np.ndarray:
        back = _power(_inverse(self.base), len(self.prefix))
        return mix((self.prefix[places + k] - self.prefix[places]) * back[places])


def text_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; a null is an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("" if not pa.types.is_binary(column.type) and not pa.types.is_large_binary(column.type) else b"")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, off, data = column.buffers()
    if off is None:
        return np.zeros(0, dtype=np.uint8), np.zeros(len(column) + 1, dtype=np.int64)
    offsets = np.frombuffer(off, dtype=np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, dtype=np.uint8)
    return raw, offsets


def groups(column: pa.Array, limit: int = GROUP_BYTES) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, bytes, offsets from 0) of consecutive rows, about ``limit`` bytes at a time."""
    raw, offsets = text_buffers(column)
    row, n = 0, len(offsets) - 1
    while row < n:
        to = int(np.searchsorted(offsets, offsets[row] + limit, side="right")) - 1
        to = min(n, max(to, row + 1))
        yield row, raw[offsets[row] : offsets[to]], offsets[row : to + 1] - offsets[row]
        row = to


#: What separates words in the contracts that say [^\x20\x09-\x0D]+.
SPACE = np.zeros(256, dtype=bool)
SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
#: Bytes of words in contracts that take ASCII letters, digits and everything beyond ASCII.
ALNUM = np.zeros(256, dtype=bool)
ALNUM[0x30:0x3A] = ALNUM[0x41:0x5B] = ALNUM[0x61:0x7B] = ALNUM[0x80:] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 32


def words(data: np.ndarray, offsets: np.ndarray, inside: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Byte starts and ends of all words (``inside``: table of word bytes), and each document's first word (one more at the end)."""
    n = len(data)
    if n == 0:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offsets), np.int64)
    now = inside[data]
    before = np.empty(n, dtype=bool)
    before[0] = False
    before[1:] = now[:-1]
    cut = offsets[1:-1]
    before[cut[cut < n]] = False
    start = np.flatnonzero(now & ~before)
    after = np.empty(n, dtype=bool)
    after[-1] = False
    after[:-1] = now[1:]
    after[cut[cut > 0] - 1] = False
    end = np.flatnonzero(now & ~after) + 1
    return start, end, np.searchsorted(start, offsets)


def byte_hash(data: np.ndarray) -> Rolling:
    return Rolling(_TABLE[data])


def word_hash(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Hashes of words; of a long document the bytes of some words at a time, as prefix sums take tens of bytes a byte."""
    if len(data) <= 2 * GROUP_BYTES or not len(start):
        return byte_hash(data).runs(start, end)
    out, k = np.empty(len(start), dtype=np.uint64), 0
    while k < len(start):
        to = max(k + 1, int(np.searchsorted(end, start[k] + GROUP_BYTES, side="right")))
        a = start[k]
        out[k:to] = byte_hash(data[a : end[to - 1]]).runs(start[k:to] - a, end[k:to] - a)
        k = to
    return out


def word_rolling(hashes: np.ndarray) -> Rolling:
    return Rolling(hashes, _BASE_WORD)


def sliding_min(values: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each ``width`` consecutive values, by block-wise forward and backward minima."""
    n = len(values)
    if n < width:
        return values[:0]
    blocks = -(-n // width)
    padded = np.full(blocks * width, np.iinfo(np.uint64).max, dtype=np.uint64)
    padded[:n] = values
    grid = padded.reshape(blocks, width)
    ahead = np.minimum.accumulate(grid, axis=1).ravel()
    behind = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(behind[: n - width + 1], ahead[width - 1 : n])


def byte_order(data: np.ndarray) -> np.ndarray:
    """A 32-bit number for the eight bytes at each place, by which byte anchors are chosen."""
    n = len(data) - 7
    if n <= 0:
        return np.zeros(0, np.uint32)
    four = np.empty(n + 4, np.uint32)
    for k in range(4):
        some = four[k::4]
        some[:] = np.frombuffer(data, np.dtype("<u4"), len(some), k)
    x = four[:n] * np.uint32(0x9E3779B1) + four[4:] * np.uint32(0x85EBCA77)
    x ^= x >> np.uint32(15)
    x *= np.uint32(0xC2B2AE3D)
    x ^= x >> np.uint32(13)
    return x


def anchors(rolling: Rolling, bounds: np.ndarray, span: int, gram: int, limit: int | None = None, order: np.ndarray | None = None) -> tuple[np.ndarray, ...]:
    """Minimizer anchors of every window of ``span`` symbols inside a document.

    Equal windows choose an equal gram at an equal place, so two windows can only be equal if
    their anchors are. Returned per anchor: gram hash, gram position, first and last window start
    that chose it, document number. ``limit``: windows of the first document that count, if not all.
    ``order``: numbers of places, from their next symbols, whose least chooses; without it the grams' hashes do.
    """
    n = len(rolling.prefix) - 1
    empty = np.zeros(0, np.int64)
    lengths = np.diff(bounds)
    if n < span or not (lengths >= span).any():
        return np.zeros(0, np.uint64), empty, empty, empty, empty
    low = np.uint64((1 << 31) - 1)  # the same bits of a hash decide in every group, whatever its size
    if order is None:
        packed = rolling.grams(gram) & ~low
    else:
        packed = order[: n - gram + 1].astype(np.uint64) << np.uint64(31)
    packed |= np.arange(len(packed), dtype=np.uint64)
    chosen = (sliding_min(packed, span - gram + 1) & low).astype(np.int64)
    long = np.flatnonzero(lengths >= span)
    count = lengths[long] - span + 1
    if limit is not None:
        count = np.minimum(count, limit)
    doc = np.repeat(long, count)
    first = np.repeat(bounds[long] - np.concatenate(([0], np.cumsum(count)[:-1])), count)
    starts = np.arange(len(doc)) + first
    place = chosen[starts]
    new = np.flatnonzero(np.concatenate(([True], place[1:] != place[:-1])))
    last = np.concatenate((new[1:], [len(starts)])) - 1
    return rolling.grams_at(place[new], gram), place[new], starts[new], starts[last], doc[new]


def signed(x: np.ndarray) -> np.ndarray:
    """The same 64 bits as a Spark bigint."""
    return x.view(np.int64) if x.dtype == np.uint64 else x.astype(np.int64)


def cover(n: int, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Which of n places lie in any of the intervals [start, end); a byte a place."""
    some = ends > starts
    starts, ends = starts[some], ends[some]
    if not len(starts):
        return np.zeros(n, dtype=bool)
    order = np.argsort(starts, kind="stable")
    s, e = starts[order], np.maximum.accumulate(ends[order])
    new = np.flatnonzero(np.concatenate(([True], s[1:] > e[:-1])))
    step = np.zeros(n + 1, dtype=np.int8)
    step[s[new]] = 1
    step[e[np.append(new[1:], len(s)) - 1]] = -1
    return np.cumsum(step[:-1], dtype=np.int8) > 0
