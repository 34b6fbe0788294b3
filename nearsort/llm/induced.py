"""External suffix sorting by recursive induction, with common-prefix lengths.

Only suffixes that start a rise (S*) are sorted, by naming the pieces between them and sorting the
names: in memory if they fit, by the same procedure if not. All other suffixes are
induced from them: a queue ordered by first symbol takes, for each suffix met in sorted order, the
one that starts a place earlier, together with the rank it was met at. Common-prefix lengths travel along: that
of two suffixes induced one after the other is one more than the least between the two that induced them. Lengths
stop at ``cap``: beyond it the order of equal prefixes is left open.

The text, the queue's runs, the order met, its lengths and all other arrays as long as the text lie in files; memory holds a
bounded number of queue entries and one chunk of each array. Work proceeds a chunk of a bucket at a time, so every step is an
array operation.
"""

from __future__ import annotations

import os
import tempfile
from collections import Counter, deque
from collections.abc import Iterator

import numpy as np

#: Queue entries held in memory, names sorted in memory, entries of one array step.
QUEUE_ENTRIES = 1 << 17
NAMES_IN_MEMORY = 1 << 20
CHUNK = 1 << 16
#: Entries up to which an array stays in memory.
SMALL = 1 << 14
_BLOCK = 1024
#: What the external parts did in this process: entries written by queues, names sorted by recursion, entries of arrays in files.
COUNTERS: Counter[str] = Counter()


def disk_array(folder: str, n: int, dtype: type) -> np.ndarray:
    """An array of zeros, in an unlinked file of its own if it is long: its space is free again once nothing refers to it."""
    if n <= SMALL:
        return np.zeros(n, dtype)
    at, name = tempfile.mkstemp(dir=folder)
    os.close(at)
    out = np.memmap(name, dtype=dtype, mode="w+", shape=(n,))
    os.unlink(name)
    COUNTERS["filed"] += n
    return np.asarray(out)


def _chunks(n: int) -> Iterator[slice]:
    for a in range(0, n, CHUNK):
        yield slice(a, min(n, a + CHUNK))


class BucketQueue:
    """A priority queue of (symbol, place, rank) tuples, asked for one symbol at a time and giving its entries in order of arrival."""

    def __init__(self, folder: str, entries: int):
        self.entries, self.held, self.written = entries, 0, 0
        self.memory: dict[int, deque[tuple[np.ndarray, np.ndarray]]] = {}
        self.index: dict[int, deque[tuple[int, int]]] = {}
        at, self.name = tempfile.mkstemp(dir=folder)
        os.close(at)

    def push(self, symbol: np.ndarray, place: np.ndarray, rank: np.ndarray) -> None:
        order = np.argsort(symbol, kind="stable")
        s, p, r = symbol[order], place[order], rank[order]
        at = np.concatenate(([0], np.flatnonzero(s[1:] != s[:-1]) + 1, [len(s)])).tolist()
        for a, b in zip(at, at[1:]):
            self.memory.setdefault(int(s[a]), deque()).append((p[a:b], r[a:b]))
        self.held += len(s)
        if self.held > self.entries:
            self._spill()

    def _spill(self) -> None:
        """What is in memory becomes a run of the file, symbol by symbol; it is older than all that follows."""
        with open(self.name, "ab") as f:
            for s in sorted(self.memory):
                n = 0
                for p, r in self.memory[s]:
                    np.stack((p, r), axis=1).astype(np.int64).tofile(f)
                    n += len(p)
                self.index.setdefault(s, deque()).append((self.written, n))
                self.written += n
        COUNTERS["spilled"] += self.held
        self.memory, self.held = {}, 0

    def pop(self, symbol: int) -> tuple[np.ndarray, np.ndarray] | None:
        """The oldest entries of a symbol, about CHUNK at most."""
        runs = self.index.get(symbol)
        if runs:
            at, n = runs.popleft()
            if n > CHUNK:
                runs.appendleft((at + CHUNK, n - CHUNK))
                n = CHUNK
            if not runs:
                del self.index[symbol]
            got = np.fromfile(self.name, np.int64, 2 * n, offset=16 * at).reshape(-1, 2)
            return got[:, 0], got[:, 1]
        mine = self.memory.get(symbol)
        if mine is None:
            return None
        parts, n = [], 0
        while mine and n < CHUNK:
            parts.append(mine.popleft())
            n += len(parts[-1][0])
        if not mine:
            del self.memory[symbol]
        self.held -= n
        return parts[0] if len(parts) == 1 else (np.concatenate([x[0] for x in parts]), np.concatenate([x[1] for x in parts]))

    def close(self) -> None:
        os.unlink(self.name)


class Scan:
    """Suffixes in the order met, with the common-prefix length of each and the one before."""

    def __init__(self, folder: str, n: int):
        self.place, self.lcp, self.n = disk_array(folder, n, np.int64), disk_array(folder, n + 1, np.int64), 0
        self.minima, self.blocks = np.empty(n // _BLOCK + 1, np.int64), 0

    def add(self, place: np.ndarray, lcp: np.ndarray) -> np.ndarray:
        a, self.n = self.n, self.n + len(place)
        self.place[a : self.n], self.lcp[a : self.n] = place, lcp
        full = self.n // _BLOCK
        if full > self.blocks:
            self.minima[self.blocks : full] = self.lcp[self.blocks * _BLOCK : full * _BLOCK].reshape(-1, _BLOCK).min(axis=1)
            self.blocks = full
        return np.arange(a, self.n)

    def least(self, rank: np.ndarray) -> np.ndarray:
        """Minimum of lcp over (rank[k], rank[k + 1]] for each k."""
        if len(rank) < 2:
            return np.zeros(0, np.int64)
        at = rank[:-1] + 1
        if int(rank[-1] - rank[0]) < 6000 * len(rank):
            return np.minimum.reduceat(self.lcp[at[0] : rank[-1] + 1], at - at[0])
        out = np.empty(len(at), np.int64)
        for k, (a, b) in enumerate(zip(at.tolist(), (rank[1:] + 1).tolist())):
            x, y = -(-a // _BLOCK), b // _BLOCK
            if x >= y:
                out[k] = self.lcp[a:b].min()
            else:
                parts = [self.minima[x:y].min()]
                if a < x * _BLOCK:
                    parts.append(self.lcp[a : x * _BLOCK].min())
                if y * _BLOCK < b:
                    parts.append(self.lcp[y * _BLOCK : b].min())
                out[k] = min(parts)
        return out

    def reversed(self) -> tuple[np.ndarray, np.ndarray]:
        """The order met, last first, and each one's common-prefix length with the one before it in that order."""
        return self.place[: self.n][::-1], self.lcp[: self.n + 1][::-1][: self.n]


def common(text: np.ndarray, a: np.ndarray, b: np.ndarray, cap: int, known: np.ndarray | None = None) -> np.ndarray:
    """Common-prefix length of suffixes a[k] and b[k], counted on from ``known``, up to ``cap``."""
    n = len(text)
    out = np.zeros(len(a), np.int64) if known is None else np.minimum(known, cap)
    live = np.flatnonzero(out < cap)
    while len(live):
        x, y = a[live] + out[live], b[live] + out[live]
        ok = (x < n) & (y < n)
        ok[ok] = text[x[ok]] == text[y[ok]]
        live = live[ok]
        out[live] += 1
        live = live[out[live] < cap]
    return out


def _rises(text: np.ndarray, folder: str) -> np.ndarray:
    """Whether each suffix (and the empty one, last) is smaller than the next one."""
    n = len(text)
    rise = disk_array(folder, n + 1, np.bool_)
    rise[n], after = True, False  # the last symbol falls: the empty suffix is the least
    for part in reversed(list(_chunks(n))):
        here = np.asarray(text[part.start : min(part.stop + 1, n)], dtype=np.int64)
        step = np.sign(np.diff(here))
        if part.stop == n:
            step = np.append(step, -1)
        at = np.where(step != 0, np.arange(len(step)), len(step))
        at = np.minimum.accumulate(at[::-1])[::-1]
        rise[part] = np.append(step, 1 if after else -1)[at] > 0
        after = bool(rise[part.start])
    return rise


def _induce(text: np.ndarray, symbols: list[int], rise: np.ndarray, seeds: np.ndarray, seed_lcp: np.ndarray | None, cap: int, folder: str, entries: int) -> tuple[np.ndarray, np.ndarray]:
    """All suffixes in order (the empty one first), from the sorted S* suffixes; without ``seed_lcp`` these share nothing."""
    n = len(text)
    count: Counter[int] = Counter()
    for part in _chunks(len(seeds)):
        count.update(dict(zip(*(x.tolist() for x in np.unique(text[seeds[part]], return_counts=True)))))
    # up: the empty suffix, then bucket by bucket the falling suffixes and the seeds
    queue, scan = BucketQueue(folder, entries), Scan(folder, n + 1)

    def feed(place: np.ndarray, rank: np.ndarray, rising: bool) -> None:
        before = place - 1
        ok = before >= 0
        ok[ok] = rise[before[ok]] == rising
        if ok.any():
            queue.push(text[before[ok]], before[ok], rank[ok])

    def bucket(c: int, rising: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """What the queue has of a symbol, and what that adds to the same symbol."""
        last = None
        while (got := queue.pop(c)) is not None:
            place, rank = got
            lcp = np.empty(len(place), np.int64)
            lcp[0] = 0 if last is None else 1 + scan.least(np.asarray([last, rank[0]]))[0]
            lcp[1:] = 1 + scan.least(rank)
            np.minimum(lcp, cap, out=lcp)
            last = rank[-1]
            yield place, lcp
            feed(place, scan.add(place, lcp), rising)

    feed(np.asarray([n]), scan.add(np.asarray([n]), np.asarray([0])), False)
    falling, shared = (disk_array(folder, n, np.int64) for _ in range(2))
    bounds: dict[int, tuple[int, int]] = {}
    used = seed = 0
    for c in symbols:
        first, end = used, None
        for place, lcp in bucket(c, False):
            falling[used : used + len(place)], shared[used : used + len(place)] = place, lcp
            used, end = used + len(place), place[-1:]
        bounds[c] = first, used
        for part in _chunks(count[c]):
            place = np.asarray(seeds[seed + part.start : seed + part.stop])
            lcp = np.zeros(len(place), np.int64) if seed_lcp is None else np.array(seed_lcp[seed + part.start : seed + part.stop])
            if part.start == 0:
                lcp[0] = 0 if end is None else common(text, place[:1], end, cap)[0]
            feed(place, scan.add(place, lcp), False)
        seed += count[c]
    queue.close()
    # down: bucket by bucket from the greatest, the rising suffixes before the falling ones
    queue, scan = BucketQueue(folder, entries), Scan(folder, n + 1)
    for c in reversed(symbols):
        end = None
        for place, _ in bucket(c, True):
            end = place[-1:]
        low, high = bounds[c]
        for b in range(high, low, -CHUNK):
            a = max(low, b - CHUNK)
            place = falling[a:b][::-1]
            lcp = np.array(shared[a + 1 : b + 1][::-1]) if b < high else np.append([0], shared[a + 1 : b][::-1])
            if b == high and end is not None:
                lcp[0] = common(text, end, place[:1], cap)[0]
            feed(place, scan.add(place, lcp), True)
    queue.close()
    scan.add(np.asarray([n]), np.asarray([0]))
    return scan.reversed()


def _in_memory(names: np.ndarray, cap: int) -> np.ndarray:
    """Suffix order of a name string by doubling, as far as ``cap`` names."""
    n = len(names)
    rank, width = names.astype(np.int64), 1
    while True:
        after = np.zeros(n, np.int64)
        after[: n - width] = rank[width:] + 1 if width < n else 0
        key = rank * (n + 2) + after
        order = np.argsort(key, kind="stable")
        s = key[order]
        new = np.concatenate(([0], np.cumsum(s[1:] != s[:-1])))
        rank = np.empty(n, np.int64)
        rank[order] = new
        width *= 2
        if new[-1] == n - 1 or width >= min(cap, n):
            return order


def _by_symbol(text: np.ndarray, symbols: list[int], stars: np.ndarray, folder: str, entries: int) -> np.ndarray:
    """Star places in order of their first symbols."""
    queue, out, n = BucketQueue(folder, entries), disk_array(folder, len(stars), np.int64), 0
    for part in _chunks(len(stars)):
        place = np.asarray(stars[part])
        queue.push(text[place], place, place)
    for c in symbols:
        while (got := queue.pop(c)) is not None:
            out[n : n + len(got[0])] = got[0]
            n += len(got[0])
    queue.close()
    return out


def sort_suffixes(text: np.ndarray, cap: int = 1 << 62, folder: str | None = None, entries: int = QUEUE_ENTRIES, names_in_memory: int = NAMES_IN_MEMORY) -> tuple[np.ndarray, np.ndarray]:
    """(suffix order, common-prefix length with the one before, at most ``cap``) of an integer array, which may lie in a file.

    An empty text has empty results. Ties beyond ``cap`` symbols are in no particular order. The results may lie in files of
    ``folder``, which can be removed while they are in use.
    """
    n = len(text)
    if n < 2:
        return np.arange(n), np.zeros(n, np.int64)
    if folder is None:
        with tempfile.TemporaryDirectory() as own:
            return sort_suffixes(text, cap, own, entries, names_in_memory)
    found: set[int] = set()
    for part in _chunks(n):
        found.update(np.unique(text[part]).tolist())
    symbols = sorted(found)
    rise = _rises(text, folder)
    many = sum(int((rise[a + 1 : min(b, n - 1) + 1] & ~rise[a : min(b, n - 1)]).sum()) for a, b in ((p.start, p.stop) for p in _chunks(n)))
    stars, k = disk_array(folder, many, np.int64), 0
    for part in _chunks(n):
        a, b = part.start, min(part.stop, n - 1)
        at = np.flatnonzero(rise[a + 1 : b + 1] & ~rise[a:b]) + a + 1
        stars[k : k + len(at)] = at
        k += len(at)
    if many == 0:
        order, lcp = _induce(text, symbols, rise, stars, None, cap, folder, entries)
        return order[1:], lcp[1:]
    # sort the pieces between stars: any order within a symbol, induced, sorts them by their pieces
    rough = _by_symbol(text, symbols, stars, folder, entries)
    met, _ = _induce(text, symbols, rise, rough, None, cap, folder, entries)
    del rough
    # each star's number, in the order of the pieces; then names, equal for equal pieces
    pieces, k = disk_array(folder, many, np.int64), 0
    for part in _chunks(n + 1):
        place = np.asarray(met[part])
        on = np.zeros(len(place), bool)
        inner = np.flatnonzero((place > 0) & (place < n))
        on[inner] = rise[place[inner]] & ~rise[place[inner] - 1]
        pieces[k : k + int(on.sum())] = np.searchsorted(stars, place[on])
        k += int(on.sum())
    del met
    names, distinct = disk_array(folder, many, np.int64), 0
    names[pieces[0]] = 0
    for part in _chunks(many - 1):
        x, y = np.asarray(pieces[part]), np.asarray(pieces[part.start + 1 : part.stop + 1])
        a, b = np.asarray(stars[x]), np.asarray(stars[y])
        inner = (x < many - 1) & (y < many - 1)  # the last piece ends the text and equals no other
        la, lb = (stars[np.minimum(z + 1, many - 1)] - p + 1 for z, p in ((x, a), (y, b)))
        same = np.zeros(len(a), bool)
        equal = np.flatnonzero(inner & (la == lb))
        same[equal] = _equal(text, a[equal], b[equal], la[equal])
        new = distinct + np.cumsum(~same)
        names[y], distinct = new, int(new[-1])
    distinct += 1
    del pieces
    deep = min(cap, many + 1)
    if distinct == many:
        sorted_names, name_lcp = disk_array(folder, many, np.int64), np.zeros(1, np.int64)
        for part in _chunks(many):
            sorted_names[names[part]] = np.arange(part.start, part.stop)
    elif many <= names_in_memory:
        sorted_names = _in_memory(names, deep)
        name_lcp = np.concatenate(([0], common(names, sorted_names[:-1], sorted_names[1:], deep)))
    else:
        COUNTERS["recursed"] += many
        sorted_names, name_lcp = sort_suffixes(names, deep, folder, entries, names_in_memory)
    # a common prefix of so many names, in symbols, then what follows it
    seeds, seed_lcp = disk_array(folder, many, np.int64), disk_array(folder, many, np.int64)
    end_of = lambda k: np.where(k < many, stars[np.minimum(k, many - 1)], n)
    for part in _chunks(many):
        of = np.asarray(sorted_names[part])
        seeds[part] = stars[of]
        a = max(part.start, 1)
        if a < part.stop:
            x, y = np.asarray(sorted_names[a - 1 : part.stop - 1]), np.asarray(sorted_names[a : part.stop])
            shared = np.zeros(len(x), np.int64) if distinct == many else np.asarray(name_lcp[a : part.stop])
            px, py = np.asarray(stars[x]), np.asarray(stars[y])
            seed_lcp[a : part.stop] = common(text, px, py, cap, np.minimum(end_of(y + shared) - py, end_of(x + shared) - px))
    order, lcp = _induce(text, symbols, rise, seeds, seed_lcp, cap, folder, entries)
    return order[1:], lcp[1:]


def _equal(text: np.ndarray, a: np.ndarray, b: np.ndarray, length: np.ndarray) -> np.ndarray:
    out = np.ones(len(a), bool)
    live, d = np.arange(len(a)), 0
    while len(live):
        live = live[length[live] > d]
        ok = text[a[live] + d] == text[b[live] + d]
        out[live[~ok]] = False
        live, d = live[ok], d + 1
    return out
