"""Candidates for recurring runs of words or bytes, found without moving texts.

Every window of ``span`` symbols is represented by its anchor, the least-hashed ``gram`` in it.
Windows of one anchor form a region. Equal windows have equal anchors at equal places, so only regions
whose anchor occurs twice matter; of those, equal regions are collapsed to their first place, and only
regions whose anchor also occurs in other surroundings have to be looked at symbol by symbol.

Two filters of fixed size (bit tables of 8 MB, broadcast) keep rows that cannot matter out of the shuffles. They
only let too much pass, never too little: exact joins follow.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame, functions as F

from . import textscan as ts
from .durable import cut, store
from .heavy import attach
from .lean import lean

#: Bits of a filter; its broadcast takes an eighth as many bytes whatever the input.
FILTER_BITS = 1 << 26
#: Different regions of one anchor up to which they are searched together; beyond it, window by window.
TOGETHER = 4096
#: Bytes of a document scanned at once.
PIECE_BYTES = ts.GROUP_BYTES
_NULL_ID = -(1 << 63)


@dataclass(frozen=True)
class Units:
    """What a window counts: ``span`` words or bytes, with anchors of ``gram`` of them; ``piece``: bytes of a document scanned at once."""

    kind: str
    span: int
    gram: int
    piece: int = PIECE_BYTES

    def scan(self, column: pa.Array) -> Iterator[tuple]:
        """(first row, bytes, symbol starts, symbol ends, first symbol of each document, hashes, symbols before, windows that count).

        A long document comes in pieces, each with the symbols that its last windows need; the first symbol's number in the document is
        ``before``. Pieces share no window, so memory stays bounded whatever a document's length.
        """
        for row, data, offsets in ts.groups(column, self.piece):
            long = len(data) > self.piece
            if self.kind == "words":
                start, end, first = ts.words(data, offsets, ~ts.SPACE)
                if not long:
                    yield row, data, start, end, first, ts.word_rolling(ts.word_hash(data, start, end)), 0, None
                    continue
                for at, to in _parts(len(start), self.span, self.piece // 8):
                    last = min(len(start), to - 1 + self.span)
                    s, e = start[at:last], end[at:last]
                    yield row, data[s[0] : e[-1]], s - s[0], e - s[0], np.asarray([0, last - at]), ts.word_rolling(ts.word_hash(data[s[0] : e[-1]], s - s[0], e - s[0])), at, to - at if last < len(start) else None
            elif not long:
                yield row, data, None, None, offsets, ts.byte_hash(data), 0, None
            else:
                for at, to in _parts(len(data), self.span, self.piece):
                    part = data[at : to - 1 + self.span]
                    yield row, part, None, None, np.asarray([0, len(part)]), ts.byte_hash(part), at, to - at if at + len(part) < len(data) else None


def _parts(n: int, span: int, size: int) -> Iterator[tuple[int, int]]:
    """Window starts of a sequence of n symbols, in runs of ``size``."""
    for at in range(0, n - span + 1, size):
        yield at, min(at + size, n - span + 1)


def named(docs: DataFrame, id_col: str, text_col: str, original: Column | None = None) -> DataFrame:
    """(original: the id column or what is to be kept, id, th, text): a null id is the least, a null text empty; th, 64 bits of the text's hash, tells texts of one id apart."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    return docs.select((F.col(id_col) if original is None else original).alias("original"), F.coalesce(F.col(id_col).cast("long"), F.lit(_NULL_ID)).alias("id"), F.xxhash64(text).alias("th"), text.alias("text"))


def prepare(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(id, th, text) of named()."""
    return named(docs, id_col, text_col).select("id", "th", "text")


def _bit_places(keys: np.ndarray) -> np.ndarray:
    h = ts.mix(keys)
    return np.concatenate((h & np.uint64(FILTER_BITS - 1), (h >> np.uint64(32)) & np.uint64(FILTER_BITS - 1))).astype(np.int64)


class Filter:
    """A bit table of fixed size: may pass keys that were never put in."""

    def __init__(self, words: np.ndarray):
        self.words = words

    def __contains__(self, key: int) -> bool:
        return bool(self.test(np.asarray([key], dtype=np.uint64))[0])

    def test(self, keys: np.ndarray) -> np.ndarray:
        at = _bit_places(keys)
        on = (self.words[at >> 6] >> (at & 63).astype(np.uint64)) & np.uint64(1) == 1
        return on[: len(keys)] & on[len(keys) :]


def build_filter(rows: DataFrame, keys: Callable[[pa.RecordBatch], np.ndarray]) -> Filter:
    """A filter of the keys that ``keys`` takes from each batch; the driver gets FILTER_BITS / 64 numbers at most."""

    def bits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at = np.unique(_bit_places(keys(b)))
            word = at >> 6
            first = np.flatnonzero(np.concatenate(([True], word[1:] != word[:-1]))) if len(at) else np.zeros(0, np.int64)
            value = np.bitwise_or.reduceat(np.uint64(1) << (at & 63).astype(np.uint64), first) if len(at) else np.zeros(0, np.uint64)
            yield pa.RecordBatch.from_arrays([pa.array(word[first], pa.int64()), pa.array(ts.signed(value), pa.int64())], names=["w", "v"])

    got = rows.mapInArrow(lean(bits), "w long, v long").groupBy("w").agg(F.bit_or("v").alias("v")).toArrow()
    words = np.zeros(FILTER_BITS // 64, dtype=np.uint64)
    words[got.column("w").to_numpy()] = got.column("v").to_numpy().view(np.uint64)
    return Filter(words)


def _long(column: pa.Array) -> np.ndarray:
    return column.to_numpy(zero_copy_only=False)


def _text_key(ids: np.ndarray, th: np.ndarray) -> np.ndarray:
    return ts.mix(ids.view(np.uint64)) ^ th.view(np.uint64)


def _place_key(ids: np.ndarray, th: np.ndarray, at: np.ndarray) -> np.ndarray:
    return ts.mix(ids.view(np.uint64)) ^ ts.mix(th.view(np.uint64) + at.astype(np.uint64))


def _regions(b: pa.RecordBatch, units: Units):
    """Per group of documents of a batch (columns id, th, text): bytes, symbol bounds and the regions' arrays.

    Of a region: anchor hash and place, first and last window, document, then id, text hash and first window in its document.
    """
    ids, th = _long(b.column(0)), _long(b.column(1))
    for row, data, start, end, first, rolling, before, limit in units.scan(b.column(2)):
        h, place, lo, hi, doc = ts.anchors(rolling, first, units.span, units.gram, limit, ts.byte_order(data) if units.kind == "bytes" else None)
        if len(h):
            yield data, start, end, first, rolling, h, place, lo, hi, doc, ids[row + doc], th[row + doc], lo - first[doc] + before


#: Fields of a region's place.
PLACE = ["id", "th", "at"]
#: Turns the hash of a probe into one that no gram has, but for a chance of 2**-64.
_PROBE = np.uint64(0xA5A5_1234_5A5A_4321)


def find(docs: DataFrame, units: Units, together: int = TOGETHER, probe: int = 0) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """Four tables over ``docs`` (as prepare() gives them). A region is at the place (id, th, at), at being its first window.

    members: (h, rh, id, th, at, n) all regions with an anchor that may recur: n windows.
    groups: (h, rh, id, th, at, n, rows, many, mixed) their distinct contents with the first place of each, of as many places as ``rows``;
    many: the content is at two places or more; mixed: the anchor has other contents too, as many as ``mixed`` says in all.
    regions: (key, id, th, at, shift, left, gram, right, n) the text of mixed groups' first places, the anchor gram being
    replaced by a digest; keyed so that equal windows meet in one key; cut to single windows where an anchor has more
    than ``together`` contents. shift: windows before this row's first, counted from the region's first.
    probes: (id, th, probes) with ``probe``, less than a gram (bytes only): how many of a text's sampled strings of ``probe`` bytes are anywhere else too.
    """
    sc = docs.sparkSession.sparkContext

    def anchor_hashes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for row, data, _, _, first, rolling, before, limit in units.scan(b.column(2)):
                order = ts.byte_order(data) if units.kind == "bytes" else None
                h = ts.anchors(rolling, first, units.span, units.gram, limit, order)[0]
                if probe:
                    h = np.concatenate((h, _probe_hashes(units, probe, rolling, first, limit, order)[0]))
                yield pa.RecordBatch.from_arrays([pa.array(ts.signed(h), pa.int64())], names=["h"])

    twice = docs.mapInArrow(lean(anchor_hashes), "h long").groupBy("h").agg(F.count("*").alias("n")).where("n > 1").select("h")
    recurring = sc.broadcast(build_filter(twice, lambda b: _long(b.column(0)).view(np.uint64)))

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["h", "rh", *PLACE, "n"]
        for b in batches:
            all_ids, all_th = _long(b.column(0)), _long(b.column(1))
            for row, data, _, _, first, rolling, before, limit in units.scan(b.column(2)):
                order = ts.byte_order(data) if units.kind == "bytes" else None
                h, _, lo, hi, doc = ts.anchors(rolling, first, units.span, units.gram, limit, order)
                on = np.flatnonzero(recurring.value.test(h))
                doc, lo, hi = doc[on], lo[on], hi[on]
                wide = [ts.signed(h[on]), ts.signed(rolling.runs(lo, hi + units.span)), all_ids[row + doc], all_th[row + doc]]
                yield pa.RecordBatch.from_arrays([*map(pa.array, wide), *(pa.array(x.astype(np.int32)) for x in (lo - first[doc] + before, hi - lo + 1))], names=names)
                if probe:
                    h, doc, at = _probe_hashes(units, probe, rolling, first, limit, order)
                    on = np.flatnonzero(recurring.value.test(h))
                    ids, th, at = all_ids[row + doc[on]], all_th[row + doc[on]], at[on] + before
                    none = pa.array(np.zeros(len(on), np.int32))
                    yield pa.RecordBatch.from_arrays([pa.array(ts.signed(h[on])), pa.array(ts.signed(_place_key(ids, th, at))), pa.array(ids), pa.array(th), none, none], names=names)

    seen = store(docs.mapInArrow(lean(emit), "h long, rh long, id long, th long, at int, n int"), "members")
    members = seen.where("n > 0")
    probes = seen.where("n = 0").select("h", F.col("rh").alias("place"), "id", "th")
    if probe:
        twice = probes.groupBy("h").agg(F.min("place").alias("first"), F.max("place").alias("last"), F.count("*").alias("rows"))
        probes = attach(probes, cut(twice.where("first != last").select("h", "rows")), "h", "rows")
    probes = probes.groupBy("id", "th").agg(F.count("*").alias("probes"))
    place = F.struct(*PLACE)
    distinct = members.groupBy("h", "rh").agg(F.min(place).alias("first"), F.max(place).alias("last"), F.first("n").alias("n"), F.count("*").alias("rows"))
    distinct = distinct.select("h", "rh", "first.*", "n", "rows", (F.col("first") != F.col("last")).alias("many"))
    mixed = distinct.groupBy("h").agg(F.count("*").alias("mixed")).where("mixed > 1")
    groups = cut(distinct.join(mixed, "h", "left").where("many or mixed is not null"))

    wanted = groups.where("mixed is not null").select("h", "rh", *PLACE, "mixed")
    owners = sc.broadcast(build_filter(wanted.select("id", "th"), lambda b: _text_key(*map(_long, b.columns))))
    spots = sc.broadcast(build_filter(wanted.select(*PLACE), lambda b: _place_key(*map(_long, b.columns))))
    schema = "h long, rh long, id long, th long, at int, left binary, gram binary, right binary, n int"

    def texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            some = owners.value.test(_text_key(_long(b.column(0)), _long(b.column(1))))
            if not some.any():
                continue
            b = b.filter(pa.array(some))
            for data, start, end, first, rolling, h, place, lo, hi, doc, ids, th, at in _regions(b, units):
                on = np.flatnonzero(recurring.value.test(h) & spots.value.test(_place_key(ids, th, at)))
                if not len(on):
                    continue
                raw = data.tobytes()
                rh = rolling.runs(lo[on], hi[on] + units.span)
                left, gram, right = [], [], []
                for p, a, z in zip(place[on].tolist(), lo[on].tolist(), (hi[on] + units.span).tolist()):
                    q = p + units.gram
                    if units.kind == "words":
                        some = [raw[start[k] : end[k]] for k in range(a, z)]
                        x, g, y = b" ".join(some[: p - a]), b" ".join(some[p - a : q - a]), b" ".join(some[q - a :])
                    else:
                        x, g, y = raw[a:p], raw[p:q], raw[q:z]
                    left.append(x)
                    gram.append(hashlib.blake2b(g, digest_size=10).digest())
                    right.append(y)
                wide = [pa.array(x) for x in (ts.signed(h[on]), ts.signed(rh), ids[on], th[on], at[on].astype(np.int32))]
                yield pa.RecordBatch.from_arrays([*wide, *(pa.array(x, pa.binary()) for x in (left, gram, right)), pa.array((hi - lo + 1)[on].astype(np.int32))], names=["h", "rh", *PLACE, "left", "gram", "right", "n"])

    found = docs.mapInArrow(lean(texts), schema).join(wanted, ["h", "rh", *PLACE]).dropDuplicates(["h", "rh", *PLACE])
    found = found.select("h", *PLACE, "left", "gram", "right", "n", "mixed")

    def key(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """One row a region, or one a window where an anchor has very many contents."""
        names = ["key", *PLACE, "shift", "left", "gram", "right", "n"]
        words = units.kind == "words"
        for b in batches:
            out: list[list] = [[] for _ in names]
            for h, i, th, at, left, gram, right, n, many in zip(*(c.to_pylist() for c in b.columns)):
                if many <= together:
                    rows = [(h, i, th, at, 0, left, gram, right, n)]
                else:
                    rows = []
                    x, y = (side.split(b" ") if words and side else [] if words else side for side in (left, right))
                    for k in range(n):
                        lo, hi = x[k:], y[: units.span - units.gram - (len(x) - k)]
                        lo, hi = (b" ".join(lo), b" ".join(hi)) if words else (lo, hi)
                        window = hashlib.blake2b(lo + b"\t" + gram + b"\t" + hi, digest_size=8).digest()
                        rows.append((int.from_bytes(window, "little", signed=True), i, th, at, k, lo, gram, hi, 1))
                for row in rows:
                    for o, v in zip(out, row):
                        o.append(v)
                if len(out[0]) > 20_000:
                    yield pa.RecordBatch.from_arrays([pa.array(o, t) for o, t in zip(out, types)], names=names)
                    out = [[] for _ in names]
            yield pa.RecordBatch.from_arrays([pa.array(o, t) for o, t in zip(out, types)], names=names)

    types = [pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.int32()]
    regions = found.mapInArrow(lean(key), "key long, id long, th long, at int, shift int, left binary, gram binary, right binary, n int")
    return members, groups, regions.repartition("key").sortWithinPartitions("key", *PLACE, "shift"), probes


def _probe_hashes(units: Units, probe: int, rolling: ts.Rolling, first: np.ndarray, limit: int | None, order: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hash, document, place in what was scanned of it) of the ``probe`` bytes at the anchors of windows that are shorter by as much as a probe is shorter than a gram.

    So every string of ``span - gram + probe`` bytes holds one, chosen by its own bytes.
    """
    h, place, _, _, doc = ts.anchors(rolling, first, units.span - units.gram + probe, probe, limit, order)
    return ts.mix(h ^ _PROBE), doc, place - first[doc]


def merged(starts: np.ndarray, span: int) -> tuple[list[int], list[int]]:
    """Intervals [a, b) that windows at these sorted starts cover."""
    if not len(starts):
        return [], []
    new = np.flatnonzero(np.concatenate(([True], starts[1:] > starts[:-1] + 1)))
    last = np.concatenate((starts[new[1:] - 1], starts[-1:])) if len(new) > 1 else starts[-1:]
    return starts[new].tolist(), (last + span).tolist()


def apply(docs: DataFrame, marks: DataFrame, id_col: str, function: Callable, fields: str) -> DataFrame:
    """``function(text bytes, interval starts, interval ends, n) -> values of fields`` for every row of ``docs`` (as named() gives them).

    marks: (id, th, a, b) intervals of symbols, and where there is a column ``n`` rows without an interval whose n are summed. Texts travel compressed.
    """
    counted = "n" in marks.columns
    each = marks.groupBy("id", "th").agg(F.collect_list(F.when(F.col("b").isNotNull(), F.struct("a", "b"))).alias("marks"), (F.sum("n") if counted else F.lit(0).cast("long")).alias("n"))
    kind = docs.schema["original"].dataType.simpleString()

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        press = zstandard.ZstdCompressor(level=1)
        for b in batches:
            raw, off = ts.text_buffers(b.column(3))
            whole, at = raw.data, off.tolist()
            yield pa.RecordBatch.from_arrays([*b.columns[:3], pa.array([press.compress(whole[x:y]) for x, y in zip(at, at[1:])], pa.binary())], names=["original", "id", "th", "z"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        press = zstandard.ZstdDecompressor()
        none = (np.zeros(0, np.int64),) * 2
        for b in batches:
            rows = []
            for z, m, n in zip(b.column(1), b.column(2), b.column(3).to_pylist()):
                rows.append(function(press.decompress(z.as_py()), *([x.to_numpy() for x in m.values.flatten()] if m.is_valid and len(m) else none), n or 0))
            if rows:
                yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(x) for x in zip(*rows))], names=[id_col, *names])

    names = [x.split()[0] for x in fields.split(", ")]
    pressed = docs.mapInArrow(lean(pack), f"original {kind}, id long, th long, z binary")
    return pressed.join(each, ["id", "th"], "left").select("original", "z", "marks", "n").mapInArrow(lean(run), f"`{id_col}` {kind}, {fields}")


def whole_marks(members: DataFrame, groups: DataFrame, span: int, keep_first: bool) -> DataFrame:
    """(id, th, a, b) intervals of regions whose content is at several places; without the first place if that is to stay."""
    many = groups.where("many").select("h", "rh", "rows", *(F.col(c).alias(f"{c}0") for c in PLACE))
    rows = attach(members, many, ["h", "rh"], "rows")
    if keep_first:
        rows = rows.where("id != id0 or th != th0 or at != at0")
    a = F.col("at").cast("long")
    return rows.select("id", "th", a.alias("a"), (a + F.col("n") - 1 + span).alias("b"))


def part_marks(found: DataFrame) -> DataFrame:
    """Intervals found inside regions: (id, th, at) and bounds relative to the region's first window."""
    return found.select("id", "th", *((F.col("at") + F.col(c)).alias(c) for c in ("a", "b")))
