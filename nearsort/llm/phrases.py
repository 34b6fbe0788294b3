"""Repeated phrases by sharded Aho-Corasick automata.

Candidate passages come keyed by anchor, so equal windows meet in one shard. A shard confirms by
the words themselves which windows recur, compiles them into automata of bounded size, and
streams its passages through them in document order to locate every occurrence.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import recurrence as rec, textscan as ts
from .lean import lean

#: Words of a phrase, of its anchor; windows that one automaton is compiled from.
SPAN, GRAM = 20, 8
SHARD_WINDOWS = 50_000


def locate(rows: list[tuple], tokens: int, seen: set[str]) -> Iterator[tuple[int, list[int]]]:
    """(row, starts of windows met before) for passages in document order; ``seen``: windows of their key met earlier."""
    texts = [list(filter(None, left.decode().split(" "))) + ["\t" + gram.hex()] + list(filter(None, right.decode().split(" "))) for left, gram, right in rows]
    count: dict[str, int] = {}
    for t in texts:
        for k in range(len(t) - tokens + 1):
            w = " ".join(t[k : k + tokens])
            count[w] = count.get(w, 0) + 1
    confirmed = [w for w, n in count.items() if n > 1 or w in seen]
    if confirmed:
        automaton = ahocorasick.Automaton()
        for k, w in enumerate(confirmed):
            automaton.add_word(f" {w} ", k)
        automaton.make_automaton()
        met = [w in seen for w in confirmed]
        for row, t in enumerate(texts):
            line = f" {' '.join(t)} "
            ends = {int(e): k for k, e in enumerate(np.cumsum([len(w) + 1 for w in t]))}
            later = []
            for end, k in automaton.iter(line):
                if met[k]:
                    later.append(ends[end] - tokens + 1)
                met[k] = True
            if later:
                yield row, later
    seen.update(count)


def _search(batches: Iterator[pa.RecordBatch], span: int, gram: int, shard: int) -> Iterator[pa.RecordBatch]:
    tokens = span - gram + 1
    rows, spots, windows, key, seen = [], [], 0, None, set()
    names = [*rec.PLACE, "a", "b"]

    def flush() -> pa.RecordBatch:
        out: list[list[int]] = [[] for _ in names]
        for row, starts in locate(rows, tokens, seen):
            *place, shift = spots[row]
            for interval in zip(*rec.merged(np.asarray(sorted(starts)) + shift, span)):
                for o, v in zip(out, (*place, *interval)):
                    o.append(v)
        return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in out], names=names)

    for b in batches:
        for k, i, th, at, shift, left, g, right, n in zip(*(c.to_pylist() for c in b.columns)):
            if k != key and windows >= shard:
                yield flush()
                rows, spots, windows = [], [], 0
                seen.clear()
            elif windows >= 2 * shard:  # a key of more windows than a shard goes on; what it has had stays known
                yield flush()
                rows, spots, windows = [], [], 0
            key = k
            rows.append((left, g, right))
            spots.append((i, th, at, shift))
            windows += n
    if rows:
        yield flush()


def removed(text: bytes, a: np.ndarray, b: np.ndarray, _: int) -> tuple[int, int, str]:
    data = np.frombuffer(text, dtype=np.uint8)
    start, end, _ = ts.words(data, np.asarray([0, len(data)]), ~ts.SPACE)
    keep = ~ts.cover(len(start), a, b) if len(a) else np.ones(len(start), bool)
    kept = b" ".join([text[x:y] for x, y in zip(start[keep].tolist(), end[keep].tolist())])
    return len(start), int(len(start) - keep.sum()), hashlib.sha256(kept).hexdigest()


def repeated_intervals(prepared: DataFrame, span: int = SPAN, gram: int = GRAM, together: int = rec.TOGETHER, shard: int = SHARD_WINDOWS, piece: int = rec.PIECE_BYTES) -> DataFrame:
    """(id, th, a, b): word intervals that windows met before cover; they may overlap."""
    members, groups, regions, _ = rec.find(prepared, rec.Units("words", span, gram, piece=piece), together)
    found = regions.mapInArrow(lean(lambda x: _search(x, span, gram, shard)), "id long, th long, at long, a long, b long")
    return rec.whole_marks(members, groups, span, keep_first=True).unionByName(rec.part_marks(found))


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", span: int = SPAN, gram: int = GRAM, together: int = rec.TOGETHER, shard: int = SHARD_WINDOWS, piece: int = rec.PIECE_BYTES) -> DataFrame:
    """n_words, n_removed and kept_sha256 of every document.

    A word goes if a window of ``span`` words over it also starts earlier: in a document of a smaller
    id, or earlier in its own. Documents of fewer words lose none. A null text has no words. A null
    id is the least. Rows that repeat an id with the same text count as one document and each get its
    result; other texts under one id are documents in an order of their own. An empty table gives an
    empty result; further columns are ignored.
    """
    prepared = rec.prepare(docs, id_col, text_col)
    marks = repeated_intervals(prepared, span, gram, together, shard, piece)
    return rec.apply(rec.named(docs, id_col, text_col), marks, id_col, removed, "n_words long, n_removed long, kept_sha256 string")

