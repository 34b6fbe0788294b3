"""The pipeline's stages against plain versions and planted cases."""

import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import corpus_pipeline as cp
from nearsort.llm import shingles, simhash, suffixes

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def table(spark, rows):
    return spark.createDataFrame([(i, t, lang, "s", len(t or "")) for i, t, lang in rows], SCHEMA)


def prose(seed, n, letters="abcdefgh"):
    r = random.Random(seed)
    return ["".join(r.choices(letters, k=r.randint(2, 7))) for _ in range(n)]


# substrings


def plain_passages(rows, span):
    words = {i: list(re.finditer(rb"[^\x20\x09-\x0D]+", (t or "").encode())) for i, t in rows}
    count = Counter(tuple(m[0] for m in w[k : k + span]) for w in words.values() for k in range(len(w) - span + 1))
    out = {}
    for i, t in rows:
        b, w, gone = (t or "").encode(), words[i], set()
        for k in range(len(w) - span + 1):
            if count[tuple(m[0] for m in w[k : k + span])] > 1:
                gone.update(range(k, k + span))
        edge = [m.start() for m in w] + [len(b)]
        keep = np.ones(len(b), bool)
        for k in gone:
            keep[edge[k] : edge[k + 1]] = False
        out[i] = bytes(np.frombuffer(b, np.uint8)[keep]).decode("utf-8", "ignore") if t is not None else None
    return out


@pytest.mark.parametrize("together, shard", [(4096, 1 << 19), (1, 500)])
def test_passages(spark, docs, odd, together, shard):
    for df in (docs, odd.where("doc_id is not null").dropDuplicates(["doc_id"]), odd.limit(0)):
        rows = [(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()]
        got = {r.doc_id: r.text for r in suffixes.cut_passages(df, together=together, shard=shard).collect()}
        assert got == plain_passages(rows, 51)


def test_short_passages_of_over_50_words_are_cut(spark, data):
    p, q = " ".join(prose(1, 51, "ab")), " ".join(prose(2, 50, "ab"))
    assert len(p) < 400
    own = [" ".join(prose(k, 80)) for k in range(10, 18)]
    rows = [(0, f"{own[0]} {p}\n{own[1]}", "en"), (1, f"{own[2]}\n{p} {own[3]}", "en"), (2, f"{own[4]} {q} {own[5]}", "en"), (3, f"{own[6]} {q} {own[7]}", "en")]
    got = {r.doc_id: (r.text, r.n_chars) for r in cp.cut_repeated_substrings(spark, table(spark, rows), data).collect()}
    want = [f"{own[0]} {own[1]}", f"{own[2]}\n{own[3]}", rows[2][1], rows[3][1]]
    assert [got[k] for k in range(4)] == [(t, len(t)) for t in want]


def test_a_passage_does_not_start_inside_a_word(spark):
    p = " ".join(prose(1, 50))
    rows = [(k, f"{' '.join(prose(20 + k, 40))} {w} {p} {' '.join(prose(30 + k, 40))}", "en") for k, w in enumerate(("bathe", "the"))]
    assert {r.doc_id: r.text for r in suffixes.cut_passages(table(spark, rows)).collect()} == {i: t for i, t, _ in rows}



# near-duplicates


def plain_clusters(rows):
    sets = {}
    for i, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} or ({tuple(w)} if w else set())
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in sorted(sets):
        for b in sorted(sets):
            both = len(sets[a] & sets[b])
            if a < b and 5 * both >= 4 * (len(sets[a]) + len(sets[b]) - both):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {i for i in sets if find(i) == i}


def test_near_duplicates_are_those_of_similar_shingles(spark, docs, odd, data):
    for df in (docs, odd.where("doc_id is not null").dropDuplicates(["doc_id"]).withColumns({"source": F.lit("s"), "n_chars": F.lit(0).cast("long")})):
        got = {r.doc_id for r in cp.drop_near_duplicates(spark, df, data).collect()}
        assert got == plain_clusters([(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()])


@pytest.mark.parametrize("texts, size", [(4, 1 << 30), (1 << 20, 5000)])
def test_components_too_large_for_a_task_are_split(spark, texts, size):
    """A chain that only neighbours link, and copies of one text with few and many changes: the same classes in chunks as whole."""
    rng, base = np.random.default_rng(4), prose(9, 120)
    rows, chain = [], base.copy()
    for k in range(60):
        chain = chain.copy()
        chain[int(rng.integers(5, 115))] = f"c{k}"  # some 5 of 116 shingles a step
        rows.append((k, " ".join(chain), "en"))
    star = prose(10, 120)
    for k in range(60, 120):
        near = star.copy()
        for x in rng.integers(0, 120, 3 if k % 4 else 6):
            near[x] = f"s{k}"
        rows.append((k, " ".join(near), "en"))
    docs = table(spark, rows)

    def kept(**bounds):
        found = defaultdict(set)
        for r in shingles.clusters(docs, **bounds).collect():
            found[bytes(r.head)].add(r.id)
        return sorted(map(sorted, found.values()))

    whole = kept()
    assert kept(texts=texts, size=size) == whole
    assert {c[0] for c in whole} == plain_clusters([(i, t) for i, t, _ in rows])


def test_near_copies_beyond_three_bits_meet(spark, data):
    rows = []
    for k in range(40):
        a, b, c = (prose(s + k, 200) for s in (1000, 2000, 3000))
        near, far = a.copy(), a.copy()
        for x in range(3):
            near[20 + 50 * x] = c[x]  # 15 of 196 shingles change: 0.86
        for x in range(8):
            far[5 + 24 * x] = c[x]  # 40 change: 0.66
        rows += [(4 * k, " ".join(a), "en"), (4 * k + 1, " ".join(near).upper(), "en"), (4 * k + 2, "\n".join(far), "en"), (4 * k + 3, " ".join(b), "en")]
    got = {r.doc_id for r in cp.drop_near_duplicates(spark, table(spark, rows), data).collect()}
    assert got == {i for i in range(160) if i % 4 != 1}


def test_covering_simhash_alone_brings_near_texts_together(spark, monkeypatch):
    """Without any band, what is within three bits of the five-word fingerprints meets and is verified, and nothing else."""
    monkeypatch.setattr(shingles, "_by_bands", lambda distinct: distinct.select(F.col("dig").alias("a"), F.col("dig").alias("b")).limit(0))
    rows, near = [], set()
    for k in range(30):
        one = prose(4000 + k, 300)
        other = [*one[:-1], f"x{k}"] if k % 2 else [*one[:100], *(f"x{n}" for n in range(40)), *one[140:]]
        rows += [(2 * k, " ".join(one), "en"), (2 * k + 1, " ".join(other), "en")]
        a, b = simhash.column_fingerprints(pa.array([" ".join(one), " ".join(other)]), 5)
        if (a ^ b).bit_count() <= 3 and shingles.alike(*(shingles.shingles(" ".join(x).encode()) for x in (one, other))):
            near.add(2 * k + 1)
    assert 5 < len(near) < 30
    assert {r.doc_id for r in shingles.keep_one(table(spark, rows)).collect()} == set(range(60)) - near


def test_texts_of_one_id_are_told_apart(spark):
    rows = [(1, " ".join(prose(1, 30)), "en"), (1, " ".join(prose(2, 30)), "en"), (1, " ".join(prose(1, 30)), "en"), (None, "x y", "en"), (None, "x y", "en")]
    assert sorted(r.doc_id or 0 for r in shingles.keep_one(table(spark, rows)).collect()) == [0, 0, 1, 1]


# language


def planted_languages():
    """(id, text, lang): each language has the words they share and the same words in letters of its own."""
    ids = [i for i in range(400) if zlib.crc32(str(i).encode()) % 4 != 2]
    shared = " ".join(prose(5, 60, "mnop"))
    letters = {"en": "abcd", "de": "efgh", "fr": "qrst", "xx": "uvwx"}
    rows = [(i, shared + " " + " ".join(prose(7, 60, "abcd")).translate(str.maketrans("abcd", letters[lang])), lang) for i, lang in zip(ids, [*letters] * 10)]
    own = {lang: " ".join(prose(8, 40, "abcd")).translate(str.maketrans("abcd", x)) for lang, x in letters.items()}
    return rows, own, shared


def test_language_is_decided_by_the_prediction(spark, data):
    rows, own, shared = planted_languages()
    cases = [(1000, own["en"], None), (1001, own["de"], "xx"), (1002, own["xx"], "en"), (1003, own["xx"], None), (1004, shared.split()[0], None), (1005, "12 34", "en"), (1006, None, "en")]
    cases = [(1000 + 8 * k + next(n for n in range(8) if zlib.crc32(str(1000 + 8 * k + n).encode()) % 4 == 2), t, lang) for k, (_, t, lang) in enumerate(cases)]
    got = {r.doc_id for r in cp.identify_language(spark, table(spark, rows + cases), data).collect()}
    assert got == {i for i, _, lang in rows if lang != "xx"} | {cases[0][0], cases[1][0]}


def test_nothing_to_learn_from_drops_no_language(spark, data):
    rows, _, _ = planted_languages()
    blank = [(i, t, None) for i, t, _ in rows] + [(2000, "12 34", None), (2001, None, None)]
    assert {r.doc_id for r in cp.identify_language(spark, table(spark, blank), data).collect()} == {i for i, _, _ in rows}
