"""Language identification: multinomial naive Bayes over hashed character n-grams.

Counts come from every labelled row in one pass; what reaches the driver is one count per language
and hash bin, a size fixed by the parameters. Scoring gathers rows of the broadcast log-probability
matrix for all n-grams of a batch and sums them per text.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from .lean import lean

#: Character n-gram lengths, hash bins, additive smoothing.
ORDERS = (1, 2, 3)
BINS = 1 << 15
ALPHA = 0.5
#: Languages a model may have; the matrix then takes at most 256 MB.
MAX_LANGS = 1024
#: Characters scored at once.
GROUP_CHARS = 1 << 17
UNDETERMINED = "und"


@dataclass
class Bayes:
    langs: list[str]
    prior: np.ndarray
    weights: np.ndarray  # (bins, languages) log probabilities


def _groups(texts: list[str]) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, bins, owners from 0) as grams() gives them, some texts at a time and a long text in pieces."""
    row = 0
    while row < len(texts):
        to, size = row, 0
        while to < len(texts) and (size < GROUP_CHARS or to == row):
            size += len(texts[to])
            to += 1
        if size <= 2 * GROUP_CHARS:
            yield row, *grams([" " + t.lower() + " " for t in texts[row:to]])
        else:
            for k in range(row, to):
                text, most = " " + texts[k].lower() + " ", max(ORDERS) - 1
                for at in range(0, len(text), GROUP_CHARS):  # n-grams that start in this piece
                    piece = text[at : at + GROUP_CHARS + most]
                    bins, _ = grams([piece], min(GROUP_CHARS, len(text) - at))
                    yield k, bins, np.zeros(len(bins), np.int64)
        row = to


def grams(padded: list[str], starts: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(bin of every n-gram, number of the text it is in) of texts that are lower-cased and padded by a space; only n-grams at the first ``starts`` places, if given."""
    points = np.frombuffer("".join(padded).encode("utf-32-le", "surrogatepass"), dtype=np.uint32).astype(np.uint64)
    owner = np.repeat(np.arange(len(padded)), [len(p) for p in padded])
    bins, owners = [], []
    for n in ORDERS:
        if len(points) < n:
            continue
        m = len(points) - n + 1 if starts is None else min(starts, len(points) - n + 1)
        h = np.full(m, n, dtype=np.uint64)
        for k in range(n):
            h = (h ^ points[k : k + m]) * np.uint64(0x9E3779B97F4A7C15)
            h ^= h >> np.uint64(29)
        inside = owner[:m] == owner[n - 1 : n - 1 + m]
        bins.append((h[inside] >> np.uint64(20)).astype(np.int64) & (BINS - 1))
        owners.append(owner[:m][inside])
    if not bins:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.concatenate(bins), np.concatenate(owners)


def has_letter(text: str) -> bool:
    return any(map(str.isalpha, text))


def fit(rows: DataFrame, text_col: str = "text", lang_col: str = "lang", alpha: float = ALPHA) -> Bayes:
    """Learn from all rows with a text and a language; with none, the model knows no language."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names: dict[str, int] = {}
        table = np.zeros((0, BINS), dtype=np.int64)
        docs: list[int] = []
        for b in batches:
            texts, langs = b.column("t").to_pylist(), b.column("l").to_pylist()
            for lang in langs:
                if lang not in names:
                    names[lang] = len(names)
                    table = np.vstack([table, np.zeros((1, BINS), np.int64)])
                    docs.append(0)
                docs[names[lang]] += 1
            codes = np.asarray([names[x] for x in langs], dtype=np.int64)
            for row, at, owner in _groups(texts):
                table += np.bincount(codes[row + owner] * BINS + at, minlength=len(names) * BINS).reshape(-1, BINS)
        for lang, k in names.items():
            at = np.flatnonzero(table[k])
            yield pa.RecordBatch.from_arrays([pa.array([lang] * (len(at) + 1), pa.string()), pa.array(np.concatenate(([-1], at)), pa.int64()), pa.array(np.concatenate(([docs[k]], table[k][at])), pa.int64())], names=["lang", "bin", "n"])

    labelled = rows.where(F.col(text_col).isNotNull() & F.col(lang_col).isNotNull()).select(F.col(text_col).alias("t"), F.col(lang_col).cast("string").alias("l"))
    counts = labelled.mapInArrow(lean(count), "lang string, bin long, n long").groupBy("lang", "bin").agg(F.sum("n").alias("n"))
    got = counts.groupBy("lang").agg(F.collect_list(F.struct("bin", "n")).alias("bins")).limit(MAX_LANGS + 1).toArrow()
    if got.num_rows > MAX_LANGS:
        raise ValueError(f"more than {MAX_LANGS} languages")
    table = sorted(zip(got.column("lang").to_pylist(), (x.values for x in got.column("bins"))))
    langs = [x[0] for x in table]
    counts_m, prior = np.zeros((BINS, len(langs))), np.zeros(len(langs))
    for k, (_, bins) in enumerate(table):
        at, n = bins.field("bin").to_numpy(), bins.field("n").to_numpy()
        counts_m[at[at >= 0], k] = n[at >= 0]
        prior[k] = n[at < 0].sum()
    if not langs:
        return Bayes([], prior, counts_m)
    weights = np.log(counts_m + alpha) - np.log(counts_m.sum(axis=0) + alpha * BINS)
    return Bayes(langs, np.log(prior / prior.sum()), np.ascontiguousarray(weights.astype(np.float32)))


def score(model: Bayes, texts: list[str | None]) -> tuple[list[str], list[float]]:
    """Most probable language and its posterior probability; ties go to the first in alphabetical order."""
    langs, values = [UNDETERMINED] * len(texts), [0.0] * len(texts)
    if not model.langs:
        return langs, values
    plain = [t or "" for t in texts]
    total = np.zeros((len(plain), len(model.langs))) + model.prior
    for row, bins, owner in _groups(plain):
        n = int(owner.max()) + 1 if len(owner) else 0
        for k in range(len(model.langs)):
            total[row : row + n, k] += np.bincount(owner, weights=model.weights[:, k][bins], minlength=n)
    best = total.argmax(axis=1)
    share = 1.0 / np.exp(total - total.max(axis=1, keepdims=True)).sum(axis=1)
    for k, text in enumerate(plain):
        if has_letter(text):
            langs[k], values[k] = model.langs[best[k]], float(share[k])
    return langs, values


def identify(docs: DataFrame, model: Bayes, text_col: str = "text", lang_out: str = "lang_pred", score_out: str = "score") -> DataFrame:
    """``docs`` with the predicted language and its probability.

    ``und`` and 0 for a null text, one without a letter, or a model without languages. All other
    columns stay as they are; columns of the two output names are replaced. An empty table gives
    an empty result; repeated rows get equal predictions.
    """
    kept = [c for c in docs.columns if c not in (lang_out, score_out)]
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            langs, values = score(shared.value, b.column(b.num_columns - 1).to_pylist())
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(langs, pa.string()), pa.array(values, pa.float64())], names=[*kept, lang_out, score_out])

    schema = "".join(f"`{c}` {docs.schema[c].dataType.simpleString()}, " for c in kept)
    return docs.select(*kept, F.col(text_col).alias("__text")).mapInArrow(lean(run), f"{schema}`{lang_out}` string, `{score_out}` double")


def held_out(id_col: str = "doc_id") -> Column:
    """The fold kept from learning: crc32 of the id as text leaves 2 on division by 4. A null id is in no fold."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 4 == 2, F.lit(False))
