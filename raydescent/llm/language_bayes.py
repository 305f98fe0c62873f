"""Language identification: multinomial naive Bayes over hashed character n-grams.

Fitting: a bounded, hash-chosen sample of labelled texts is counted by language and n-gram bucket on the executors.
Scoring: the matrix of log-probabilities (languages x buckets, a size set by parameters) is broadcast. The n-grams of a
batch of whole texts are one sparse matrix of counts (text, bucket, count), which is multiplied with it in numpy.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from raydescent.llm.common import spare

UNKNOWN = "und"
#: Candidates for letters; isalpha() then leaves out the numerals among them, such as superscripts and fractions.
_WORD = re.compile(r"[^\W\d_]")
#: Characters of a batch that are worked off at a time.
_STEP = 1 << 18


@dataclass(frozen=True)
class NgramModel:
    languages: tuple[str, ...]
    log_probs: np.ndarray  # buckets x languages
    log_priors: np.ndarray
    orders: tuple[int, ...]


def has_letter(text: str) -> bool:
    """Whether a character of the text is of a letter category (L) of Unicode."""
    return any(m.group().isalpha() for m in _WORD.finditer(text))


def ngram_rows(texts: list[str], orders: tuple[int, ...], buckets: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(text, bucket) of every n-gram of the lower-cased texts, in bounded portions; a long text is in several of them."""
    most = max(orders)

    def pieces():
        for row, text in enumerate(texts):
            low = text.lower()
            for at in range(0, len(low), _STEP):
                yield row, low[at : at + _STEP + most - 1], min(_STEP, len(low) - at)

    def portion(held):
        c = np.frombuffer("".join(p for _, p, _ in held).encode("utf-32-le", "surrogatepass"), "<u4")
        size, own = (np.array(x, np.int64) for x in zip(*((len(p), n) for _, p, n in held)))
        stop = np.cumsum(size)
        row = np.repeat(np.array([r for r, _, _ in held], np.int64), size)
        place = np.arange(len(c)) - np.repeat(stop - size, size)
        left = np.repeat(size, size) - place  # characters from here to the end of the piece
        counts = place < np.repeat(own, size)  # n-grams that start beyond belong to the text's next piece
        for n in orders:
            at = np.flatnonzero(counts & (left >= n))
            h = np.full(len(at), n, np.uint32)
            for i in range(n):
                h = (h ^ c[at + i]) * np.uint32(0x9E3779B1)
                h ^= h >> np.uint32(15)
            yield row[at], (h & np.uint32(buckets - 1)).astype(np.int64)

    held, size = [], 0
    for piece in pieces():
        held.append(piece)
        size += len(piece[1])
        if size >= _STEP:
            yield from portion(held)
            held, size = [], 0
    if held:
        yield from portion(held)


def ngram_counts(text: str, orders: tuple[int, ...], buckets: int) -> np.ndarray:
    """How often each bucket's n-grams occur in the whole lower-cased text."""
    total = np.zeros(buckets, np.int64)
    for _, at in ngram_rows([text], orders, buckets):
        total += np.bincount(at, minlength=buckets)
    return total


def _fold(batches, orders, buckets):
    sums: dict[str, np.ndarray] = {}
    docs: dict[str, int] = {}
    for batch in batches:
        langs, texts = batch.column("lang").to_pylist(), batch.column("text").to_pylist()
        for lang in set(langs):
            own = [t for t, x in zip(texts, langs) if x == lang]
            total = sums.setdefault(lang, np.zeros(buckets, np.int64))
            for _, at in ngram_rows(own, orders, buckets):
                total += np.bincount(at, minlength=buckets)
            docs[lang] = docs.get(lang, 0) + len(own)
    for lang, s in sums.items():
        at = np.flatnonzero(s)
        yield pa.RecordBatch.from_pydict({"lang": [lang], "docs": [docs[lang]], "at": [at.astype(np.int32)], "n": [s[at]]})


def fit(docs: DataFrame, lang_col: str = "lang", id_col: str = "doc_id", text_col: str = "text", most_rows: int = 20_000, orders: tuple[int, ...] = (2, 3), buckets: int = 1 << 14, smoothing: float = 0.5) -> NgramModel:
    """Learn from at most about most_rows labelled rows (null texts and labels are left out), chosen by a hash of the id.

    buckets must be a power of two. The languages (some hundreds at most) are those in the sample; an empty sample gives a model without any,
    which answers UNKNOWN. At most one row per language and task, of bounded size, comes to the driver as a sum.
    """
    rows = docs.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(lang_col).cast("string").alias("lang"), F.col(text_col).alias("text"), F.col(id_col).alias("id"))
    n = rows.count()
    if n > most_rows:
        rows = rows.where(F.shiftrightunsigned(F.xxhash64("id"), 11) < int(2**53 * most_rows / n))
    part = rows.select("lang", "text").mapInArrow(lambda b: _fold(b, orders, buckets), "lang string, docs long, at array<int>, n array<long>")
    cells = part.select("lang", "docs", F.explode(F.arrays_zip("at", "n")).alias("c")).groupBy("lang", "c.at").agg(F.sum("c.n").alias("n"))
    sums: dict[str, np.ndarray] = {}
    for lang, at, k in cells.groupBy("lang").agg(F.collect_list("at"), F.collect_list("n")).collect():  # languages x buckets numbers
        sums[lang] = np.zeros(buckets)
        sums[lang][at] = k
    languages = tuple(sorted(sums))
    if not languages:
        return NgramModel((), np.zeros((buckets, 0)), np.zeros(0), orders)
    counts = np.stack([sums[x] for x in languages], axis=1) + smoothing
    return NgramModel(languages, np.log(counts / counts.sum(axis=0)), np.log(np.full(len(languages), 1 / len(languages))), orders)


def batch_scores(texts: list[str], model: NgramModel) -> np.ndarray:
    """texts x languages: log-prior and summed log-probabilities, by sparse counts of a portion of n-grams at a time."""
    scores = np.tile(model.log_priors, (len(texts), 1))
    buckets = len(model.log_probs)
    for row, bucket in ngram_rows(texts, model.orders, buckets):
        if not len(row):
            continue
        first = row[0]  # rows ascend within a portion
        cell, many = np.unique((row - first) * buckets + bucket, return_counts=True)
        text, at = first + cell // buckets, cell % buckets
        for j in range(len(model.languages)):
            scores[:, j] += np.bincount(text, weights=many * model.log_probs[at, j], minlength=len(texts))
    return scores


def identify(texts: list[str | None], model: NgramModel) -> list[tuple[str, float]]:
    """Language and posterior share of each text; null, empty and letterless texts are UNKNOWN with share 0."""
    out = [(UNKNOWN, 0.0)] * len(texts)
    known = [i for i, t in enumerate(texts) if t is not None and has_letter(t)] if model.languages else []
    if known:
        scores = batch_scores([texts[i] for i in known], model)
        shares = np.exp(scores - scores.max(axis=1, keepdims=True))
        best = scores.argmax(axis=1)
        for i, b, s in zip(known, best.tolist(), (shares[np.arange(len(best)), best] / shares.sum(axis=1)).tolist()):
            out[i] = (model.languages[b], s)
    return out


def predict(docs: DataFrame, model: NgramModel, text_col: str = "text", names: tuple[str, str] = ("lang_pred", "score")) -> DataFrame:
    """docs with the predicted language and its score (the posterior share) under names; null, empty and letterless texts
    are 'und' with score 0. Columns of those names in docs are replaced.
    """
    held = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("lang string, share double")
    def guess(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for texts in batches:
            yield pd.DataFrame(identify(texts.tolist(), held.value), columns=["lang", "share"])

    rows = docs.drop(*names)
    (found,) = spare([*docs.columns, *names], "_guess")
    kept = [F.col(f"`{c}`") for c in rows.columns]
    return rows.withColumn(found, guess(F.col(text_col))).select(*kept, F.col(found)["lang"].alias(names[0]), F.col(found)["share"].alias(names[1]))


def learned_rows(id_col: Column) -> Column:
    """Rows that may be learned from: crc32 of the id as text, modulo 4, is not 2. A null id counts as empty text."""
    return F.crc32(F.coalesce(id_col.cast("string"), F.lit("")).cast("binary")) % 4 != 2
