"""Language identification: multinomial logistic regression on TF-IDF of character n-grams.

Features are hashed n-grams of one to three characters of the lower-cased text, weighted by term and inverse document
frequency and scaled to unit length. Weights are fitted by follow-the-regularised-leader with elastic-net penalties, so
most stay exactly zero; a temperature, fitted on a part of the rows that the weights never saw, calibrates the scores.
The classifier is fitted on a bounded sample of the distinct labelled rows (``sample_rows``, spread over the table by a hash
of the row, each whole); scoring reads every row and whole text.

Defined results: ``und`` with score 0 where the text is null, has no letter, or nothing could be learned; equal scores go to
the language that sorts first; rows with a null label are not learned from; an empty table gives no rows.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from orthant.functions.shipping import ship

from .common import distinct_sample

BUCKETS_LOG2, ORDERS = 15, (1, 2, 3)
#: Most labelled rows that the fit takes, and the part of them kept for the temperature.
SAMPLE_ROWS, HELD_FOR_TEMPERATURE = 3000, 0.2
ALPHA, BETA, L1, L2, EPOCHS = 2.0, 1.0, 0.02, 0.5, 3
UNKNOWN = "und"
#: A letter, for learning and for prediction alike; signs that are numbers, such as ½, ① and ², are none.
LETTER = r"\p{L}"
_LETTER = regex.compile(LETTER)
_MIX = (np.uint32(2654435761), np.uint32(2246822519), np.uint32(3266489917))
#: Characters hashed together, so that memory follows one stretch of a long text.
STRETCH = 1 << 18


def grams(text: str, bits: int = BUCKETS_LOG2) -> np.ndarray:
    """Counts of the hashed n-grams of the whole text."""
    total = np.zeros(1 << bits, dtype=np.int64)
    low = text.lower()
    for at in range(0, len(low), STRETCH):
        c = np.frombuffer(low[at : at + STRETCH + max(ORDERS) - 1].encode("utf-32-le", "surrogatepass"), dtype="<u4")
        last = at + STRETCH >= len(low)
        for n in ORDERS:
            size = len(c) - n + 1 if last else STRETCH
            if size <= 0:
                continue
            h = np.full(size, n, dtype=np.uint32) * _MIX[2]
            for k in range(n):
                h = (h ^ c[k : k + size]) * _MIX[k % 2]
                h ^= h >> np.uint32(15)
            total += np.bincount(h >> np.uint32(32 - bits), minlength=1 << bits)
    return total


@dataclass
class LanguageModel:
    languages: list[str]
    idf: np.ndarray
    weights: np.ndarray  # buckets x languages
    temperature: float

    def logits(self, counts: np.ndarray) -> np.ndarray:
        x = np.log1p(counts) * self.idf  # damped, so that a passage repeated many times doesn't outweigh the rest
        return (x @ self.weights) / max(1e-12, float(np.sqrt(x @ x)))

    def predict(self, text: str | None) -> tuple[str, float]:
        if not text or not self.languages or not _LETTER.search(text):
            return UNKNOWN, 0.0
        z = self.logits(grams(text)) / self.temperature
        p = np.exp(z - z.max())
        p /= p.sum()
        k = int(p.argmax())
        return self.languages[k], float(p[k])


def fit_ftrl(rows: list[tuple[np.ndarray, np.ndarray]], labels: np.ndarray, classes: int, buckets: int, seed: int = 42) -> np.ndarray:
    """Weights (buckets x classes) of sparse rows (indices, values), one pass after another in a seeded order."""
    z, n, rng = np.zeros((buckets, classes)), np.zeros((buckets, classes)), np.random.default_rng(seed)

    def current(at: np.ndarray) -> np.ndarray:
        zi = z[at]
        return np.where(np.abs(zi) <= L1, 0.0, -(zi - np.sign(zi) * L1) / ((BETA + np.sqrt(n[at])) / ALPHA + L2))

    for _ in range(EPOCHS):
        for r in rng.permutation(len(rows)):
            at, x = rows[r]
            w = current(at)
            s = x @ w
            p = np.exp(s - s.max())
            p /= p.sum()
            p[labels[r]] -= 1
            g = x[:, None] * p[None, :]
            root = np.sqrt(n[at])
            z[at] += g - (np.sqrt(n[at] + g * g) - root) / ALPHA * w
            n[at] += g * g
    return current(np.arange(buckets))


def fit_temperature(logits: np.ndarray, labels: np.ndarray) -> float:
    """The temperature of least log loss, from a grid over four decades."""
    def loss(t: float) -> float:
        s = logits / t
        s = s - s.max(axis=1, keepdims=True)
        return float(np.mean(np.log(np.exp(s).sum(axis=1)) - s[np.arange(len(labels)), labels]))

    return min(np.geomspace(0.01, 100, 161), key=lambda t: (loss(t), t)) if len(labels) else 1.0


def fit(rows: list[tuple[np.ndarray, np.ndarray]], labels: list[str]) -> LanguageModel:
    """rows: (indices, counts) of each training text; the first part fits the weights, the rest the temperature."""
    languages = sorted(set(labels))
    buckets = 1 << BUCKETS_LOG2
    if not languages:
        return LanguageModel([], np.zeros(buckets), np.zeros((buckets, 0)), 1.0)
    y = np.array([languages.index(x) for x in labels])
    df = np.zeros(buckets)
    for at, _ in rows:
        df[at] += 1
    idf = np.log((1 + len(rows)) / (1 + df)) + 1

    def scaled(at: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        x = np.log1p(n) * idf[at]
        return at, x / max(1e-12, float(np.sqrt(x @ x)))

    every = [scaled(at, n) for at, n in rows]
    cut = max(1, round(len(rows) * (1 - HELD_FOR_TEMPERATURE)))
    weights = fit_ftrl(every[:cut], y[:cut], len(languages), buckets)
    held = np.array([x @ weights[at] for at, x in every[cut:]]).reshape(-1, len(languages))
    return LanguageModel(languages, idf, weights, float(fit_temperature(held, y[cut:])))


def _sparse_grams(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for lang, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            c = grams(text)
            at = np.flatnonzero(c)
            yield pa.RecordBatch.from_arrays([pa.array([lang]), pa.array([at.astype("<u4").tobytes()]), pa.array([c[at].astype("<u4").tobytes()])], ["lang", "at", "n"])


def _fit_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One row: the model of all rows of the task, fitted in an order by content, so that it doesn't follow the partitions."""
    found = [r for batch in batches for r in zip(*(batch.column(c).to_pylist() for c in ("lang", "at", "n")), strict=True)]
    found.sort(key=lambda r: (hash_of(r[1], r[2]), r[0]))
    model = fit([(np.frombuffer(at, dtype="<u4"), np.frombuffer(n, dtype="<u4")) for _, at, n in found], [lang for lang, _, _ in found])
    yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(model)], pa.binary())], ["model"])


def train(docs: DataFrame, learn: Column, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", sample_rows: int = SAMPLE_ROWS) -> LanguageModel:
    """Fit on at most sample_rows of the distinct rows that learn marks and that have a label and a letter; in one task, not on the driver."""
    ship(docs.sparkSession)
    able = docs.where(learn & F.col(lang_col).isNotNull() & F.rlike(text_col, F.lit(LETTER)))
    texts = distinct_sample(able.select(F.col(id_col).alias("id"), F.col(lang_col).alias("lang"), F.col(text_col).alias("text")), sample_rows, docs.count(), 8)
    found = texts.select("lang", "text").mapInArrow(_sparse_grams, "lang string, at binary, n binary").repartition(1).mapInArrow(_fit_rows, "model binary").collect()
    return pickle.loads(found[0]["model"]) if found else fit([], [])


def hash_of(*parts: bytes) -> int:
    import zlib

    at = 0
    for p in parts:
        at = zlib.crc32(p, at)
    return at


def _score(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        for batch in batches:
            told = [model.predict(t.as_py()) for t in batch.column("text")]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array([x[0] for x in told], pa.string()), pa.array([x[1] for x in told], pa.float64())], ["doc_id", "held_out", "lang_pred", "score"])

    return run


def held_out(id_col: str, parts: int, part: int) -> Column:
    return F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")) % parts == part


def identify(docs: DataFrame, model: LanguageModel, held: Column, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, lang_pred, score of every row."""
    ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    read = docs.select(F.col(id_col).cast("long").alias("doc_id"), held.alias("held_out"), F.col(text_col).alias("text"))
    return read.mapInArrow(_score(shared), "doc_id long, held_out boolean, lang_pred string, score double")


def _keep(shared, least: float, text_col: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        for batch in batches:
            told = [model.predict(t.as_py()) for t in batch.column(text_col)]
            yield batch.filter(pa.array([lang != UNKNOWN and s >= least for lang, s in told], pa.bool_()))

    return run


def keep_identified(docs: DataFrame, least: float = 0.3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs without those that have no letter or no language of at least this score, all columns kept."""
    model = train(docs, ~held_out(id_col, 4, 2), id_col, text_col)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    return docs.mapInArrow(_keep(shared, least, text_col), docs.schema)


def languages(docs: DataFrame) -> DataFrame:
    """Train on the rows whose remainder by 4 is not 2, then predict every row."""
    held = held_out("doc_id", 4, 2)
    return identify(docs, train(docs, ~held), held)
