"""Language-model scores: a word-level base and a causal self-attention model on subword ids.

1. One pass over all training documents counts words (by 64-bit digest); tasks fold their own counts first.
2. The words' counts give the subwords' counts, and these the output classes and units of the model.
3. A first fit, in one task, to a bounded, documented number of training words (``first_words``) gives the attention weights a
   common start; then every partition trains on all of its training documents, every token once, and the weights are
   averaged by the number of windows. The sums are of whole numbers, so they don't depend on the order of arrival; the
   weights do depend on how the table is split into partitions.
4. One pass scores every text: whole, in overlapping windows, each token once. The score is the attention model's alone.

Word counts are looked up in two ways, which together are exact: frequent words, at most about ``heavy``, go to the
workers as sorted arrays; occurrences of all other words are joined to their counts by digest. That is for the base only.

Defined results: null text is empty and consists of the end token; without training documents the base takes N = V = 0 and
the model its untrained start; repeated rows each get a row; an empty table gives no rows.
"""

from __future__ import annotations

import zlib
from collections import Counter, defaultdict
from collections.abc import Callable, Iterator
from itertools import chain, count, islice

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from orthant.functions.shipping import ship

from . import attention
from .common import whole_text, written
from .langid import held_out
from .tokens import RUN_CHARS, ByteLevelTokenizer, tokenizer

#: Words sent to the workers, words a task folds, words a task keeps encoded between two runs, words of the first fit, windows that its passes see at least.
HEAVY, FOLDED, KNOWN, FIRST_WORDS, FIRST_WINDOWS = 1_000_000, 500_000, 300_000, 400_000, 200_000
IDS, SEED = 50_257, 42
#: Weights are added up as whole multiples of its reciprocal.
GRAIN = 1 << 20


def digest(word: bytes) -> int:
    """The 64-bit hash that Spark's xxhash64 gives, as an unsigned number."""
    return xxhash.xxh64_intdigest(word, SEED)


class WordIds:
    """Subword ids of lower-cased words, each with a leading space.

    All words of a list are encoded in one call, joined: no match of the pre-tokenizer reaches over the space before a word,
    and words hold no space, so a token that begins with one begins a word. Lists that don't come apart so go word by word.
    """

    def __init__(self, path: str) -> None:
        self.tok = tokenizer(path, ByteLevelTokenizer)
        fast = self.tok.fast
        self.opens = None if fast is None else np.array([fast.decode_single_token_bytes(i)[:1] == b" " for i in range(fast.n_vocab)])

    def of(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all words in a row, how many each has)."""
        if self.opens is not None and words and max(map(len, words)) < RUN_CHARS:
            flat = self.tok.fast.encode_to_numpy((b" " + b" ".join(words)).decode("utf-8"), disallowed_special=())
            starts = np.flatnonzero(self.opens[flat])
            if len(starts) == len(words):
                return flat.astype(np.uint16), np.diff(np.append(starts, len(flat)))
        parts = [np.frombuffer(x, dtype="<u4") for x in self.tok.encode([" " + w.decode("utf-8") for w in words])]
        return np.concatenate([np.zeros(0, dtype=np.uint16), *(x.astype(np.uint16) for x in parts)]), np.array([len(x) for x in parts], dtype=np.int64)


_OPEN: dict[str, WordIds] = {}


def word_ids(path: str) -> WordIds:
    if path not in _OPEN:
        _OPEN[path] = WordIds(path)
    return _OPEN[path]


class Known:
    """Words met so far, numbered as they came, with their subword ids, digests and whatever else is told of new ones.

    A word is encoded once however many runs it is in. Beyond ``KNOWN`` words all are forgotten before the next run.
    """

    def __init__(self, ids: WordIds) -> None:
        self.ids = ids
        self.forget()

    def forget(self) -> None:
        self.place: dict[bytes, int] = defaultdict(count().__next__)
        self.flat, self.length, self.values = np.zeros(0, dtype=np.uint16), np.zeros(0, dtype=np.int64), {}

    def numbers(self, words: Iterator[bytes], n: int) -> np.ndarray:
        if len(self.place) > KNOWN:
            self.forget()
        return np.fromiter(map(self.place.__getitem__, words), dtype=np.int64, count=n)

    def _new(self, had: int) -> list[bytes]:
        return list(islice(self.place, had, None))

    def encoded(self) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all words in a row, how many each has)."""
        if len(self.length) < len(self.place):
            flat, length = self.ids.of(self._new(len(self.length)))
            self.flat, self.length = np.concatenate([self.flat, flat]), np.concatenate([self.length, length])
        return self.flat, self.length

    def value(self, name: str, of: Callable[[list[bytes]], np.ndarray]) -> np.ndarray:
        """of(words) for all words, worked out for the new ones."""
        had = self.values.get(name)
        new = self._new(0 if had is None else len(had))
        if new or had is None:
            self.values[name] = of(new) if had is None else np.concatenate([had, of(new)])
        return self.values[name]


class Run:
    """Some documents' words as numbers of known words."""

    def __init__(self, docs: list[list[bytes]], known: Known | None = None) -> None:
        self.known = known or Known(None)
        self.sizes = np.fromiter(map(len, docs), dtype=np.int64, count=len(docs))
        self.at = self.known.numbers(chain.from_iterable(docs), int(self.sizes.sum()))
        self.doc = np.repeat(np.arange(len(docs)), self.sizes)

    def sequences(self, ids: WordIds) -> list[np.ndarray]:
        """Subword ids of each document."""
        self.known.ids = ids
        flat, length = self.known.encoded()
        n = length[self.at]
        ends = np.concatenate([[0], np.cumsum(n)])
        index = np.repeat((np.cumsum(length) - length)[self.at] - ends[:-1], n)
        index += np.arange(len(index))
        return np.split(flat[index], ends[np.cumsum(self.sizes)[:-1]])

    def sums(self, value: np.ndarray) -> np.ndarray:
        """Per document the sum of a value of its words."""
        return np.bincount(self.doc, weights=value[self.at], minlength=len(self.sizes))


def _slices(batch: pa.RecordBatch, column: str, most: int = 4 << 20) -> Iterator[tuple[int, list[list[bytes]]]]:
    """Runs of documents as lists of words, with the first row's number: about so many bytes a run."""
    out, held, first = [], 0, 0
    for i, t in enumerate(batch.column(column).cast(pa.binary())):
        b = t.as_py()
        out.append(b.lower().split())
        held += len(b)
        if held >= most:
            yield first, out
            out, held, first = [], 0, i + 1
    if out:
        yield first, out


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(word, n) of the task's documents, folded; the number of documents under a null word."""
    words, docs = Counter(), 0
    fold = lambda: pa.RecordBatch.from_arrays([pa.array(list(words), pa.binary()), pa.array(list(words.values()), pa.int64())], ["word", "n"])
    for batch in batches:
        for _, run_of in _slices(batch, "text"):
            docs += len(run_of)
            words.update(chain.from_iterable(run_of))
            if len(words) >= FOLDED:
                yield fold()
                words.clear()
    yield fold()
    yield pa.RecordBatch.from_arrays([pa.array([None], pa.binary()), pa.array([docs], pa.int64())], ["word", "n"])


def corpus_counts(texts: DataFrame) -> DataFrame:
    """(word, key, n): occurrences of every word of the texts, its digest; the number of texts under a null word."""
    counted = texts.mapInArrow(_count, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n"))
    return written(counted.select("word", F.xxhash64("word").alias("key"), "n"), "counts")


def _subwords(path: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, total = word_ids(path), np.zeros(IDS, dtype=np.int64)
        for batch in batches:
            flat, length = ids.of(batch.column("word").to_pylist())
            total += np.bincount(flat, weights=np.repeat(batch.column("n").to_numpy(), length), minlength=IDS).astype(np.int64)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], ["id", "n"])

    return run


def subword_counts(words: DataFrame, path: str) -> np.ndarray:
    """How often each subword id occurs, from the counts of all words."""
    rows = words.select("word", "n").mapInArrow(_subwords(path), "id long, n long").groupBy("id").agg(F.sum("n").alias("n")).toArrow()  # a row for each id
    out = np.zeros(IDS, dtype=np.int64)
    out[rows.column("id").to_numpy()] = rows.column("n").to_numpy()
    return out


def _sequences(batches: Iterator[pa.RecordBatch], ids: WordIds) -> Iterator[list[np.ndarray]]:
    known = Known(ids)
    for batch in batches:
        for _, docs in _slices(batch, "text"):
            yield Run(docs, known).sequences(ids)


def _first_fit(path: str, shared):
    """One row: weights after as many passes over the task's documents as make FIRST_WINDOWS windows, in an order by content."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = shared.value
        found = sorted((s for part in _sequences(batches, word_ids(path)) for s in part), key=lambda s: (zlib.crc32(s.tobytes()), s.tobytes()))
        windows = len(attention.Windows(found, vocabulary, 0)) if found else 1
        passes = -(-FIRST_WINDOWS // windows)
        trainer = attention.Trainer(attention.start(vocabulary), vocabulary, passes * windows)
        for _ in range(passes):
            trainer.feed(found)
        yield pa.RecordBatch.from_arrays([pa.array([attention.pack(trainer.w).astype("<f4").tobytes()], pa.binary())], ["weights"])

    return run


def _refine(path: str, first, shared, expected: int, mergers: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = shared.value
        start = attention.start(vocabulary)
        trainer = attention.Trainer(attention.unpack(first.value, start), vocabulary, expected)
        for sequences in _sequences(batches, word_ids(path)):
            trainer.feed(sequences)
        part, grains = TaskContext.get().partitionId() % mergers, np.rint(attention.pack(trainer.w).astype(np.float64) * GRAIN).astype(np.int64) * trainer.seen
        yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([trainer.seen], pa.int64()), pa.array([grains.tobytes()], pa.binary())], ["part", "n", "weights"])

    return run


def _add_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    n, total = 0, None
    for batch in batches:
        for k, b in zip(batch.column("n").to_pylist(), batch.column("weights").to_pylist(), strict=True):
            n, total = n + k, np.frombuffer(b, dtype=np.int64) + (0 if total is None else total)
    if total is not None:
        yield pa.RecordBatch.from_arrays([pa.array([0], pa.int32()), pa.array([n], pa.int64()), pa.array([total.tobytes()], pa.binary())], ["part", "n", "weights"])


def train(texts: DataFrame, path: str, vocabulary: attention.Vocabulary, words: int, subwords: int, first_words: int = FIRST_WORDS) -> np.ndarray:
    """Attention weights, packed, from all training texts (id, text) with so many words and subwords."""
    sc = texts.sparkSession.sparkContext
    shared = sc.broadcast(vocabulary)
    share = min(1.0, first_words / max(1, words))
    chosen = texts.where(F.pmod(F.xxhash64(F.lit(6), *texts.columns), F.lit(1 << 30)) < int(share * (1 << 30))).select("text")
    # without the limit, one row repeated very often would all be chosen at once
    start = chosen.limit(2 * first_words).repartition(1).mapInArrow(_first_fit(path, shared), "weights binary").collect()
    weights = np.frombuffer(start[0]["weights"], dtype="<f4") if start else attention.pack(attention.start(vocabulary))
    parts = max(1, texts.rdd.getNumPartitions())
    mergers = max(1, round(parts**0.5))
    schema = "part int, n long, weights binary"
    tuned = texts.select("text").mapInArrow(_refine(path, sc.broadcast(weights), shared, subwords // (attention.WINDOW * parts), mergers), schema)
    # as many sums as the root of the partitions come to the driver
    n, total = 0, np.zeros(len(weights), dtype=object if parts > 1000 else np.int64)
    for r in tuned.repartitionById(mergers, "part").mapInArrow(_add_up, schema).toLocalIterator():
        n, total = n + r["n"], total + np.frombuffer(r["weights"], dtype=np.int64)
    return (total / (n * GRAIN)).astype(np.float32) if n else weights


def heavy_words(counts: DataFrame, distinct: int, heavy: int = HEAVY) -> tuple[int, np.ndarray, np.ndarray]:
    """(least count, digests ascending, counts): words above the least count, at most 1.5 * heavy of them."""
    least = 0
    if distinct > heavy:
        least = int(counts.agg(F.percentile_approx("n", 1 - heavy / distinct, 10_000).alias("q")).first()["q"])
        while counts.where(F.col("n") > least).count() > 1.5 * heavy:
            least = 2 * least + 1
    found = counts.where(F.col("n") > least).select("key", "n").toArrow()
    key, n = found.column("key").to_numpy(), found.column("n").to_numpy()
    order = np.argsort(key)
    return least, key[order], n[order]


SCORED = "row long, doc_id long, held_out boolean, n_tokens long, n_known long, base double, score double, key long"
SCORED_NAMES = [x.split()[0] for x in SCORED.split(", ")]


def _score(path: str, shared, total: int, distinct: int, ends: int):
    """Rows of documents (key null) and of the occurrences of words that aren't frequent (row and key)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weights, vocabulary, keys, counts = shared.value
        w = attention.unpack(weights, attention.start(vocabulary))
        ids, row = word_ids(path), TaskContext.get().partitionId() << 33
        scale, known_words = np.log10(total + distinct + 1), Known(ids)
        digests = lambda words: np.fromiter(map(digest, words), dtype=np.uint64, count=len(words)).view(np.int64)

        def corpus(words: list[bytes]) -> np.ndarray:
            h = digests(words)
            at = np.minimum(np.searchsorted(keys, h), max(0, len(keys) - 1))
            return np.where(keys[at] == h, counts[at], -1) if len(keys) else np.full(len(h), -1)

        for batch in batches:
            docs, held = batch.column("doc_id"), batch.column("held_out")
            for first, words in _slices(batch, "text"):
                own = Run(words, known_words)
                score = attention.log10_probabilities(w, own.sequences(ids), vocabulary)
                n = known_words.value("n", corpus)
                rows = np.arange(row, row + len(words))
                row += len(words)
                here = n >= 0
                known = own.sums((n > 0).astype(float)).astype(np.int64) + (ends > 0)
                base = own.sums(np.where(here, np.log10(np.maximum(n, 0) + 1.0) - scale, 0.0)) + np.log10(ends + 1.0) - scale
                yield pa.RecordBatch.from_arrays([pa.array(rows), docs.slice(first, len(rows)), held.slice(first, len(rows)), pa.array(own.sizes + 1), pa.array(known), pa.array(base), pa.array(score), pa.nulls(len(rows), pa.int64())], SCORED_NAMES)
                light = np.flatnonzero(~here[own.at])
                if len(light):
                    k, h = len(light), known_words.value("key", digests)
                    yield pa.RecordBatch.from_arrays([pa.array(rows[own.doc[light]]), pa.nulls(k, pa.int64()), pa.nulls(k, pa.bool_()), *(pa.nulls(k, t) for t in (pa.int64(), pa.int64(), pa.float64(), pa.float64())), pa.array(h[own.at[light]])], SCORED_NAMES)

    return run


def score(docs: DataFrame, path: str, held: Column, id_col: str = "doc_id", text_col: str = "text", heavy: int = HEAVY) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score; learning from rows that held doesn't mark."""
    ship(docs.sparkSession)
    read = docs.select(F.col(id_col).cast("long").alias("doc_id"), held.alias("held_out"), whole_text(text_col).alias("text"))
    learn = read.where(~F.col("held_out"))
    counts = corpus_counts(learn.select("text"))
    words = counts.where("word is not null")
    r = counts.agg(F.sum(F.when(F.col("word").isNull(), F.col("n"))).alias("docs"), F.sum(F.when(F.col("word").isNotNull(), F.col("n"))).alias("n"), F.count("word").alias("k")).first()
    ends = int(r["docs"] or 0)
    total, distinct = int(r["n"] or 0) + ends, int(r["k"]) + (ends > 0)
    subwords = subword_counts(words, path)
    subwords[IDS - 1] += ends
    vocabulary = attention.Vocabulary.of(subwords, IDS - 1)
    w = train(learn.select("doc_id", "text"), path, vocabulary, total, int(subwords.sum()))
    least, keys, n = heavy_words(words, distinct, heavy)
    shared = docs.sparkSession.sparkContext.broadcast((w, vocabulary, keys, n))
    scored = written(read.mapInArrow(_score(path, shared, total, distinct, ends), SCORED), "scored")
    light = scored.where("key is not null").select("row", "key").join(written(words.where(F.col("n") <= least).select("key", "n"), "light"), "key", "left")
    scale = float(np.log10(total + distinct + 1))
    per = light.groupBy("row").agg(F.sum(F.log10(F.coalesce("n", F.lit(0)) + F.lit(1.0)) - F.lit(scale)).alias("_base"), F.count("n").alias("_known"))
    told = scored.where("key is null").join(per, "row", "left")
    return told.select("doc_id", "held_out", "n_tokens", (F.col("n_known") + F.coalesce("_known", F.lit(0))).alias("n_known"), F.lit(total).cast("long").alias("train_tokens"), (F.col("base") + F.coalesce("_base", F.lit(0.0))).alias("base_score"), "score")


def lm_scores(docs: DataFrame, path: str) -> DataFrame:
    """Learn from the rows whose remainder by 7 is not 2, then score every row."""
    return score(docs, path, held_out("doc_id", 7, 2))
