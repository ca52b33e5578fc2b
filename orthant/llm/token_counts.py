"""Token counts behind a digest cache.

The cache is a Parquet table (digest, tokenizer, n_tokens) that is only appended to. A text's key is the SHA-256 of its
normalised content and a tokenizer version (a digest of the vocabulary file). Texts whose key is stored are not encoded
again; of the others one copy each is: copies inside a map task fold there, so a digest that a third of the rows share
costs a shuffled text per task and not per row. The misses are appended, and every document is joined to the counts. Which
digests are missing is found by joining digests alone; a run that misses nothing shuffles no text.

Defined results: null text counts as empty and has no tokens; repeated rows each get a row; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from orthant.functions.shipping import ship

from .common import fresh_path, shuffle_partitions, whole_text, written
from .tokens import in_slices, tokenizer

CACHE_SCHEMA = "digest binary, tokenizer string, n_tokens long"
LIMIT = 2048


def tokenizer_version(path: str) -> str:
    with open(path, "rb") as f:
        return hashlib.sha256(f.read()).hexdigest()[:16]


#: Digests that a task remembers, missing digests that are broadcast, bytes of text that a task encodes, about.
SEEN, BROADCAST_DIGESTS, PART_BYTES = 500_000, 500_000, 64 << 20


def _new(digests: list[bytes], seen: set[bytes]) -> list[int]:
    """Places of digests that aren't in seen, which gets them; it is emptied when it is full, which costs repeated work only."""
    keep = [i for i, d in enumerate(digests) if d not in seen and not seen.add(d)]
    if len(seen) > SEEN:
        seen.clear()
    return keep


def _first_copies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows whose digest this task has not passed on yet."""
    seen: set[bytes] = set()
    for batch in batches:
        yield batch.take(pa.array(_new(batch.column("digest").to_pylist(), seen), pa.int64()))


def _encode(path: str, version: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok, seen = tokenizer(path), set()
        for batch in batches:
            digests, texts = batch.column("digest").to_pylist(), batch.column("text").to_pylist()
            new = _new(digests, seen)
            counts: list[int] = []
            for a, b in in_slices([texts[i] for i in new]):
                counts += tok.count([texts[i] for i in new[a:b]])
            yield pa.RecordBatch.from_arrays([pa.array([digests[i] for i in new], pa.binary()), pa.array([version] * len(new), pa.string()), pa.array(counts, pa.int64())], ["digest", "tokenizer", "n_tokens"])

    return run


def cached_counts(spark, cache_path: str, version: str) -> DataFrame | None:
    try:
        return spark.read.schema(CACHE_SCHEMA).parquet(cache_path).where(F.col("tokenizer") == version).drop("tokenizer")
    except AnalysisException as e:
        if "PATH_NOT_FOUND" not in str(e):
            raise
        return None


def _misses(texts: DataFrame, keyed: DataFrame, stored: DataFrame | None) -> DataFrame | None:
    """(digest, text) of the texts whose digest isn't stored; None if there are none. Digests are compared, texts stay where they are."""
    if stored is None:
        return texts
    missing = written(keyed.select("digest").distinct().join(stored, "digest", "left_anti"), "missing")
    n = missing.count()
    if not n:
        return None
    return texts.join(F.broadcast(missing) if n <= BROADCAST_DIGESTS else missing, "digest", "left_semi")


def count_tokens(docs: DataFrame, tokenizer_path: str, cache_path: str | None = None, limit: int = LIMIT, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: id, n_bytes, n_tokens, over_limit. Without a cache_path the cache lives as long as the session."""
    spark = docs.sparkSession
    ship(spark)
    cache_path = cache_path or fresh_path(spark, "token_cache")
    version = tokenizer_version(tokenizer_path)
    text = whole_text(text_col)
    digest = F.unhex(F.sha2(text.cast("binary"), 256)).alias("digest")
    keyed = written(docs.select(F.col(id_col).alias("_id"), F.octet_length(text).cast("long").alias("n_bytes"), digest), "digests")
    misses = _misses(docs.select(digest, text.alias("text")), keyed, cached_counts(spark, cache_path, version))
    if misses is not None:
        # copies fold in their task; partitions follow the bytes, so a task doesn't grow with the corpus
        size = keyed.agg(F.sum("n_bytes").alias("n")).first()["n"] or 0
        firsts = misses.mapInArrow(_first_copies, misses.schema).repartition(max(shuffle_partitions(spark), -(-size // PART_BYTES)), "digest")
        firsts.mapInArrow(_encode(tokenizer_path, version), CACHE_SCHEMA).write.mode("append").parquet(cache_path)
    # a writer that ran at the same time, or another task, may have stored a digest too
    counts = written(cached_counts(spark, cache_path, version).groupBy("digest").agg(F.max("n_tokens").alias("n_tokens")), "counts")
    return keyed.join(counts, "digest").select(F.col("_id").alias(id_col), "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))


def counts_cold_and_warm(docs: DataFrame, tokenizer_path: str) -> DataFrame:
    """The counts twice over one cache: the first run finds it empty and fills it, the second, whose rows these are, encodes nothing."""
    cache_path = fresh_path(docs.sparkSession, "token_cache")
    count_tokens(docs, tokenizer_path, cache_path)
    return count_tokens(docs, tokenizer_path, cache_path)
