"""SimHash near-dedup by meet-in-the-middle ball hashing.

Two 64-bit fingerprints within 3 bits meet at a middle: one flips at most two bits, the other at most one. Parity says
who does what. At an odd distance exactly one of the two has an even number of set bits; it emits itself and its flips
of two bits, and the odd one emits its flips of one bit. At distance 2 both emit their flips of one bit. Of three
differing bits two lie in the same half of the word, so flips of two bits are needed inside a half only. That is
1 + 64 + 992 variants of an even and 64 of an odd fingerprint: not every fingerprint emits the whole ball of half the radius
and more, but of any two within the radius both emit a common variant.

Variants are shuffled packed: a record holds those of a run of fingerprints that fall into one slice of the hashed
variant space, as fingerprint and mask number. A slice sorts its variants; in a bucket every member links to one member
that is a single flip away (their distance is at most 3, which is verified), so thousands of close fingerprints never
make all their pairs, and the links of a slice leave it as a spanning forest. Equal fingerprints are one node from the
start. Components then come from the links of all slices.

Defined results: null and empty texts have fingerprint 0 and are linked like any other; repeated rows share their
component; a document without links is its own component; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from orthant.functions.shipping import ship

from .common import shuffle_partitions, whole_text, written
from .components import connected_components

BITS, RADIUS, WIDTH, SEED = 64, 3, 3, 42
#: Fingerprints expanded together, and variants that a slice holds on average: some hundred MB while they are sorted.
RUN, SLICE_ROWS = 1024, 4_000_000

_ONE = [1 << i for i in range(BITS)]
_TWO = [1 << i | 1 << j for half in (range(32), range(32, 64)) for i, j in combinations(half, 2)]
MASKS = np.array([0, *_ONE, *_TWO], dtype=np.uint64)
ODD = np.arange(1, BITS + 1)
MEAN_VARIANTS = (len(MASKS) + BITS) // 2


def fingerprint(text: bytes, width: int = WIDTH, seed: int = SEED) -> int:
    """Majority bits of the shingles' hashes, as an unsigned number; 0 without words."""
    words = text.lower().split()  # of bytes: lowers A-Z only, splits at the six ASCII spaces only
    if not words:
        return 0
    runs = [b" ".join(words)] if len(words) < width else map(b" ".join, zip(*(words[i:] for i in range(width)), strict=False))
    digest = xxhash.xxh64_intdigest
    h = np.array([digest(r, seed) for r in runs], dtype="<u8")
    total = np.zeros(BITS, dtype=np.int64)
    for at in range(0, len(h), 65_536):
        part = h[at : at + 65_536]
        total += np.unpackbits(part.view(np.uint8).reshape(len(part), 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * total > len(h), bitorder="little").view("<u8")[0])


def _fingerprints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        texts = batch.column(1).cast(pa.binary())
        h = np.fromiter((fingerprint(t.as_py()) for t in texts), dtype=np.uint64, count=len(texts))
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(h.view(np.int64))], ["doc_id", "fp"])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fp): fp is the fingerprint's 64 bits as a long."""
    read = docs.select(F.col(id_col).cast("long").alias("doc_id"), whole_text(text_col).alias("text"))
    return read.mapInArrow(_fingerprints, "doc_id long, fp long")


def _slice_of(v: np.ndarray, slices: int) -> np.ndarray:
    return ((v * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(32)) % np.uint64(slices)


def _emit(slices: int):
    """Packed variants: (slice, fps, masks), the last two as bytes of u8 and u2."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            every = batch.column(0).to_numpy().view(np.uint64)
            for at in range(0, len(every), RUN):
                fp = every[at : at + RUN]
                even = np.bitwise_count(fp) % 2 == 0
                owner = np.concatenate([np.repeat(np.flatnonzero(even), len(MASKS)), np.repeat(np.flatnonzero(~even), len(ODD))])
                mask = np.concatenate([np.tile(np.arange(len(MASKS)), int(even.sum())), np.tile(ODD, int((~even).sum()))]).astype(np.uint16)
                to = _slice_of(fp[owner] ^ MASKS[mask], slices)
                order = np.argsort(to, kind="stable")
                to, fps, masks = to[order], fp[owner[order]], mask[order]
                starts = np.flatnonzero(np.r_[True, to[1:] != to[:-1]])
                ends = np.r_[starts[1:], len(to)]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(to[starts].astype(np.int32)), pa.array([fps[s:e].tobytes() for s, e in zip(starts, ends, strict=True)], pa.binary()), pa.array([masks[s:e].tobytes() for s, e in zip(starts, ends, strict=True)], pa.binary())],
                    ["slice", "fps", "masks"],
                )

    return run


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, root) without the roots: the components of the pairs as stars."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    i, j = at[: len(a)], at[len(a) :]
    label = np.arange(len(nodes))
    while True:
        low = np.minimum(label[i], label[j])
        new = label.copy()
        for k in (i, j, label[i], label[j]):
            np.minimum.at(new, k, low)
        new = new[new]
        if (new == label).all():
            break
        label = new
    rest = np.flatnonzero(label != np.arange(len(nodes)))
    return nodes[rest], nodes[label[rest]]


def links_in(fp: np.ndarray, mask: np.ndarray, radius: int = RADIUS) -> tuple[np.ndarray, np.ndarray]:
    """Links of the fingerprints that share a variant: each bucket's members to its least single flip, verified."""
    v = fp ^ MASKS[mask]
    order = np.argsort(v, kind="stable")
    v, fp, single = v[order], fp[order], (mask[order] <= BITS)
    starts = np.flatnonzero(np.r_[True, v[1:] != v[:-1]]) if len(v) else np.array([], dtype=np.int64)
    size = np.diff(np.r_[starts, len(v)])
    hub = np.minimum.reduceat(np.where(single, fp, np.uint64(2**64 - 1)), starts) if len(v) else fp
    some = np.logical_or.reduceat(single, starts) if len(v) else single
    keep = np.repeat(some & (size > 1), size)
    a, b = fp[keep], np.repeat(hub, size)[keep]
    true = (a != b) & (np.bitwise_count(a ^ b) <= radius)
    return a[true], b[true]


def _meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    fps, masks = [], []
    for batch in batches:
        fps += batch.column("fps").to_pylist()
        masks += batch.column("masks").to_pylist()
    a, b = forest(*links_in(np.frombuffer(b"".join(fps), dtype=np.uint64), np.frombuffer(b"".join(masks), dtype=np.uint16)))
    yield pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], ["u", "v"])


def links(fps: DataFrame, n: int) -> DataFrame:
    """(u, v): a forest per slice whose components together are those of all pairs within 3 bits; fps: n distinct (fp)."""
    least = shuffle_partitions(fps.sparkSession)
    slices = max(least, -(-n * MEAN_VARIANTS // SLICE_ROWS))
    dealt = fps.select("fp").repartition(max(least, n // (16 * RUN)))
    emitted = dealt.mapInArrow(_emit(slices), "slice int, fps binary, masks binary")
    return emitted.repartitionById(slices, "slice").mapInArrow(_meet, "u long, v long")


def _named(own: DataFrame) -> DataFrame:
    """(fp, component_id) of fingerprints (doc_id, fp)."""
    nodes = written(own.groupBy("fp").agg(F.min("doc_id").alias("first")), "nodes")
    roots = connected_components(links(nodes, nodes.count()))
    rooted = written(nodes.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "first", F.coalesce("root", "fp").alias("root")), "rooted")
    # most nodes are alone; only the others need their root's smallest document
    least = rooted.where("root <> fp").groupBy("root").agg(F.min("first").alias("_m"))
    named = rooted.join(least, "root", "left").join(nodes.select(F.col("fp").alias("root"), F.col("first").alias("_r")), "root")
    return written(named.select("fp", F.least("_m", "_r").alias("component_id")), "named")


def near_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, fp long, component_id (smallest doc_id that links reach)."""
    ship(docs.sparkSession)
    own = written(fingerprints(docs, id_col, text_col), "fingerprints")
    return own.join(_named(own), "fp").select("doc_id", "fp", "component_id")


def _with_fingerprint(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        texts = batch.column("_text").cast(pa.binary())
        h = np.fromiter((fingerprint(t.as_py()) for t in texts), dtype=np.uint64, count=len(texts))
        yield pa.RecordBatch.from_arrays([batch.column("_all"), batch.column("_id"), pa.array(h.view(np.int64))], ["_all", "_id", "_fp"])


def keep_first(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with one document of each group, that with the smallest id, all columns kept.

    Rows find their group by fingerprint, not by id, so null and repeated ids are safe: a null id loses to any other, and of
    rows with the same id and fingerprint one stays.
    """
    ship(docs.sparkSession)
    # all columns travel as one, so their names can't clash with ours
    rows = docs.select(F.struct("*").alias("_all"), F.col(id_col).cast("long").alias("_id"), whole_text(text_col).alias("_text"))
    schema = T.StructType([rows.schema["_all"], rows.schema["_id"], T.StructField("_fp", T.LongType())])
    # fingerprints are made once and lie beside their rows
    marked = written(rows.mapInArrow(_with_fingerprint, schema), "marked")
    named = _named(marked.select(F.col("_id").alias("doc_id"), F.col("_fp").alias("fp"))).withColumnRenamed("fp", "_fp")
    left = marked.join(named, "_fp").where(F.col("_id").eqNullSafe(F.col("component_id")))
    ranked = left.withColumn("_rank", F.row_number().over(Window.partitionBy("_fp").orderBy("_id")))
    return ranked.where("_rank = 1").select("_all.*")


def near_dedup(docs: DataFrame) -> DataFrame:
    """doc_id, fingerprint as 16 lowercase hex digits, component_id."""
    return near_groups(docs).select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
