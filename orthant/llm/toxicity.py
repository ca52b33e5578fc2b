"""Toxicity by weak supervision.

Many voters look at a document: lexicon voters, each firing on one word or word beginning that the labelled sample
associates with toxicity, and pattern voters (shouting, exclamation marks, symbols, repetition, short texts, no lexicon hit
at all); the given label is one voter more. A generative label model over a hidden class holds, for every voter, how
often it fires on either class, given what the voter does that it depends on most: the dependencies are a forest of greatest
mutual information within the classes, as far as it is significant, so the beginnings of one word don't count as independent
evidence. Rates, dependencies and the prior are all estimated by expectation maximisation, which starts at the given labels;
their voter too has an estimated reliability. A sparse linear classifier is trained on the posterior labels, over words
and beginnings that lean to either side, and scores every text, labelled or not.

The fit takes a bounded sample of the distinct labelled rows (``sample_rows``, chosen by a hash of the row, each text whole),
in one task.

Defined results: a null text is empty and scores like any text without words; without labelled rows every score is 0;
null labels aren't learned from; repeated rows each get a row; an empty table gives no rows.
"""

from __future__ import annotations

import pickle
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from orthant.functions.shipping import ship

from .common import distinct_sample, whole_text
from .langid import held_out

#: Most labelled rows of the fit, lexicon voters, and words that a worker remembers.
SAMPLE_ROWS, LEXICON, MEMO_WORDS = 12_000, 320, 300_000
BEGINNINGS, LEAST_DOCS = (4, 5, 6), 4
#: Least share of toxic documents among those that a lexicon voter fires on.
LEAST_SHARE = 0.6
#: Least association of a feature with clean documents.
CLEAN_SIDE = 4.0
#: Lexicon voters wanted on a toxic document.
COVER = 4
#: Rounds, between rounds that look for dependencies anew, doubt in the given labels at the start, pseudo-rows of a rate,
#: least G statistic of a dependency.
EM_ROUNDS, EVERY, DOUBT, PSEUDO, SIGNIFICANT = 20, 5, 0.03, 0.1, 15.0
STEPS, RATE, L1, L2 = 400, 0.5, 1e-4, 1e-6
_SPACE_OUT = bytes(c if c >= 128 or chr(c).isalnum() else 32 for c in range(256))
_UPPER, _SYMBOLS = bytes(range(65, 91)), b"#*$%&|<>"
PATTERNS = ("exclaims", "shouts", "symbols", "repeats", "short")


def word_features(word: bytes) -> list[int]:
    """64-bit keys of a word and its beginnings."""
    w = word.decode("utf-8", "replace")
    keys = [xxhash.xxh64_intdigest(word, 1)]
    return keys + [xxhash.xxh64_intdigest(w[:n].encode("utf-8", "replace"), 2 + n) for n in BEGINNINGS if len(w) > n]


def words(text: bytes) -> list[bytes]:
    return text.translate(_SPACE_OUT).lower().split()


def patterns(text: bytes, tokens: list[bytes], distinct: int) -> np.ndarray:
    n = max(1, len(text))
    return np.array([
        text.count(b"!") >= 3,
        (len(text) - len(text.translate(None, _UPPER))) / n > 0.3,
        (len(text) - len(text.translate(None, _SYMBOLS))) / n > 0.02,
        distinct < 0.3 * len(tokens),
        len(tokens) < 20,
    ], dtype=np.float64)


def association(x_toxic: np.ndarray, x_clean: np.ndarray, toxic: int, clean: int) -> np.ndarray:
    """Smoothed log-odds ratio over its standard error, per feature."""
    a, b = x_toxic + 0.5, x_clean + 0.5
    c, d = toxic - x_toxic + 0.5, clean - x_clean + 0.5
    return (np.log(a / c) - np.log(b / d)) / np.sqrt(1 / a + 1 / b + 1 / c + 1 / d)


@dataclass
class LabelModel:
    """Voters fire or not, given the hidden class (clean, toxic) and whether the voter fires that they depend on."""

    prior: float
    parent: np.ndarray  # -1: depends on the class only
    fires: np.ndarray  # voters x class x (parent silent, parent fires)

    def posterior(self, votes: np.ndarray) -> np.ndarray:
        """votes: documents x voters, 1 where a voter fires."""
        above = np.where(self.parent >= 0, votes[:, self.parent], 0.0)
        score = np.log([1 - self.prior, self.prior])
        each = []
        for k in (0, 1):
            on, off = np.log(self.fires[:, k]), np.log1p(-self.fires[:, k])
            quiet = votes * (on[:, 0] - off[:, 0]) + off[:, 0]
            loud = votes * (on[:, 1] - off[:, 1]) + off[:, 1]
            each.append(score[k] + (quiet + above * (loud - quiet)).sum(axis=1))
        return 1 / (1 + np.exp(-np.clip(each[1] - each[0], -50, 50)))


def dependencies(votes: np.ndarray, p: np.ndarray) -> np.ndarray:
    """Parents of the voters: a forest of the significant pairs with the greatest mutual information within the classes."""
    n, m = votes.shape
    information = np.zeros((m, m))
    for w in (1 - p, p):
        total = w.sum() + 1e-9
        both = votes.T @ (votes * w[:, None]) / total
        one = np.diag(both).copy()
        for joint, a, b in ((both, one[:, None], one[None, :]), (one[:, None] - both, one[:, None], 1 - one[None, :]), (one[None, :] - both, 1 - one[:, None], one[None, :]), (1 - one[:, None] - one[None, :] + both, 1 - one[:, None], 1 - one[None, :])):
            joint = np.maximum(joint, 0)
            with np.errstate(divide="ignore", invalid="ignore"):
                information += total / n * np.where(joint > 0, joint * np.log(joint / (a * b)), 0.0)
    information = np.where(2 * n * information > SIGNIFICANT, information, 0.0)
    np.fill_diagonal(information, 0)
    parent, best, via = np.full(m, -1), np.full(m, -1.0), np.full(m, -1)
    waiting = np.ones(m, dtype=bool)
    for _ in range(m):  # the next voter is the one most dependent on those taken
        k = int(np.flatnonzero(waiting)[best[waiting].argmax()])
        waiting[k] = False
        parent[k] = via[k] if best[k] > 0 else -1
        more = waiting & (information[k] > best)
        best[more], via[more] = information[k][more], k
    return parent


def fit_label_model(votes: np.ndarray, labels: np.ndarray) -> LabelModel:
    """All rates and dependencies, with the given labels as the last voter; the classes are named after where it starts."""
    votes = np.column_stack([votes, labels == 1]).astype(np.float64)
    p, model, parent = np.where(labels == 1, 1 - DOUBT, DOUBT), None, None
    for i in range(EM_ROUNDS):
        if i % EVERY == 0:
            parent = np.append(dependencies(votes[:, :-1], p), -1)  # the label's errors are its own
        above = np.where(parent >= 0, votes[:, parent], 0.0)
        fires = np.empty((votes.shape[1], 2, 2))
        for k, w in ((0, 1 - p), (1, p)):
            alone = (w @ votes + PSEUDO / 2) / (w.sum() + PSEUDO)
            for s, side in ((0, 1 - above), (1, above)):
                weight = side * w[:, None]
                # where the parent hardly ever does that, the rate without it
                fires[:, k, s] = ((weight * votes).sum(axis=0) + PSEUDO * alone) / (weight.sum(axis=0) + PSEUDO)
        model = LabelModel(float(np.clip(p.mean(), 1e-3, 1 - 1e-3)), parent, np.clip(fires, 1e-5, 1 - 1e-5))
        p = model.posterior(votes)
    return model


def spread(candidates: np.ndarray, at: np.ndarray, doc: np.ndarray, toxic_doc: np.ndarray, n_docs: int) -> np.ndarray:
    """Voters from the candidates, best first: one is taken while it reaches toxic documents that have fewer than COVER voters."""
    place = np.full(int(at.max()) + 1, -1)
    place[candidates] = np.arange(len(candidates))
    mine = (place[at] >= 0) & toxic_doc
    order = np.argsort(place[at[mine]], kind="stable")
    owner, of = doc[mine][order], place[at[mine]][order]
    bounds = np.searchsorted(of, np.arange(len(candidates) + 1))
    covered, taken = np.zeros(n_docs, dtype=int), []
    for k in range(len(candidates)):
        docs = owner[bounds[k] : bounds[k + 1]]
        if len(taken) < LEXICON and (covered[docs] < COVER).sum() >= LEAST_DOCS:
            taken.append(candidates[k])
            covered[docs] += 1
    return np.array(taken, dtype=int)


@dataclass
class ToxicityModel:
    bias: float = -50.0
    weights: dict[int, float] = field(default_factory=dict)
    pattern_weights: np.ndarray = field(default_factory=lambda: np.zeros(len(PATTERNS)))
    memo: dict[bytes, tuple] = field(default_factory=dict)

    def score(self, text: bytes) -> float:
        tokens = words(text)
        distinct, memo, found = set(tokens), self.memo, set()
        for w in distinct:
            active = memo.get(w)
            if active is None:
                active = tuple(k for k in word_features(w) if k in self.weights)
                if len(memo) < MEMO_WORDS:
                    memo[w] = active
            if active:
                found.update(active)
        z = self.bias + sum(sorted(self.weights[k] for k in found)) + float(self.pattern_weights @ patterns(text, tokens, len(distinct)))
        return float(1 / (1 + np.exp(-min(50.0, max(-50.0, z)))))


def fit(keys: list[np.ndarray], extra: np.ndarray, labels: np.ndarray) -> ToxicityModel:
    """keys: feature keys of each sampled document; extra: pattern columns; labels 0 or 1."""
    if not len(labels) or labels.min() == labels.max():
        return ToxicityModel(50.0 if len(labels) and labels.max() else -50.0)
    every, at = np.unique(np.concatenate(keys), return_inverse=True)
    doc = np.repeat(np.arange(len(keys)), [len(k) for k in keys])
    toxic_doc = labels[doc] == 1
    n_toxic, n_clean = np.bincount(at[toxic_doc], minlength=len(every)), np.bincount(at[~toxic_doc], minlength=len(every))
    z = association(n_toxic, n_clean, int((labels == 1).sum()), int((labels == 0).sum()))
    often = n_toxic + n_clean >= LEAST_DOCS
    # voters
    share = (n_toxic + 0.5) / (n_toxic + n_clean + 1)
    chosen = np.flatnonzero(often & (z > 3) & (share > LEAST_SHARE))
    chosen = spread(chosen[np.argsort(-z[chosen], kind="stable")], at, doc, toxic_doc, len(keys))
    column = np.full(len(every), -1)
    column[chosen] = np.arange(len(chosen))
    votes = np.zeros((len(keys), len(chosen) + len(PATTERNS) + 1))
    hit = column[at] >= 0
    votes[doc[hit], column[at[hit]]] = 1
    votes[:, len(chosen) : len(chosen) + len(PATTERNS)] = extra
    votes[:, -1] = votes[:, : len(chosen)].sum(axis=1) == 0
    soft = fit_label_model(votes, labels).posterior(np.column_stack([votes, labels == 1]).astype(np.float64))
    # linear classifier on the posterior labels, over features seen often enough and leaning to a side
    use = np.flatnonzero(often & ((z > 3) & (share > LEAST_SHARE) | (z < -CLEAN_SIDE)))
    index = np.full(len(every), -1)
    index[use] = np.arange(len(use))
    kept = index[at] >= 0
    order = np.argsort(doc[kept], kind="stable")
    feature, owner = index[at[kept]][order], doc[kept][order]
    w, b, v = np.zeros(len(use)), float(np.log(soft.mean() / (1 - soft.mean()))), np.zeros(len(PATTERNS))
    square, square_v, square_b = np.full(len(use), 1e-6), np.full(len(PATTERNS), 1e-6), 1e-6
    for _ in range(STEPS):  # over all rows: adaptive proximal steps
        p = 1 / (1 + np.exp(-np.clip(b + np.bincount(owner, weights=w[feature], minlength=len(keys)) + extra @ v, -50, 50)))
        g = (p - soft) / len(keys)
        gw, gv, gb = np.bincount(feature, weights=g[owner], minlength=len(use)) + L2 * w, extra.T @ g + L2 * v, g.sum()
        square, square_v, square_b = square + gw**2, square_v + gv**2, square_b + gb**2
        step = RATE / np.sqrt(square)
        w = w - step * gw
        w = np.sign(w) * np.maximum(0, np.abs(w) - step * L1)
        v, b = v - RATE / np.sqrt(square_v) * gv, b - RATE / np.sqrt(square_b) * gb
    own = np.flatnonzero(w)
    return ToxicityModel(b, dict(zip(every[use[own]].tolist(), w[own].tolist(), strict=True)), v)


def _sample_features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for label, text in zip(batch.column(0).to_pylist(), batch.column(1).cast(pa.binary()).to_pylist(), strict=True):
            tokens = words(text)
            distinct = set(tokens)
            keys = np.unique(np.array([k for w in distinct for k in word_features(w)], dtype=np.uint64))
            yield pa.RecordBatch.from_arrays([pa.array([label], pa.int32()), pa.array([keys.tobytes()], pa.binary()), pa.array([patterns(text, tokens, len(distinct)).tobytes()], pa.binary())], ["label", "keys", "extra"])


def _fit_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One row: the model of all rows of the task, fitted in an order by content."""
    found = [r for batch in batches for r in zip(*(batch.column(c).to_pylist() for c in ("label", "keys", "extra")), strict=True)]
    found.sort(key=lambda r: (zlib.crc32(r[1]), r[1], r[0]))
    extra = np.array([np.frombuffer(x) for _, _, x in found]).reshape(-1, len(PATTERNS))
    model = fit([np.frombuffer(k, dtype=np.uint64) for _, k, _ in found], extra, np.array([y for y, _, _ in found]))
    yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(model)], pa.binary())], ["model"])


def train(docs: DataFrame, labels: DataFrame, learn: Column, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", sample_rows: int = SAMPLE_ROWS) -> ToxicityModel:
    """Fit on at most sample_rows of the distinct labelled rows that learn (over the id) marks; in one task, not on the driver."""
    ship(docs.sparkSession)
    own = labels.where(learn & F.col(label_col).isNotNull()).select(F.col(id_col).alias("id"), F.col(label_col).cast("int").alias("label"))
    # labels first, so that only texts of chosen ids are gathered; then rows, so that an id of very many rows doesn't count more
    chosen = distinct_sample(own, sample_rows, labels.count(), 7).groupBy("id").agg(F.max("label").alias("label"))
    met = docs.select(F.col(id_col).alias("id"), whole_text(text_col).alias("text")).join(F.broadcast(chosen), "id")
    texts = distinct_sample(met, sample_rows, met.select("id").count(), 7)
    found = texts.select("label", "text").mapInArrow(_sample_features, "label int, keys binary, extra binary").repartition(1).mapInArrow(_fit_rows, "model binary").collect()
    return pickle.loads(found[0]["model"]) if found else fit([], np.zeros((0, len(PATTERNS))), np.zeros(0))


def _score(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        for batch in batches:
            s = np.array([model.score(t.as_py()) for t in batch.column("text").cast(pa.binary())], dtype=np.float64)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(s), pa.array((s >= 0.5).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    return run


def score(docs: DataFrame, model: ToxicityModel, held: Column, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, score, predicted of every row."""
    ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    read = docs.select(F.col(id_col).cast("long").alias("doc_id"), held.alias("held_out"), whole_text(text_col).alias("text"))
    return read.mapInArrow(_score(shared), "doc_id long, held_out boolean, score double, predicted int")


def toxicity(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Train on labelled rows whose remainder by 5 is not 0, then score every row."""
    held = held_out("doc_id", 5, 0)
    return score(docs, train(docs, labels, ~held), held)
