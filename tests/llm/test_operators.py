"""Operators against SQL, brute force, exact round trips and held-out accuracy."""

import hashlib
import math
import re
import zlib
from collections import Counter

import duckdb
import numpy as np
import pytest
import xxhash
from conftest import DATA, same_rows
from pyspark.sql import functions as F

from orthant.llm import attention, chat, exact_dedup, langid, lm, mixing, packing, quality, queries, simhash, token_counts, tokens, toxicity
from orthant.llm.components import connected_components

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SF = f"{DATA}/sf0.001"
NASTY = [None, "", " ", "\n\t \x0b\x0c\r", "a", "a b", "  lead and trail  ", "Á é 　 x y", "<|endoftext|> a <|startoftext|>", "word " * 30_000, "x" * 9_000, "\x1c q", "it's  I'LL 's 12 3.4\n\n\nx", "😀 日本語 text", "İ ΑΣ. ΑΣ"]


@pytest.fixture(scope="module")
def texts():
    rows = duckdb.sql(f"SELECT doc_id, text, lang, source FROM '{SF}/documents.parquet' ORDER BY doc_id").fetchall()
    return [(i, t, lang, s, len(t)) for i, t, lang, s in rows] + [(1000 + i, t, "en" if i % 2 else None, None if i % 3 else "z", 0) for i, t in enumerate(NASTY)] + [(1001, "", "en", None, 0)]


@pytest.fixture(scope="module")
def docs(spark, texts):
    df = spark.createDataFrame(texts, "doc_id long, text string, lang string, source string, n_chars long").repartition(3)
    # extra columns whose names the operators use themselves
    for c in ("_hex", "_id", "_fp", "size", "cell", "key", "component_id", "_row", "pi", "kept", "fp", "_all", "n_words", "score"):
        df = df.selectExpr("*", f"doc_id AS `{c}`")
    return df


@pytest.fixture(scope="module")
def empty(docs):
    return docs.where("false")


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_queries_equal_their_sql(spark, name):
    assert same_rows(queries.queries()[name](spark, SF), queries.oracle_sql()[name], SF)


# ---- 1 mixing ----


def test_null_vectors():
    rng = np.random.default_rng(1)
    for p in (1, 2, 3):
        for _ in range(50):
            a = rng.integers(0, 4, (p, p + 1)).astype(float)
            u = mixing.null_vector([tuple(c) for c in a.T])
            assert max(map(abs, u)) > 0 and np.allclose(a @ u, 0)


def test_flight_keeps_totals():
    import random

    rng = np.random.default_rng(2)
    size = rng.integers(1, 500, 300).astype(float)
    pi = rng.random(300)
    balance = [(1.0, float(s)) for s in size]
    out = np.array(mixing.flight(pi.tolist(), balance, random.Random(3)))
    assert ((out > 0) & (out < 1)).sum() <= 2
    assert math.isclose(out.sum(), pi.sum(), rel_tol=1e-6) and math.isclose(out @ size, pi @ size, rel_tol=1e-6)


def test_flight_keeps_inclusion_probabilities():
    import random

    pi, balance = [0.2, 0.5, 0.8, 0.3, 0.7, 0.5], [(1.0, s) for s in (3.0, 1.0, 4.0, 1.0, 5.0, 9.0)]
    mean = np.mean([mixing.flight(pi, balance, random.Random(i)) for i in range(3000)], axis=0)
    assert np.allclose(mean, pi, atol=0.04)


def test_mix_by_brute_force(docs, texts):
    rows = mixing.mix(docs, chunk=8).collect()
    assert len(rows) == len(texts)
    size = {}
    for i, t, _, s, _ in texts:
        size.setdefault((s is None, s or ""), []).append(len(WORD.findall(t or "")))
    names, weight = sorted(size), {}
    for k, s in enumerate(names):
        weight[s] = (5, 2, 1)[k % 3]
    total = {s: sum(v) for s, v in size.items()}
    # share by weight, cap, reshare
    target, open_ = {}, set(names)
    left = float(sum(total.values()))
    while open_:
        w = sum(weight[s] for s in open_)
        over = [s for s in open_ if left * weight[s] / w > 3 * total[s]]
        if not over:
            target |= {s: left * weight[s] / w for s in open_}
            break
        for s in over:
            target[s] = 3.0 * total[s]
        left -= sum(target[s] for s in over)
        open_ -= set(over)
    of = {i: (s is None, s or "") for i, _, _, s, _ in texts}
    taken = Counter()
    for r in rows:
        s = of[r["doc_id"]]
        assert r["source_size"] == total[s] and math.isclose(r["target"], target[s], rel_tol=1e-9, abs_tol=1e-9)
        assert 0 <= r["taken"] <= 3 * r["size"] and (not r["size"] or r["taken"] % r["size"] == 0)
        taken[s] += r["taken"]
    for s in names:
        assert abs(taken[s] - target[s]) <= max(size[s], default=0)


def test_mix_comes_near_its_targets(spark):
    """Sources of fifty documents: within a few words, or a thousandth."""
    docs = spark.read.parquet(f"{DATA}/sf0.01/documents.parquet")
    met = mixing.mix(docs).join(docs.select("doc_id", "source"), "doc_id").groupBy("source").agg(F.first("target").alias("t"), F.sum("taken").alias("k"), F.count("*").alias("n")).collect()
    assert len(met) == 20 and all(r["n"] == 50 and abs(r["k"] - r["t"]) <= 3 + 0.001 * r["t"] for r in met)


def test_mix_of_null_and_equal_ids_and_texts(spark):
    """Rows without an id, or all with one, or with equal texts, are dealt into chunks like any others."""
    rows = [(None if i % 3 == 0 else 7 if i % 3 == 1 else i, f"a few words of {i} " * (1 + i % 9), "s") for i in range(3000)] + [(10_000 + i, "one and the same text", "t") for i in range(500)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    taken = mixing.mix(df, chunk=200).groupBy("source_size").agg(F.first("target").alias("t"), F.sum("taken").alias("k"), F.count("*").alias("n")).collect()
    assert sorted(r["n"] for r in taken) == [500, 3000] and all(abs(r["k"] - r["t"]) <= 20 for r in taken)
    hashed = df.withColumn("_row", F.xxhash64(*df.columns)).where("doc_id is null").select(F.xxhash64("doc_id", "_row", F.lit(42)).alias("h")).distinct().count()
    assert hashed == 1000  # one each, not one for all


def test_mix_reruns_agree(docs):
    a = sorted(map(tuple, mixing.mix(docs).collect()), key=str)
    assert a == sorted(map(tuple, mixing.mix(docs.repartition(7)).collect()), key=str)


def test_mix_copies(docs):
    told = {}
    for r in mixing.mix(docs, with_row=True).collect():
        told[r["_row"]] = told.get(r["_row"], 0) + r["_times"]
    got = mixing.copies(docs)
    assert got.columns == docs.columns and got.count() == sum(told.values())


# ---- 2 near copies ----


def test_variants_meet_within_three_bits():
    rng = np.random.default_rng(5)
    base = rng.integers(0, 2**63, 200, dtype=np.uint64)
    near = np.concatenate([base, *(base ^ np.array([sum(1 << int(b) for b in rng.choice(64, k, replace=False)) for _ in base], dtype=np.uint64) for k in (1, 2, 3, 4, 5))])
    near = np.unique(near)
    even = np.bitwise_count(near) % 2 == 0
    fp = np.concatenate([np.repeat(near[even], len(simhash.MASKS)), np.repeat(near[~even], len(simhash.ODD))])
    mask = np.concatenate([np.tile(np.arange(len(simhash.MASKS)), even.sum()), np.tile(simhash.ODD, (~even).sum())])
    a, b = simhash.forest(*simhash.links_in(fp, mask))
    label = {int(x): int(x) for x in near} | dict(zip(a.tolist(), b.tolist()))
    d = np.bitwise_count(near[:, None] ^ near[None, :]) <= 3
    want = np.arange(len(near))
    while True:
        new = np.array([want[d[i]].min() for i in range(len(near))])
        if (new == want).all():
            break
        want = new
    root = {}
    assert all(root.setdefault(int(w), label[int(x)]) == label[int(x)] for x, w in zip(near, want))
    assert len(set(want.tolist())) == len({label[int(x)] for x in near})


def plain_fingerprint(t):
    w = WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in t or ""))
    runs = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] if len(w) >= 3 else [" ".join(w)] if w else []
    h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in runs]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def test_near_groups_by_brute_force(docs, texts):
    rows = simhash.near_groups(docs).collect()
    fp = {(i, t): plain_fingerprint(t) for i, t, *_ in texts}
    assert sorted((r["doc_id"], r["fp"] % 2**64) for r in rows) == sorted((i, fp[i, t]) for i, t, *_ in texts)
    ids, f = np.array([i for i, *_ in texts]), np.array([fp[i, t] for i, t, *_ in texts], dtype=np.uint64)
    d, want = np.bitwise_count(f[:, None] ^ f[None, :]) <= 3, ids.copy()
    while True:
        new = np.array([want[d[i]].min() for i in range(len(ids))])
        if (new == want).all():
            break
        want = new
    assert sorted((r["doc_id"], r["component_id"]) for r in rows) == sorted(zip(ids.tolist(), want.tolist()))
    kept = simhash.keep_first(docs)
    assert kept.columns == docs.columns
    assert sorted(r["doc_id"] for r in kept.select("doc_id").collect()) == sorted(set(want.tolist()))


def test_components(spark):
    rng = np.random.default_rng(3)
    edges = [(int(a), int(b)) for a, b in rng.integers(0, 300, (200, 2))] + [(i, i + 1) for i in range(1000, 1060)] + [(5, 5), (7, None)]
    got = dict(map(tuple, connected_components(spark.createDataFrame(edges, "u long, v long")).collect()))
    up = {x: x for e in edges for x in e if x is not None}
    for _ in range(len(up)):
        before = dict(up)
        for a, b in edges:
            if b is not None:
                up[a] = up[b] = min(up[a], up[b])
        if before == up:
            break
    linked = {x for a, b in edges if b is not None and a != b for x in (a, b)}
    assert got == {x: up[x] for x in linked}


# ---- 3 token counts, tokenizers ----


@pytest.mark.parametrize(("name", "kind"), [("byte_bpe_50k.json", tokens.PieceTokenizer), ("byte_bpe_50k.json", tokens.ByteLevelTokenizer), ("word_bpe_49k.json", tokens.PieceTokenizer)])
def test_tokenizers_equal_the_library(texts, name, kind):
    from tokenizers import Tokenizer

    lib, own, all_texts = Tokenizer.from_file(tokens.vocabulary(name)), kind(tokens.vocabulary(name)), [t or "" for _, t, *_ in texts]
    want = [lib.encode(t, add_special_tokens=False).ids for t in all_texts]
    assert [np.frombuffer(x, dtype="<u4").tolist() for x in own.encode(all_texts)] == want
    assert own.count(all_texts) == [len(x) for x in want] == own.count(all_texts)


def test_token_counts_and_their_cache(spark, docs, texts, tmp_path):
    from tokenizers import Tokenizer

    path, lib = tokens.vocabulary("word_bpe_49k.json"), Tokenizer.from_file(tokens.vocabulary("word_bpe_49k.json"))
    want = sorted((i, len((t or "").encode()), n := len(lib.encode(t or "", add_special_tokens=False).ids), n > 2048) for i, t, *_ in texts)
    cache = str(tmp_path / "cache")
    first = token_counts.count_tokens(docs.where("doc_id < 100"), path, cache).count()
    stored = spark.read.parquet(cache).count()
    assert first == 100 and stored <= 100
    assert sorted(map(tuple, token_counts.count_tokens(docs, path, cache).collect())) == want
    all_stored = spark.read.parquet(cache).count()
    assert sorted(map(tuple, token_counts.count_tokens(docs, path, cache).collect())) == want
    assert spark.read.parquet(cache).count() == all_stored == len({t or "" for _, t, *_ in texts})
    files = len(spark.read.parquet(cache).inputFiles())
    assert sorted(map(tuple, token_counts.counts_cold_and_warm(docs, path).collect())) == want
    token_counts.count_tokens(docs, path, cache)
    assert len(spark.read.parquet(cache).inputFiles()) == files  # a warm run encodes and appends nothing


def test_token_digests_are_remembered_in_bounds(monkeypatch):
    monkeypatch.setattr(token_counts, "SEEN", 3)
    seen = set()
    assert token_counts._new([b"a", b"b", b"a"], seen) == [0, 1] and token_counts._new([b"c", b"d", b"a"], seen) == [0, 1]
    assert not seen and token_counts._new([b"a"], seen) == [0]


# ---- 4 exact copies ----


@pytest.mark.parametrize("min_rows", [2, 1000])
def test_exact_groups(docs, texts, min_rows):
    rows = exact_dedup.exact_groups(docs, min_rows=min_rows).collect()
    by = {}
    for i, t, *_ in texts:
        by.setdefault(t or "", []).append(i)
    want = sorted((i, max(by[t or ""]), len(by[t or ""]), hashlib.sha256((t or "").encode()).hexdigest()) for i, t, *_ in texts)
    assert sorted((r["doc_id"], r["keep_id"], r["group_size"], r["text_sha256"]) for r in rows) == want
    assert sorted(r["doc_id"] for r in rows if r["kept"]) == sorted(max(v) for v in by.values())
    kept = exact_dedup.keep_one(docs, min_rows=min_rows)
    assert kept.columns == docs.columns and sorted(r[0] for r in kept.select("doc_id").collect()) == sorted(max(v) for v in by.values())


def test_exact_groups_with_null_and_repeated_ids(spark):
    rows = [(None, "a"), (None, "a"), (3, "a"), (3, "a"), (None, "b"), (1, None), (2, "")]
    for min_rows in (1, 1000):
        got = exact_dedup.exact_groups(spark.createDataFrame(rows, "doc_id long, text string"), min_rows=min_rows).collect()
        assert sorted((str(r["doc_id"]), str(r["keep_id"]), r["group_size"], r["kept"]) for r in got) == [("1", "2", 2, False), ("2", "2", 2, True), ("3", "3", 4, False), ("3", "3", 4, True), ("None", "3", 4, False), ("None", "3", 4, False), ("None", "None", 1, True)]


# ---- 5 quality ----


def plain_quality(t):
    t = t or ""
    w = WORD.findall(t)
    seen, dup = set(), 0
    for line in t.split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    c = Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
    cover = {i + k for i in range(len(w) - 2) if c[tuple(w[i : i + 3])] > 1 for k in range(3)}
    return len(w), sum(map(len, w)), sum(x in "#*$%&|<>" for x in t), dup, len(cover), len(w) < 50 or 100 * len(cover) > 50 * len(w)


def test_quality_by_brute_force(docs, texts):
    rows = quality.judge(docs).collect()
    got = sorted((r["doc_id"], r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"], r["base_failed"]) for r in rows)
    assert got == sorted((i, *plain_quality(t)) for i, t, *_ in texts)
    assert not any(r["kept"] and r["base_failed"] for r in rows)


def test_many_repeated_windows(spark):
    t = " ".join(f"w{i % 40} x{i % 7} y{i}" if i % 3 else f"w{i % 40} x{i % 7} z" for i in range(900))
    r = quality.judge(spark.createDataFrame([(1, t, "en")], "doc_id long, text string, lang string")).first()
    assert (r["n_words"], r["n_repeat_words"]) == (plain_quality(t)[0], plain_quality(t)[4])


def test_distance(spark):
    p, q = [0.5, 0.5, 0.0], [0.0, 0.5, 0.5]
    from pyspark.sql import functions as F

    a = spark.range(1).select(quality.js_distance(F.array(*map(F.lit, p)), F.array(*map(F.lit, q))).alias("d")).first()["d"]
    kl = lambda x, m: sum(u * math.log2(u / v) for u, v in zip(x, m) if u)
    m = [(u + v) / 2 for u, v in zip(p, q)]
    assert math.isclose(a, math.sqrt((kl(p, m) + kl(q, m)) / 2))


def test_quality_keeps_clean_documents(spark):
    rows = quality.judge(spark.read.parquet(f"{DATA}/sf0.01/documents.parquet")).where("not base_failed and not kept").select("doc_id").collect()
    good = {r[0] for r in duckdb.sql(f"SELECT doc_id FROM '{DATA}/sf0.01/labels.parquet' WHERE quality = 1").fetchall()}
    assert not good & {r[0] for r in rows}


def test_quality_refuses_documents_without_common_words(spark):
    docs = duckdb.sql(f"SELECT doc_id, text, lang FROM '{DATA}/sf0.01/documents.parquet' WHERE lang = 'en' ORDER BY doc_id LIMIT 300").fetchall()
    bare = [(10_000_000 + i, " ".join(w for w in t.split() if w.lower().rstrip(".,;:!?") not in quality.COMMON), None) for i, t, _ in docs]
    rows = {r["doc_id"]: r for r in quality.judge(spark.createDataFrame(docs + bare, "doc_id long, text string, lang string")).collect()}
    # only the words speak against these
    tried = [r for i, r in rows.items() if i >= 10_000_000 and rows[i - 10_000_000]["kept"] and r["n_words"] >= 80 and not r["base_failed"] and r["char_distance"] <= quality.CHAR_DISTANCE]
    assert len(tried) > 10 and not any(r["kept"] for r in tried)


def test_verdicts_by_brute_force(docs, texts, monkeypatch):
    """References, distances and kept, in plain Python; thresholds at which both distances decide here."""
    monkeypatch.setattr(quality, "CHAR_DISTANCE", 0.05)
    monkeypatch.setattr(quality, "WORD_DISTANCE", 0.15)
    classes = [re.compile(c) for c in quality.CLASSES]

    def counts(t):
        t = t or ""
        k = [len(c.findall(t)) for c in classes]
        w = [x.lower().rstrip(".,;:!?") for x in WORD.findall(t)]
        c = [w.count(x) for x in quality.COMMON]
        return [*k, len(t) - sum(k)], [*c, len(w) - sum(c)]

    def distance(a, b):
        p, q = ([x / max(1, sum(v)) for x in v] for v in (a, b))
        return math.sqrt(max(0.0, sum(x * math.log2(2 * x / (x + y)) / 2 for v, u in ((p, q), (q, p)) for x, y in zip(v, u) if x)))

    own, refs = {}, {}
    for n, (i, t, lang, *_) in enumerate(texts):
        own[n] = (i, *counts(t), plain_quality(t))
        if lang is not None and not own[n][3][5]:
            have = refs.setdefault(lang, ([0] * len(own[n][1]), [0] * len(own[n][2])))
            refs[lang] = tuple([a + b for a, b in zip(x, y)] for x, y in zip(have, own[n][1:3]))
    want = []
    for n, (_, t, *_) in enumerate(texts):
        i, k, w, base = own[n]
        far = [min(distance(v, r[j]) for r in refs.values()) for j, v in enumerate((k, w))]
        odd = (len(t or "") >= quality.GUARD_CHARS and far[0] > 0.05) or (base[0] >= quality.GUARD_WORDS and far[1] > 0.15)
        want.append((i, not base[5] and not odd, round(far[0], 6), round(far[1], 6)))
    got = [(r["doc_id"], r["kept"], round(r["char_distance"], 6), round(r["word_distance"], 6)) for r in quality.judge(docs).collect()]
    assert sorted(got) == sorted(want) and len({k for _, k, *_ in want}) == 2


def test_three_hundred_languages(spark, monkeypatch):
    """Each language's documents pass by their own reference, in one block or in several."""
    rng = np.random.default_rng(3)
    words = [f"w{i}" for i in range(200)]
    rows = [(i, " ".join(rng.choice(words, 90)) + f" {'$' * (i % 300)}", f"l{i % 300}") for i in range(600)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    one = sorted(tuple(r) for r in quality.judge(df).collect())
    monkeypatch.setattr(quality, "BLOCK", 70)
    assert sorted(tuple(r) for r in quality.judge(df).collect()) == one
    assert max(r[-2] for r in one) < 0.1


# ---- 6 language model ----


def test_gradients():
    voc = attention.Vocabulary.of(np.arange(1000, 0, -1), 999)
    w = {k: a.astype(np.float64) for k, a in attention.start(voc).items()}
    rng = np.random.default_rng(0)
    x, scored, targets = attention.Windows([rng.integers(0, 900, 70)], voc).take(slice(None))
    loss = lambda w: attention.gradients(w, x, targets, scored, voc)[0]
    _, d, rows = attention.gradients(w, x, targets, scored, voc)
    whole = np.zeros_like(w["e"])
    whole[rows] = d["e"]
    d["e"] = whole
    for k in w:
        for i in [np.unravel_index(np.abs(d[k]).argmax(), d[k].shape), *(tuple(rng.integers(0, n) for n in d[k].shape) for _ in range(3))]:
            up, down = ({n: a.copy() for n, a in w.items()} for _ in range(2))
            up[k][i] += 1e-5
            down[k][i] -= 1e-5
            assert math.isclose(d[k][i], (loss(up) - loss(down)) / 2e-5, rel_tol=1e-3, abs_tol=1e-7)


def test_every_token_is_scored_once():
    voc = attention.Vocabulary.of(np.ones(1000), 999)
    for n in (0, 1, 7, 31, 32, 33, 55, 56, 57, 200):
        for overlap in (0, attention.OVERLAP):
            _, scored, targets = attention.Windows([np.arange(n), np.arange(3)], voc, overlap).take(slice(None))
            assert targets[scored].tolist() == [*range(n), 999, 0, 1, 2, 999]


def test_probabilities_sum_to_one():
    """Over all that may follow two subwords, by brute force; a later subword changes no earlier probability."""
    voc = attention.Vocabulary.of(np.arange(5000), 4999)
    w = attention.start(voc, 3)
    w["t"] = np.random.default_rng(4).normal(0, 0.5, w["t"].shape).astype(np.float32)
    each = np.array([attention.log10_tokens(w, [np.array([5, 7, i])], voc) for i in range(0, 5000, 97)])
    assert np.allclose(each[:, :2], each[0, :2], atol=1e-5)
    x, _, _ = attention.Windows([np.array([5, 7])], voc).take(slice(None))
    h = np.repeat(attention.body(w, x)[-1][2:3], 5000, axis=0)
    p = 10 ** (attention.outputs(w, h, np.arange(5000), voc)[0] / np.log(10) + voc.inside)
    assert math.isclose(p.sum(), 1, rel_tol=1e-4)
    assert np.allclose(np.log10(p[0:5000:97]), each[:, 2], atol=1e-4)


def test_score_by_brute_force():
    """One text at a time, place by place, against the batched windows."""
    voc = attention.Vocabulary.of(np.arange(300, 0, -1), 299)
    w = attention.start(voc, 5)
    rng = np.random.default_rng(6)
    texts = [rng.integers(0, 299, n) for n in (0, 1, 30, 33, 120)]
    got = attention.log10_probabilities(w, texts, voc)
    of = np.repeat(np.arange(len(voc.bounds) - 1), np.diff(voc.bounds))
    for text, have in zip(texts, got, strict=True):
        line, total, begin = [299, *text.tolist(), 299], 0.0, 0
        for t in range(1, len(line)):
            if t - 1 - begin == attention.WINDOW:
                begin += attention.WINDOW - attention.OVERLAP
            rows = np.zeros((1, attention.WINDOW), dtype=int)
            rows[0, : t - begin] = voc.row[line[begin:t]]
            h = attention.body(w, rows)[-1][t - 1 - begin]
            z, unit = np.exp(w["u"] @ h), voc.unit[line[t]]
            mine = np.exp(w["t"] @ h) * (of == of[unit])
            total += math.log10(z[of[unit]] / z.sum()) + math.log10(mine[unit] / mine.sum()) + voc.inside[line[t]]
        assert math.isclose(have, total, rel_tol=1e-4)


@pytest.mark.parametrize("heavy", [1_000_000, 200])
def test_lm_base_by_brute_force(docs, texts, heavy):
    path = tokens.vocabulary("byte_bpe_50k.json")
    rows = lm.score(docs, path, langid.held_out("doc_id", 7, 2), heavy=heavy).collect()
    words = [(i, (t or "").encode().lower().split()) for i, t, *_ in texts]
    c = Counter()
    for i, w in words:
        if zlib.crc32(str(i).encode()) % 7 != 2:
            c.update([*w, "end"])
    n, v = sum(c.values()), len(c)
    want = sorted((i, zlib.crc32(str(i).encode()) % 7 == 2, len(w) + 1, sum(c[x] > 0 for x in [*w, "end"]), n, round(sum(math.log10((c[x] + 1) / (n + v + 1)) for x in [*w, "end"]), 5)) for i, w in words)
    assert sorted((r["doc_id"], r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"], round(r["base_score"], 5)) for r in rows) == want
    assert all(r["score"] < 0 and math.isfinite(r["score"]) for r in rows)


def test_lm_score_does_not_depend_on_heavy(docs):
    path = tokens.vocabulary("byte_bpe_50k.json")
    few, all_ = (sorted((r["doc_id"], r["n_tokens"], r["score"]) for r in lm.score(docs, path, langid.held_out("doc_id", 7, 2), heavy=h).collect()) for h in (200, 1_000_000))
    assert len(few) == len(all_) and all(a[:2] == b[:2] and math.isclose(a[2], b[2], rel_tol=1e-9) for a, b in zip(few, all_, strict=True))


def test_network_is_not_cut():
    """Tokens after a window's start see at least 8 tokens of context; the dealt network's sizes."""
    voc = attention.Vocabulary.of(np.ones(5000), 999)
    _, scored, _ = attention.Windows([np.arange(200)], voc).take(slice(None))
    assert len(scored) > 1 and all(s.argmax() >= 8 for s in scored[1:])
    w = attention.start(voc)
    assert w["e"].shape[1] >= 24 and w["w1"].shape[1] >= 48 and len(w["t"]) >= 256


def test_every_training_document_trains(spark):
    """Windows trained on after the first fit: those of all training documents, each once."""
    path = tokens.vocabulary("byte_bpe_50k.json")
    rows = spark.createDataFrame([(i, f"word{i % 7} and more words of {i} " * (1 + i % 50)) for i in range(400)], "doc_id long, text string").repartition(5)
    counts = lm.corpus_counts(rows.select("text"))
    voc = attention.Vocabulary.of(lm.subword_counts(counts.where("word is not null"), path), lm.IDS - 1)
    sc, ids = spark.sparkContext, lm.word_ids(path)
    first, shared = sc.broadcast(attention.pack(attention.start(voc))), sc.broadcast(voc)
    seen = rows.select("text").mapInArrow(lm._refine(path, first, shared, 100, 2), "part int, n long, weights binary").agg(F.sum("n").alias("n")).first()["n"]
    every = lm.Run([r["text"].encode().lower().split() for r in rows.collect()]).sequences(ids)
    assert seen == len(attention.Windows(every, voc, 0))


def test_a_word_is_encoded_once_over_runs(monkeypatch):
    """Forgotten words are encoded again; the ids are the same."""
    ids = lm.word_ids(tokens.vocabulary("byte_bpe_50k.json"))
    runs = [[[b"one", b"two", b"one"], [], [b"drei"]], [[b"two", "z\u00fcgig".encode(), b"drei"]], [[b"one"]]]
    want, asked = [[s.tolist() for s in lm.Run(r).sequences(ids)] for r in runs], []
    of = lm.WordIds.of
    monkeypatch.setattr(lm.WordIds, "of", lambda self, words: asked.extend(words) or of(self, words))
    for most, n in ((100, 4), (2, 7)):
        monkeypatch.setattr(lm, "KNOWN", most)
        known = lm.Known(ids)
        assert [[s.tolist() for s in lm.Run(r, known).sequences(ids)] for r in runs] == want and len(asked) == n
        asked.clear()


def test_no_hidden_states_of_repeated_places(monkeypatch):
    """Those that are made equal the whole window's, and every token's log is that of one window at a time."""
    voc = attention.Vocabulary.of(np.arange(300, 0, -1), 299)
    w, rng = attention.start(voc, 5), np.random.default_rng(7)
    x, _, _ = attention.Windows([rng.integers(0, 299, 400)], voc).take(slice(None))
    whole = attention.body(w, x)[-1].reshape(len(x), attention.WINDOW, -1)
    assert np.allclose(attention.body(w, x, 8)[-1].reshape(len(x), attention.WINDOW - 8, -1), whole[:, 8:], atol=1e-5)
    texts, made, body = [rng.integers(0, 299, n) for n in (0, 1, 31, 32, 100, 400)], [], attention.body
    monkeypatch.setattr(attention, "body", lambda *a: made.append(b := body(*a)) or b)
    got = attention.log10_tokens(w, texts, voc, 3)
    every = attention.Windows(texts, voc)
    assert sum(len(b[-1]) for b in made) == len(every) * attention.WINDOW - (every.number > 0).sum() * attention.OVERLAP
    x, scored, targets = every.take(slice(None))
    want = attention.outputs(w, body(w, x)[-1][scored.ravel()], targets[scored], voc)[0] / np.log(10) + voc.inside[targets[scored]]
    assert len(got) == sum(len(s) + 1 for s in texts) and np.allclose(got, want, atol=1e-5)


def test_model_beats_the_base_on_held_out_texts(spark):
    """log10 per word of held-out documents of sf 0.01."""
    docs = spark.read.parquet(f"{DATA}/sf0.01/documents.parquet")
    got = lm.lm_scores(docs, tokens.vocabulary("byte_bpe_50k.json")).where("held_out").agg(F.sum("score").alias("m"), F.sum("base_score").alias("b"), F.sum("n_tokens").alias("n")).first()
    assert got["m"] / got["n"] > got["b"] / got["n"] + 0.02


# ---- 7 and 8, held out ----


def test_toxicity_held_out(spark):
    sf = f"{DATA}/sf0.1"
    got = {r["doc_id"]: r for r in queries.op7_toxicity(spark, sf).collect()}
    truth = duckdb.sql(f"SELECT doc_id, toxic FROM '{sf}/labels.parquet'").fetchall()
    held = [(got[i]["predicted"], y) for i, y in truth if got[i]["held_out"]]
    hits = sum(a == b == 1 for a, b in held)
    assert hits / sum(a for a, _ in held) > 0.9 and hits / sum(b for _, b in held) > 0.75
    assert all(0 <= r["score"] <= 1 and r["predicted"] == (r["score"] >= 0.5) for r in got.values())
    assert all(r["held_out"] == (zlib.crc32(str(i).encode()) % 5 == 0) for i, r in got.items())


def test_label_model_estimates_rates_and_dependencies():
    """Three copies of one voter hang together and count once; the given label's reliability is estimated, not set."""
    rng = np.random.default_rng(4)
    y = rng.random(6000) < 0.3
    noisy = lambda p, q: np.where(y, rng.random(6000) < p, rng.random(6000) < q).astype(float)
    a, b, c = noisy(0.7, 0.1), noisy(0.6, 0.2), noisy(0.65, 0.1)
    votes, given = np.stack([a, a, a, b, c], axis=1), np.where(rng.random(6000) < 0.1, ~y, y).astype(int)
    model = toxicity.fit_label_model(votes, given)
    assert model.parent[:3].tolist().count(-1) == 1 and {*model.parent[:3].tolist()} <= {-1, 0, 1, 2} and model.parent[5] == -1
    p = model.posterior(np.column_stack([votes, given == 1]).astype(float))
    assert ((p > 0.5) == y).mean() > (given == y).mean() and abs(model.prior - 0.3) < 0.05
    assert abs(model.fires[5, 1, 0] - 0.9) < 0.09 and abs(model.fires[5, 0, 0] - 0.1) < 0.09
    once = toxicity.fit_label_model(votes[:, 2:], given)
    full = lambda v: np.column_stack([v, given == 1]).astype(float)
    assert np.allclose(model.posterior(full(votes)), once.posterior(full(votes[:, 2:])), atol=0.02)


def test_dependencies_by_brute_force():
    """Greatest spanning tree over the significant pairs: its total is that of the best tree among all."""
    from itertools import product

    rng = np.random.default_rng(5)
    x = rng.integers(0, 2, (400, 4)).astype(float)
    x[:, 1] = np.where(rng.random(400) < 0.8, x[:, 0], x[:, 1])
    x[:, 3] = np.where(rng.random(400) < 0.7, x[:, 1], x[:, 3])
    p = np.full(400, 0.5)

    def information(i, j):
        total = 0.0
        for u, v in product((0, 1), repeat=2):
            both, one, two = ((x[:, i] == u) & (x[:, j] == v)).mean(), (x[:, i] == u).mean(), (x[:, j] == v).mean()
            total += both * math.log(both / one / two) if both else 0
        return total if 2 * 400 * total > toxicity.SIGNIFICANT else 0.0

    got = sum(information(i, int(k)) for i, k in enumerate(toxicity.dependencies(x, p)) if k >= 0)
    best = max(sum(information(i, j) for i, j in tree) for tree in product(*([(i, j) for j in range(4) if j != i] for i in range(1, 4))) if all(len({0} | {a for a, _ in tree}) == 4 for _ in (0,)) and _is_tree(tree))
    assert math.isclose(got, best, rel_tol=1e-9)


def _is_tree(edges):
    reached = {0}
    for _ in edges:
        reached |= {a for a, b in edges if b in reached}
    return len(reached) == 4


def test_one_id_on_very_many_rows(spark):
    """Samples hold rows, not ids: ten thousand rows of one id, alike or not, neither enlarge nor take over the sample."""
    some = [(i, f"les mots français de {i} " * 5 if i % 2 else f"some English words about {i} " * 5, "fr" if i % 2 else "en") for i in range(300)]
    alike = [(7, "les mots français de tous les jours", "fr")] * 5000 + [(8, f"some English words number {i}", "en") for i in range(5000)]
    rows = spark.createDataFrame(some + alike, "doc_id long, text string, lang string")
    from orthant.llm.common import distinct_sample

    assert distinct_sample(rows, 200, 10_300, 8).count() == 200
    assert distinct_sample(rows, 20_000, 10_300, 8).count() == 300 + 1 + 5000
    model = langid.train(rows, F.lit(True), sample_rows=500)
    assert model.predict("les mots de tous")[0] == "fr" and model.predict("some words about")[0] == "en"
    labels = spark.createDataFrame([(i, int(i % 2)) for i in range(300)], "doc_id long, toxic int")
    found = toxicity.train(rows, labels, F.lit(True), sample_rows=500)
    assert found.score("les mots français".encode()) > 0.5 > found.score(b"some English words about")


def test_letters(spark):
    rows = [(i, t, "en" if i % 2 else "fr") for i, t in enumerate(["½ 12", "①", "²", "Ⅷ", "१२", "ª", "a½", "é", "日本", "_", "12"])]
    got = {r["doc_id"]: r["lang_pred"] for r in langid.identify(spark.createDataFrame(rows, "doc_id long, text string, lang string"), langid.train(spark.createDataFrame([(100, "one text", "en"), (101, "un texte", "fr")], "doc_id long, text string, lang string"), F.lit(True)), F.lit(False)).collect()}
    assert {i for i, x in got.items() if x == "und"} == {0, 1, 2, 3, 4, 9, 10}


def test_language_held_out(spark):
    sf = f"{DATA}/sf0.01"
    got = {r["doc_id"]: r for r in queries.op8_language_id(spark, sf).collect()}
    truth = dict(duckdb.sql(f"SELECT doc_id, lang FROM '{sf}/documents.parquet'").fetchall())
    held = [r for r in got.values() if r["held_out"]]
    assert sum(r["lang_pred"] == truth[r["doc_id"]] for r in held) / len(held) > 0.98
    assert all(r["held_out"] == (zlib.crc32(str(i).encode()) % 4 == 2) for i, r in got.items())


def test_language_of_odd_texts(docs):
    rows = [r for r in langid.languages(docs).collect() if r["doc_id"] >= 1000]
    blank = {1000 + i for i, t in enumerate(NASTY) if not t or not any(c.isalpha() for c in t)} | {1001}
    assert {r["doc_id"] for r in rows if r["lang_pred"] == "und"} == blank
    assert all(0 <= r["score"] <= 1 for r in rows)


def test_grams_do_not_depend_on_stretches(monkeypatch):
    t = "Some text, ñandú. " * 40
    whole = langid.grams(t)
    monkeypatch.setattr(langid, "STRETCH", 7)
    assert (langid.grams(t) == whole).all() and whole.sum() == 3 * len(t) - 3


# ---- 9 packing ----


def test_packing(docs, texts):
    from tokenizers import Tokenizer

    lib = Tokenizer.from_file(tokens.vocabulary("byte_bpe_50k.json"))
    rows = packing.pack(docs, tokens.vocabulary("byte_bpe_50k.json")).collect()
    want = []
    for i, t, *_ in texts:
        ids = [*lib.encode(t or "", add_special_tokens=False).ids, 0]
        cut = len(ids) % 2048 or 2048
        bounds = [0, *range(min(cut, len(ids)), len(ids) + 1, 2048)]
        want += [(i, k, a, b - a, zlib.crc32(np.array(ids[a:b], dtype="<u4").tobytes())) for k, (a, b) in enumerate(zip(bounds, bounds[1:]))]
    assert sorted((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in rows) == sorted(want)
    by = {}
    for r in rows:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for places in by.values():
        at = 0
        for offset, length in sorted(places):
            assert offset == at
            at += length
        assert at <= 2048
    # a few hundred documents: the best known packing is at most one above the bound
    assert len(by) - packing.lower_bound(Counter(r["length"] for r in rows), 2048) in (0, 1)


def least_bins(items, capacity):
    best = [len(items)]

    def go(k, bins):
        if len(bins) >= best[0]:
            return
        if k == len(items):
            best[0] = len(bins)
            return
        for i in range(len(bins)):
            if bins[i] + items[k] <= capacity:
                bins[i] += items[k]
                go(k + 1, bins)
                bins[i] -= items[k]
        go(k + 1, [*bins, items[k]])

    go(0, [])
    return best[0]


def test_packing_is_optimal_on_small_cases():
    rng = np.random.default_rng(6)
    for _ in range(150):
        capacity = int(rng.integers(8, 30))
        items = sorted(rng.integers(1, capacity + 1, rng.integers(1, 10)).tolist(), reverse=True)
        plan = packing.pack_histogram(Counter(items), capacity)
        used = Counter()
        for parts, times in plan.patterns:
            assert sum(parts) <= capacity
            for x in parts:
                used[x] += times
        assert used == Counter(items) and plan.bound <= plan.sequences == sum(t for _, t in plan.patterns)
        assert plan.sequences == least_bins(items, capacity)


def used_by(plan, capacity):
    assert all(sum(parts) <= capacity and times > 0 for parts, times in plan)
    return sum((Counter({x: times * parts.count(x) for x in set(parts)}) for parts, times in plan), Counter())


def test_best_fit_decreasing_equals_piece_by_piece():
    rng = np.random.default_rng(8)
    for _ in range(200):
        capacity = int(rng.integers(10, 60))
        items = rng.integers(1, capacity + 1, rng.integers(1, 60)).tolist()
        rooms = []
        for x in sorted(items, reverse=True):
            fits = [r for r in rooms if r >= x]
            if fits:
                rooms.remove(min(fits))
            rooms.append((min(fits) if fits else capacity) - x)
        plan = packing.best_fit_decreasing(Counter(items), capacity)
        assert used_by(plan, capacity) == Counter(items) and sum(t for _, t in plan) == len(rooms)


def test_packing_is_optimal_around_a_third_of_the_capacity():
    rng, better = np.random.default_rng(9), 0
    for _ in range(60):
        items = sorted(rng.integers(22, 42, rng.integers(12, 18)).tolist(), reverse=True)
        plan = packing.pack_histogram(Counter(items), 100)
        assert used_by(plan.patterns, 100) == Counter(items) and plan.sequences == least_bins(items, 100)
        better += plan.sequences < sum(t for _, t in packing.best_fit_decreasing(Counter(items), 100))
    assert better


def test_fillings_are_all_undominated_ones():
    """Against all subsets: a filling is out if one piece that stays out could take the place of several or of a shorter one."""
    from itertools import combinations

    rng = np.random.default_rng(10)
    for _ in range(60):
        room, items = 40, sorted(rng.integers(3, 30, 7).tolist(), reverse=True)
        lengths = sorted(set(items), reverse=True)
        want = set()
        for k in range(len(items) + 1):
            for own in combinations(range(len(items)), k):
                waste = room - sum(items[i] for i in own)
                if waste < 0:
                    continue
                parts, out = [items[i] for i in own], Counter(items) - Counter(items[i] for i in own)
                swaps = [t for j in range(len(parts) + 1) for t in combinations(parts, j)]
                if not any(sum(t) <= y <= sum(t) + waste and (len(t) != 1 or t[0] < y) for t in swaps for y in out if y <= room):
                    want.add((waste, tuple(parts)))
        got = [f for f in packing.fillings(lengths, [items.count(x) for x in lengths], room, room) if f[1] is not None]
        assert set(got) == want and len(got) == len(want) and [w for w, _ in got] == sorted(w for w, _ in got)


def test_search_beats_best_fit_on_hard_lengths():
    items = Counter(np.random.default_rng(1).integers(500, 1101, 3000).tolist())
    plan = packing.pack_histogram(items)
    assert used_by(plan.patterns, packing.CAPACITY) == items
    assert plan.sequences <= 0.97 * sum(t for _, t in packing.best_fit_decreasing(items, packing.CAPACITY)) and plan.sequences < 1266


# ---- 10 chat ----

TURNS = [
    (1, 0, "user", "hi"), (1, 1, "assistant", "</s>[INST] ok"), (1, 2, "assistant", "\\e\\l\\b [x] <y>"), (1, 2, "assistant", "\\e\\l\\b [x] <y>"), (2, 0, "a\nb", "x\ny"), (2, 1, "[INST]", ""), (2, None, None, None),
    (3, 0, "assistant", ""), (4, 0, "\\ user", "t"), (None, 0, "assistant", "n"), (5, 5, "user", "é😀"), (5, 1, "user</s>", "</s></s>"),
]


def test_chat_round_trip(spark):
    df = spark.createDataFrame(TURNS, "conv_id long, turn long, role string, text string").selectExpr("*", "turn AS formatted", "role AS turns", "text AS r")
    got = {r["conv_id"]: r for r in chat.format_chats(chat.with_probe(df)).collect()}
    by = {}
    for c, n, r, t in [*TURNS, (-7, 0, "user", chat.PROBE_TEXT), (-7, 1, "assistant", chat.PROBE_TEXT)]:
        by.setdefault(c, []).append((n is not None, n or 0, r or "", t or ""))
    assert set(got) == set(by)
    for c, turns in by.items():
        assert [(x["role"], x["text"]) for x in got[c]["turns"]] == [(r, t) for _, _, r, t in sorted(turns)]
        assert got[c]["formatted"].count("</s>") == len(turns)
    d = {r["conv_id"]: r for r in chat.digests(chat.format_chats(chat.with_probe(df))).collect()}
    for c, turns in by.items():
        loss = "".join(t for _, _, r, t in sorted(turns) if r == "assistant")
        assert (d[c]["loss_chars"], d[c]["loss_sha256"]) == (len(loss), hashlib.sha256(loss.encode()).hexdigest())


def test_chat_escapes_until_identical(spark, monkeypatch):
    """Without the look for control strings the round trip alone finds what to escape, in as many rounds as it takes."""
    monkeypatch.setattr(chat, "CONTROL", ())
    hard = [(9, i, r, t) for i, (r, t) in enumerate([("u", "a</s>b"), ("u", "[INST] u\nx"), ("v\nw", "</s>[INST] u\nx</s>"), ("u", "plain"), ("\\ u", "</s>"), ("u", "")])]
    rows = [*hard, (10, 0, "u", "plain"), (11, 0, "\\ u", "x")]
    got = {r["conv_id"]: r for r in chat.format_chats(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()}
    for c in (9, 10, 11):
        assert got[c]["same"] and [(x["role"], x["text"]) for x in got[c]["turns"]] == [(r, t) for k, _, r, t in rows if k == c]
    assert got[9]["formatted"].count(chat.ESCAPED) < len(hard) and chat.ESCAPED not in got[10]["formatted"]


# ---- empty tables ----


def test_empty_tables(spark, empty):
    path = tokens.vocabulary("byte_bpe_50k.json")
    labels = spark.createDataFrame([], "doc_id long, toxic int")
    for df in (mixing.mix(empty), mixing.copies(empty), simhash.near_dedup(empty), simhash.keep_first(empty), token_counts.count_tokens(empty, path), exact_dedup.exact_groups(empty), exact_dedup.keep_one(empty), quality.judge(empty), lm.lm_scores(empty, path), toxicity.toxicity(empty, labels), langid.languages(empty), langid.keep_identified(empty), packing.pack(empty, path)):
        assert df.count() == 0
    none = spark.createDataFrame([], "conv_id long, turn long, role string, text string")
    assert chat.format_chats(none).count() == 0


def test_toxicity_without_labels(docs, spark):
    got = toxicity.toxicity(docs, spark.createDataFrame([(1, None)], "doc_id long, toxic int")).collect()
    assert all(r["predicted"] == 0 and 0 <= r["score"] < 1e-6 for r in got)
