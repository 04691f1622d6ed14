"""Quality and language: held-out accuracy on the given tables, and odd rows."""

from __future__ import annotations

import math
import re
import zlib
from collections import Counter

import numpy as np
import pytest

from blocksketch.llm import common, language, quality, queries

BIG = "/root/testdata/sf0.01"
DOCS = "doc_id long, text string, lang string, source string, n_chars long, score string"


def test_quality_parts_held_out_labels(spark):
    out = queries.op4_quality_classifier(spark, BIG)
    labels = spark.read.parquet(f"{BIG}/labels.parquet").select("doc_id", "quality")
    rows = out.join(labels, "doc_id").where("held_out").collect()
    good, bad = [r.score for r in rows if r.quality == 1], [r.score for r in rows if r.quality == 0]
    auc = np.mean([(g > b) + 0.5 * (g == b) for g in good for b in bad])
    assert auc > 0.95
    assert np.mean([r.predicted == r.quality for r in rows]) > 0.95
    assert out.where("held_out <> (pmod(crc32(cast(doc_id as string)), 5) = 0) or score < 0 or score > 1 or (predicted = 1) <> (score >= 0.3)").count() == 0


def test_quality_odd_rows(spark):
    docs = spark.createDataFrame([(1, None, None, None, 0, "x"), (2, "", "en", "s", 0, "x"), (2, "", "en", "s", 0, "x"), (None, "word " * 9, "en", "s", 0, "x"), (4, "!" * 90_000, "en", "s", 0, "x")], DOCS)
    labels = spark.createDataFrame([(1, None, 0), (2, 1, 0), (2, 0, 0), (None, 1, 0)], "doc_id long, quality int, toxic int")
    out = quality.score_documents(docs, labels).collect()
    assert len(out) == 5 and all(r.score == 0.5 for r in out)
    assert quality.score_documents(docs.limit(0), labels).count() == 0


def test_bradley_terry_recovers_the_order():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(400, 18))
    y = (x[:, 0] - 2 * x[:, 1] > 0).astype(int)
    model = quality.learn(x, y)
    assert model.weights[0] > 0 > model.weights[1]
    assert abs(model.weights[1]) > abs(model.weights[0])
    s = ((x - model.centre) / model.scale) @ model.weights * model.slope + model.offset
    assert ((1 / (1 + np.exp(-s)) >= 0.3) == y).mean() > 0.97


def test_language_on_held_out_rows(spark):
    out = queries.op5_language_id(spark, BIG)
    docs = spark.read.parquet(f"{BIG}/documents.parquet").select("doc_id", "lang")
    rows = out.join(docs, "doc_id").where("held_out and lang is not null").collect()
    assert np.mean([r.lang_pred == r.lang for r in rows]) > 0.97
    assert all(0 <= r.score <= 1 for r in rows)


def test_language_odd_rows(spark):
    rows = [(1, "the other thing and then there", "en"), (2, "der andere und die sache", "de"), (3, "nur ein anderes wort der", "de")] * 4
    docs = spark.createDataFrame([(i, t, lang, "s", 0, "x") for i, t, lang in rows], DOCS)
    learned = language.learn(docs)
    assert learned.names == ["de", "en"]
    odd = spark.createDataFrame([(1, None, None, None, 0, "x"), (2, "", "en", "s", 0, "x"), (3, "12 !? 3", "en", "s", 0, "x"), (4, "and then the other", "de", "s", 0, "x"), (5, "die sache und " * 30_000, "en", "s", 0, "x"), (5, "q", "en", "s", 0, "x")], DOCS)
    got = [(r.doc_id, r.lang_pred) for r in language.identify(odd, learned).orderBy("doc_id").collect()]
    assert got[:5] == [(1, "und"), (2, "und"), (3, "und"), (4, "en"), (5, "de")]
    nothing = language.learn(docs.where("lang is null"))
    assert {r.lang_pred for r in language.identify(odd, nothing).collect()} == {"und"}
    assert language.identify(odd.limit(0), learned).count() == 0


def test_filter_returns_all_languages_of_a_gram(spark):
    docs = spark.createDataFrame([(i, "shared onlyen" if i % 2 else "shared onlyde", "en" if i % 2 else "de", "s", 0, "x") for i in range(20)], DOCS)
    f = language.learn(docs)
    data = np.frombuffer(b"shared", np.uint8)
    owner, key = language.grams_of(data, np.array([0, 6]))
    one, two = language._slots(key, len(f.masks))
    assert set((f.masks[one, 0] & f.masks[two, 0]).tolist()) == {3}


def naive_features(text):
    """The same features by plain counting, in Python's own numbers."""
    raw = (text or "").encode()
    if not raw:
        return [0.0] * quality.WIDTH
    n = len(raw)
    out = [math.sqrt(sum(raw.count(bytes([c])) for c in members) / n) for members in quality._CLASSES.values()]
    shares = [raw.count(bytes([c])) / n for c in set(raw)]
    words = re.findall(rb"[0-9A-Za-z\x80-\xff]+", raw)
    many = max(1, len(words))
    counts = Counter(words)
    out += [-sum(p * math.log2(p) for p in shares), math.log1p(n)]
    out += [math.log1p(sum(map(len, words)) / many), sum(a == b for a, b in zip(words, words[1:], strict=False)) / many, len(counts) / many**0.8] if words else [0.0] * 3
    out += [math.log1p(n / (raw.count(b"\n") + 1)), max(counts.values()) / many if words else 0.0]

    def mix(v):
        return int(common.mix(np.array([v & (2**64 - 1)], np.uint64))[0])

    code = lambda w: sum(mix(c + 257 * (i + 1)) for i, c in enumerate(w)) & (2**64 - 1)
    slots = Counter(code(w) % quality.HASHED for w in words)
    slots.update(mix(code(u) * 3 + code(v)) % quality.HASHED for u, v in zip(words, words[1:], strict=False))
    return out + [math.sqrt(slots[i] / (2 * many)) for i in range(quality.HASHED)]


def test_quality_features_and_scores_against_plain_counting(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.001/labels.parquet")
    rows = [(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()] + [(10**9, None), (10**9 + 1, ""), (10**9 + 2, "!!!"), (10**9 + 3, "a a")]
    naive = {i: naive_features(t) for i, t in rows}
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    for r in quality.featured(df, ("doc_id",)).collect():
        assert np.allclose(np.frombuffer(r.x, "<f4"), naive[r.doc_id], atol=1e-5)
    learns = {r.doc_id: r.quality for r in labels.collect() if r.quality is not None and zlib.crc32(str(r.doc_id).encode()) % 5 and r.doc_id in naive}
    x, y = np.array([naive[i] for i in learns], np.float32), np.array(list(learns.values()))
    order = np.argsort(list(learns))
    model = quality.learn(x[order], y[order])
    for r in quality.score_documents(df, labels).collect():
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0)
        assert r.score == pytest.approx(float(model.score(np.array([naive[r.doc_id]]))[0]), abs=2e-3)
        assert r.predicted == (r.score >= 0.3)


def test_threshold_is_a_quantile_of_the_scores():
    s = np.array([5.0, 1.0, 2.0, 3.0, 4.0])
    assert quality.quantile_cut(s, 0.4) == 2.5
    assert quality.quantile_cut(s, 0.0) == 1.5 and quality.quantile_cut(s, 1.0) == 4.5 and quality.quantile_cut(s[:1], 0.5) == 5.0


def naive_grams(text):
    """Four-byte n-grams of folded UTF-8 with the blanks at both ends, but those with two blanks side by side."""
    raw = bytes(c + 32 if 65 <= c <= 90 else c if 97 <= c <= 122 or c >= 128 else 32 for c in text.encode())
    padded = b" " + raw + b"  "
    return [padded[i : i + 4] for i in range(len(raw)) if b"  " not in padded[i : i + 4]]


def test_language_against_exact_sets(spark):
    """Learned sets and predictions against plain sets: the filter adds false positives and loses none."""
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").where("lang is not null and text is not null")
    rows = [(r.doc_id, r.text, r.lang) for r in docs.collect()]
    f = language.learn(docs.repartition(7))
    counts = {n: Counter(g for _, t, lang in rows if lang == n for g in naive_grams(t)) for n in f.names}
    total = {n: sum(c.values()) for n, c in counts.items()}
    rate = lambda n, g: counts[n][g] / total[n]
    grams = set().union(*counts.values())
    best = {g: max(rate(n, g) for n in f.names) for g in grams}
    sets = {n: {g for g in counts[n] if counts[n][g] >= 3 and rate(n, g) >= 1e-6 and rate(n, g) >= 0.3 * best[g]} for n in f.names}
    false = Counter()
    for g in grams:
        one, two = language._slots(np.array([int.from_bytes(g, "big")], np.uint64), len(f.masks))
        mask = int((f.masks[one, 0] & f.masks[two, 0])[0])
        for i, n in enumerate(f.names):
            assert g not in sets[n] or mask >> i & 1
            false[n] += g not in sets[n] and mask >> i & 1
    assert all(false[n] <= 3 * f.rates[i] * len(grams) + 10 for i, n in enumerate(f.names))
    got = {r.doc_id: r.lang_pred for r in language.identify(docs, f).collect()}
    agree = 0
    for i, t, _ in rows:
        hits = {n: sum(g in sets[n] for g in naive_grams(t)) for n in f.names}
        agree += got[i] in [n for n in f.names if hits[n] == max(hits.values())] or max(hits.values()) == 0
    assert agree >= 0.99 * len(rows)


def test_full_filter_does_not_divide_by_zero():
    f = language.LanguageFilter(["a", "b"], np.full((1 << 16, 1), 3, np.uint64), np.ones(2))
    best, score = f.predict(np.frombuffer(b"some text here", np.uint8), np.array([0, 14]))
    assert np.isfinite(score).all() and score[0] == 0.0 and best[0] in (0, 1)


if __name__ == "__main__":
    pytest.main([__file__])
