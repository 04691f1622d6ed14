"""Repeated strings, similar documents and near vectors against brute force."""

from __future__ import annotations

import hashlib
import random
import re

import numpy as np
import pytest

from blocksketch.llm import components, embedding_dedup, ngram_join, suffix_dedup

DOCS = "doc_id long, text string, spans string"


def brute_repeats(rows, n):
    first: dict[bytes, int] = {}
    key = lambda i: float("inf") if i is None else i
    for i, t in rows:
        b = (t or "").encode()
        for p in range(len(b) - n + 1):
            s = b[p : p + n]
            first[s] = min(first.get(s, float("inf")), key(i))
    out = []
    for i, t in rows:
        b = (t or "").encode()
        gone = np.zeros(len(b), bool)
        for p in range(len(b) - n + 1):
            if first[b[p : p + n]] < key(i):
                gone[p : p + n] = True
        kept = bytes(c for c, g in zip(b, gone, strict=True) if not g)
        out.append((i, len(b), int(gone.sum()), int((gone & ~np.r_[False, gone[:-1]]).sum()), hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=str)


@pytest.mark.parametrize(("n", "seed"), [(6, 1), (10, 2), (50, 3)])
def test_repeats_of_random_texts(spark, n, seed):
    rng = random.Random(seed)
    alphabet = "ab" if n < 50 else "abcdé"
    parts = ["".join(rng.choice(alphabet) for _ in range(rng.randrange(2, 3 * n))) for _ in range(12)]
    rows = [(i, "".join(rng.choice(parts) for _ in range(rng.randrange(6)))) for i in range(25)]
    rows += [(50 + i, "=" * (40 * i) + "ab" * 90 + parts[0] * 9) for i in range(4)]
    rows += [(7, rows[7][1]), (None, rows[3][1]), (None, None), (40, ""), (41, rows[5][1] + "x"), (41, "y" + rows[5][1]), (90, "ab" * 3000)]
    df = spark.createDataFrame([(i, t, "clash") for i, t in rows], DOCS).repartition(5)
    got = sorted((tuple(r) for r in suffix_dedup.remove_repeats(df, n=n).collect()), key=str)
    assert got == brute_repeats(rows, n)


def test_repeats_of_the_documents(spark, sf_dir):
    df = spark.read.parquet(f"{sf_dir}/documents.parquet").repartition(7)
    rows = [(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()]
    got = sorted((tuple(r) for r in suffix_dedup.remove_repeats(df).collect()), key=str)
    assert got == brute_repeats(rows, 50)


def test_repeats_of_nothing(spark):
    assert suffix_dedup.remove_repeats(spark.createDataFrame([], DOCS)).count() == 0


def test_repeats_of_many_rows_with_one_id(spark):
    rng = random.Random(4)
    shared = "a passage that is shared by very many rows of the same table, word by word"
    rows = [(None, f"{rng.random()} {shared} {rng.random()}") for _ in range(3000)] + [(9, f"{shared}{i}") for i in range(400)]
    rows += [((1 << 63) - 1, shared + "?"), ((1 << 63) - 1, "." + shared), (12, shared), (12, shared), (12, shared)]
    df = spark.createDataFrame([(i, t, "x") for i, t in rows], DOCS).repartition(9)
    got = sorted((tuple(r) for r in suffix_dedup.remove_repeats(df).collect()), key=str)
    assert got == brute_repeats(rows, 50)


def test_the_largest_id_comes_before_null(spark):
    text = "words that stand in two rows, of which one has no id, and that are long enough"
    rows = [(None, text + "a"), ((1 << 63) - 1, text + "b")]
    got = {r.doc_id: r.n_removed for r in suffix_dedup.remove_repeats(spark.createDataFrame([(i, t, "x") for i, t in rows], DOCS)).collect()}
    assert got == {None: len(text), (1 << 63) - 1: 0}


def _names(rows):
    cols = [np.array(c, np.int64) for c in zip(*rows, strict=True)]
    return cols[0].view(np.uint64), cols[1].view(np.uint64), *cols[2:]


@pytest.mark.parametrize("parts", [1, 3, 7])
def test_rounds_settle_names_across_batches(spark, parts):
    """Runs of one name come from several scans, which each settle what they see themselves."""
    rng = random.Random(parts)
    rows = [(rng.randrange(6), 0, rng.randrange(4), 0, rng.randrange(1 << 20) << 12) for _ in range(300)] + [(90, 0, 3, 0, 1 << 12), (90, 0, 3, 0, 2 << 12), (91, 0, 3, 0, 5 << 12)]
    some = [rows[i::parts] for i in range(parts)]

    def sent(settle):
        made = [settle(*_names(r)).to_pylist() for r in some]
        return spark.createDataFrame([tuple(r[c] for c in ("a", "b", "doc", "tag", "at", "also")) for m in made for r in m], suffix_dedup._ROWS)

    docs_of = {a: {r[2] for r in rows if r[0] == a} for a, *_ in rows}
    told = {(r.doc, r.at) for r in suffix_dedup.repeated(sent(suffix_dedup.settle_repeated)).collect()}
    assert told == {(r[2], r[4]) for r in rows if len(docs_of[r[0]]) > 1}
    later = {(r.doc, r.at) for r in suffix_dedup.later_of_equal_names(sent(suffix_dedup.settle_later)).collect()}
    assert later == {(r[2], r[4]) for r in rows if r[2] > min(docs_of[r[0]])}


def shingles(text, n=5):
    words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    return {tuple(words[i : i + n]) for i in range(max(1, len(words) - n + 1))} if words else set()


def brute_groups(items, linked):
    n = len(items)
    near = [[j for j in range(n) if j != i and linked(items[i], items[j])] for i in range(n)]
    label = list(range(n))
    changed = True
    while changed:
        changed = False
        for i in range(n):
            low = min([label[i], *(label[j] for j in near[i])])
            changed |= low != label[i]
            label[i] = low
    return [len(x) for x in near], label


def check_similar(spark, rows, got):
    links, label = brute_groups([shingles(t) for _, t in rows], lambda a, b: bool(a) and bool(b) and len(a & b) >= 0.8 * len(a | b))
    ids: dict[int, list] = {}
    for (i, _), g in zip(rows, label, strict=True):
        ids.setdefault(g, []).append(i)
    want = sorted(((i, min(ids[g]), k, i == min(ids[g])) for (i, _), k, g in zip(rows, links, label, strict=True)), key=str)
    assert sorted((tuple(r) for r in got), key=str) == want


def test_similar_documents(spark, sf_dir):
    df = spark.read.parquet(f"{sf_dir}/documents.parquet").repartition(5)
    rows = [(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()]
    check_similar(spark, rows, ngram_join.similar_documents(df).collect())


def test_similar_in_large_groups(spark, monkeypatch):
    monkeypatch.setattr(ngram_join, "LARGE_BUCKET", 20)
    rng = random.Random(4)
    base = [f"w{rng.randrange(10**6)}" for _ in range(150)]
    rows = []
    for i in range(120):
        words = list(base)
        for _ in range(rng.randrange(6)):
            words[rng.randrange(len(words))] = f"x{rng.randrange(10**6)}"
        rows.append((i, " ".join(words)))
    rows += [(200, None), (201, ""), (202, "one two"), (203, "One, two!"), (204, " ".join(base)), (204, " ".join(base)), (205, "z " * 20_000), (206, "z " * 9)]
    df = spark.createDataFrame([(i, t, "clash") for i, t in rows], DOCS).repartition(6)
    check_similar(spark, rows, ngram_join.similar_documents(df).collect())
    assert ngram_join.similar_documents(df.limit(0)).count() == 0


def test_blocks_of_a_cluster_lose_no_link(spark):
    rng = np.random.default_rng(5)
    base = rng.integers(0, 1 << 62, 60)
    sets = []
    for _ in range(1300):
        keep = base[rng.random(60) > 0.06]
        sets.append(np.unique(np.r_[keep, rng.integers(0, 1 << 62, 3)]))
    rows = [(1, i, 1 + i % 2, s.astype("<i8").tobytes()) for i, s in enumerate(sets)]
    df = spark.createDataFrame(rows, "cluster long, node long, weight long, shingles binary")
    got = {r.node: r.links for r in ngram_join.verified(df, 0.8).groupBy("node").sum("links").withColumnRenamed("sum(links)", "links").collect()}
    near = ngram_join.compare_sets(sets, np.arange(1300), np.arange(1300), 0.8)
    np.fill_diagonal(near, False)
    want = near @ np.array([1 + i % 2 for i in range(1300)])
    assert got == {i: int(v) for i, v in enumerate(want) if v}


def test_nodes_that_clash_are_told_apart(spark):
    df = spark.createDataFrame([(1, 7, "a"), (1, 8, "b"), (1, 8, "c"), (2, 9, "d")], "node long, other long, name string")
    got = {r.name: r.node for r in ngram_join.told_apart(df).collect()}
    assert got["d"] == 2 and got["b"] == got["c"] != got["a"] and len(got) == 4


@pytest.mark.parametrize("most", [0, 1_000_000])
def test_components_by_broadcast_and_by_exchange(spark, monkeypatch, most):
    monkeypatch.setattr(components, "MOST_BROADCAST_EDGES", most)
    rng = random.Random(8)
    edges = [(0, i) for i in range(1, 150)] + [(i, i + 1) for i in range(200, 260)] + [(rng.randrange(300, 400), rng.randrange(300, 400)) for _ in range(60)] + [(5, 5), (None, 3)]
    label = {v: v for e in edges if None not in e and e[0] != e[1] for v in e}
    for _ in range(len(label)):
        for a, b in edges:
            if a is not None and a != b:
                label[a] = label[b] = min(label[a], label[b])
    got = {r.node: r.component for r in components.components(spark.createDataFrame(edges, "src long, dst long")).collect()}
    assert got == label


def test_blocks_of_different_sizes_lose_no_link(spark, monkeypatch):
    monkeypatch.setattr(ngram_join, "BLOCK", 40)
    rng = np.random.default_rng(9)
    base = rng.integers(0, 1 << 62, 400)
    sets = [np.unique(base[: 20 + i]) for i in range(0, 380, 2)] + [np.unique(np.r_[base[:50], rng.integers(0, 1 << 62, 5)]) for _ in range(90)]
    df = spark.createDataFrame([(3, i, 1, s.astype("<i8").tobytes()) for i, s in enumerate(sets)], "cluster long, node long, weight long, shingles binary")
    got = {r.node: r.links for r in ngram_join.verified(df, 0.8).groupBy("node").sum("links").withColumnRenamed("sum(links)", "links").collect()}
    near = ngram_join.compare_sets(sets, np.arange(len(sets)), np.arange(len(sets)), 0.8)
    np.fill_diagonal(near, False)
    assert got == {i: int(v) for i, v in enumerate(near.sum(1)) if v}


def test_recall_of_planted_pairs_just_above_the_threshold(spark):
    """Pairs whose exact similarity lies in 0.80 to 0.85, as many of them as the bands promise."""
    rng, rows, planted = random.Random(12), [], 0
    while planted < 300:
        words = [f"p{planted}w{rng.randrange(10**9)}" for _ in range(rng.randrange(60, 200))]
        other = list(words)
        for _ in range(rng.randrange(1, 5)):
            other[rng.randrange(len(other))] = f"q{rng.randrange(10**9)}"
        a, b = shingles(" ".join(words)), shingles(" ".join(other))
        if 0.8 <= len(a & b) / len(a | b) <= 0.85:
            rows += [(2 * planted, " ".join(words)), (2 * planted + 1, " ".join(other))]
            planted += 1
    df = spark.createDataFrame([(i, t, "x") for i, t in rows], DOCS).repartition(4)
    found = sum(r.n_links for r in ngram_join.similar_documents(df).collect()) // 2
    assert found >= 298


def test_recall_of_the_bands():
    bands, rows = ngram_join.bands_for(0.8, 0.9999)
    assert 1 - (1 - 0.8**rows) ** bands >= 0.9999


def check_vectors(rows, got, cosine=0.9):
    def unit(v):
        if v is None or not len(v) or any(x is None or not np.isfinite(x) for x in v) or not any(v):
            return None
        x = np.array(v, np.float64)
        x = x / np.abs(x).max()
        return x / np.sqrt(x @ x)

    links, label = brute_groups([unit(v) for _, v in rows], lambda a, b: a is not None and b is not None and len(a) == len(b) and float(a @ b) >= cosine)
    ids: dict[int, list] = {}
    for (i, _), g in zip(rows, label, strict=True):
        ids.setdefault(g, []).append(i)
    want = sorted((i, k, min(ids[g]), i == min(ids[g])) for (i, _), k, g in zip(rows, links, label, strict=True))
    assert sorted(tuple(r) for r in got) == want


def test_near_vectors(spark, sf_dir, monkeypatch):
    monkeypatch.setattr(embedding_dedup, "BLOCK", 64)
    monkeypatch.setattr(embedding_dedup, "LEAF", 16)
    df = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    rows = [(r.vec_id, r.embedding) for r in df.collect()]
    check_vectors(rows, embedding_dedup.near_duplicates(df).collect())


def test_near_vectors_in_rounds_shuffle_no_pair_of_blocks(spark, monkeypatch):
    monkeypatch.setattr(embedding_dedup, "BLOCK", 64)
    monkeypatch.setattr(embedding_dedup, "LEAF", 16)
    monkeypatch.setattr(embedding_dedup, "ROUND_NUMBERS", 8 * 64 * 3)
    rng = np.random.default_rng(4)
    rows = [(i, rng.normal(size=8).astype(np.float32).tolist()) for i in range(900)]
    rows += [(i, (np.array(rows[i % 50][1]) * 1.5 + 0.01).astype(np.float32).tolist()) for i in range(900, 960)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    made = []
    keep = embedding_dedup.materialise
    monkeypatch.setattr(embedding_dedup, "materialise", lambda df, label="t": made.append((label, df._jdf.queryExecution().toString())) or keep(df, label))
    check_vectors(rows, embedding_dedup.near_duplicates(df).collect())
    rounds = [plan for label, plan in made if label == "found"]
    assert len(rounds) > 2 and not any("Exchange" in plan or "Repartition" in plan for plan in rounds)


def test_odd_vectors(spark):
    rng = np.random.default_rng(8)
    rows = [(i, rng.normal(size=6).tolist()) for i in range(40)]
    rows += [(50, None), (51, []), (52, [0.0] * 6), (53, [1.0, None, 0, 0, 0, 0]), (54, [float("nan")] + [1.0] * 5), (55, [float("inf")] + [1.0] * 5), (56, [-0.0, 1.0, 0, 0, 0, 0]), (57, [0.0, 1.0, 0, 0, 0, 0]), (57, [0.0, 1.0, 0, 0, 0, 0]), (58, [1e-300] * 6), (59, [1e300] * 6), (60, [1.0, 2.0]), (61, [2.0, 4.0]), (62, [3.0])]
    rows = [(i, None if v is None else [None if x is None else float(x) for x in v]) for i, v in rows]
    df = spark.createDataFrame([(i, v, 0, 0) for i, v in rows], "vec_id long, embedding array<double>, label int, n_links int")
    check_vectors(rows, embedding_dedup.near_duplicates(df).collect())
    assert embedding_dedup.near_duplicates(df.limit(0)).count() == 0


def test_components(spark):
    rng = random.Random(6)
    edges = [(rng.randrange(200), rng.randrange(200)) for _ in range(120)] + [(i, i + 1) for i in range(300, 340)] + [(500, k) for k in range(501, 560)] + [(1, 1), (None, 2)]
    got = dict(tuple(r) for r in components.components(spark.createDataFrame(edges, "src long, dst long")).collect())
    label: dict[int, int] = {}
    real = [(a, b) for a, b in edges if a is not None and a != b]
    for a, b in real:
        label.setdefault(a, a)
        label.setdefault(b, b)
    for _ in range(len(label)):
        for a, b in real:
            label[a] = label[b] = min(label[a], label[b])
    assert got == label
