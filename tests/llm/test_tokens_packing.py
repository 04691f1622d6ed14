"""Token counts and packing against the library, and packing against exact minima."""

from __future__ import annotations

import random
import zlib
from collections import Counter

import numpy as np
import pytest
from tokenizers import Tokenizer

from blocksketch.llm import packing, tokens

public_tokenizers = pytest.importorskip("public_tokenizers")
SCHEMA = "doc_id long, text string, source string, n_tokens string"


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(str(public_tokenizers.path("byte_bpe_50k.json")))


ODD = [
    None, "", " ", "  ", "\n", " \n ", "a", " a", "a ", "a  b", "a   b\n\n c", "it's we'll I'D", "x<|endoftext|>y <|endoftext|>", "<|endoftext|>", "\t\ttab", "a b 　c",
    "​ zero", "\x1c\x1d sep", "é combining", "\U0001f600\U0001f600 emoji", "12345 67 8th", "a" * 3000, "ab" * 500, "...!!!???", "\r\n\r\n x", "日本語のテキスト", "﻿bom", "end\n",
]


def test_counts_equal_the_library(spark, library):
    rows = [(i, t, "s", "clash") for i, t in enumerate(ODD)] + [(5, ODD[9], "s", "clash")] * 2
    got = sorted(map(tuple, tokens.token_counts(spark.createDataFrame(rows, SCHEMA)).collect()))
    want = sorted((i, len((t or "").encode()), len(library.encode(t or "", add_special_tokens=False).ids), len(library.encode(t or "", add_special_tokens=False).ids) > 512) for i, t, *_ in rows)
    assert got == want


def test_counts_of_the_documents(spark, sf_dir, library):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    want = {r.doc_id: len(library.encode(r.text or "", add_special_tokens=False).ids) for r in docs.collect()}
    assert {r.doc_id: r.n_tokens for r in tokens.token_counts(docs).collect()} == want


def test_random_texts(library):
    rng = random.Random(3)
    table = tokens.PieceTable(str(public_tokenizers.path("byte_bpe_50k.json")), True)
    alphabet = "aaabcde  \n\t'sé漢😀.,!0129<|>"
    texts = ["".join(rng.choice(alphabet) for _ in range(rng.randrange(60))) for _ in range(1500)]
    for t, ids in zip(texts, table.of(texts), strict=True):
        assert np.frombuffer(ids, "<u4").tolist() == library.encode(t, add_special_tokens=False).ids, repr(t)


def test_pieces_hold_every_id_once(spark, library):
    rows = [(i, t, "s", "clash") for i, t in enumerate([*ODD, "word " * 2500])]
    docs = spark.createDataFrame(rows, SCHEMA)
    out = packing.pack(docs, capacity=256).collect()
    for i, t, *_ in rows:
        ids = [*library.encode(t or "", add_special_tokens=False).ids, 2]
        mine = sorted((r for r in out if r.doc_id == i), key=lambda r: r.piece)
        assert sum(r.length for r in mine) == len(ids)
        at = 0
        for k, r in enumerate(mine):
            assert (r.piece, r.start) == (k, at)
            assert k == 0 or r.length == 256
            assert r.ids_crc32 == zlib.crc32(np.array(ids[at : at + r.length], "<u4").tobytes())
            at += r.length
    check_places(out, 256)


def check_places(out, capacity):
    by: dict[int, list] = {}
    for r in out:
        by.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for spans in by.values():
        at = 0
        for offset, length in sorted(spans):
            assert offset == at
            at += length
        assert at <= capacity
    return len(by)


def test_packing_is_gapless_and_near_the_bound(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    out = packing.pack(docs).collect()
    used = check_places(out, 1024)
    assert used <= 1.02 * packing.lower_bound(Counter(r.length for r in out), 1024) + 1


def test_packing_by_small_cells_and_many_salts(spark, sf_dir, monkeypatch):
    monkeypatch.setattr(packing, "LEAST_CELL", 2)
    monkeypatch.setattr(packing, "MOST_CELLS", 1 << 30)
    rng = random.Random(6)
    pieces = spark.createDataFrame([(i, 0, rng.choice([512, 512, 300, 212, 100, 1024, 7])) for i in range(700)], "doc_id long, piece int, length long").repartition(5)
    out = packing.assign(pieces, 1024, rows_per_salt=10).collect()
    assert len(out) == 700 and check_places(out, 1024) == sum(n for _, n in packing.plan(Counter(r.length for r in out), 1024))


def test_empty_table(spark):
    none = spark.createDataFrame([], SCHEMA)
    assert packing.pack(none).count() == 0
    assert tokens.token_counts(none).count() == 0


@pytest.mark.parametrize("seed", range(60))
def test_reduction_never_costs_a_sequence(seed):
    rng = random.Random(seed)
    capacity = rng.choice([10, 17, 30])
    items = [rng.randint(1, capacity) for _ in range(rng.randint(1, 9))]
    fixed, rest = packing.reduce_by_dominance(Counter(items), capacity)
    left = list(rest.elements())
    assert sorted(left + [x for p, n in fixed for x in p * n]) == sorted(items)
    best = packing.exact_minimum(items, capacity)
    assert sum(n for _, n in fixed) + packing.exact_minimum(left, capacity) == best
    assert packing.lower_bound(Counter(items), capacity) <= best
    made = packing.plan(Counter(items), capacity)
    assert sorted(x for p, n in made for x in p * n) == sorted(items)
    assert all(sum(p) <= capacity for p, _ in made)
    assert sum(n for _, n in made) <= 1.5 * best
