"""N-gram Jaccard self-join of documents by MinHash banding and exact verification.

A document is the set of its five-word shingles.  Documents with equal sets are
one class.  Band and row counts follow from the similarity and a target
recall.  Classes meet on band hashes; inside a bucket short signatures decide
who may be similar at all, and only a spanning forest of these candidates
leaves the bucket.  Its components are clusters whose full shingle sets are
then compared exactly, in blocks, so that a cluster of any size is many bounded
tasks and no list of pairs is ever written.  Every link between different
classes inside a cluster is counted.

Defined results: words are as in the decontamination operator (A-Z lowered,
runs of letters, digits and non-ASCII characters); a text of one to four words
has one shingle, a null or wordless text has none and links with nothing;
repeated rows are copies of each other; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from blocksketch.llm.common import discard, materialise, mix, row_runs, ship, text_buffer
from blocksketch.llm.components import components
from blocksketch.llm.url_filter import _block, _mask, build_filter

RUN_BYTES = 1 << 20
#: Classes compared at once: a pair of blocks is one task's work.
BLOCK = 1024
#: Buckets with more classes than this join all to one without looking at signatures.
LARGE_BUCKET = 1000
#: Block numbers of a size band.
_BAND = 1 << 30
_STEP = np.uint64(0x9E3779B97F4A7C15)
_LOWER = np.zeros(256, np.uint8)
for _r in (range(0x30, 0x3A), range(0x61, 0x7B), range(0x80, 0x100)):
    _LOWER[list(_r)] = list(_r)
_LOWER[0x41:0x5B] = np.arange(0x61, 0x7B)


def bands_for(similarity: float, recall: float, rows: int = 6) -> tuple[int, int]:
    """(bands, rows): the fewest bands that find a pair at ``similarity`` with probability ``recall``."""
    return int(np.ceil(np.log(1 - recall) / np.log(1 - similarity**rows))), rows


def shingles_of(data: np.ndarray, offsets: np.ndarray, n: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """(row, 64-bit hash) of the distinct word n-grams of each row, in order of row and hash."""
    rows, sizes = len(offsets) - 1, np.diff(offsets)
    folded = _LOWER[data]
    inside = folded != 0
    row = np.repeat(np.arange(rows), sizes)
    before = np.zeros(len(data), bool)
    before[1:] = inside[:-1]
    before[offsets[:-1][sizes > 0]] = False
    begins = inside & ~before
    starts = np.flatnonzero(begins)
    if not len(starts):
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    at = np.flatnonzero(inside)
    place = at - starts[np.cumsum(begins[at]) - 1]
    codes = mix(folded[at].astype(np.uint64) + np.uint64(257) * (place.astype(np.uint64) + np.uint64(1)))
    word = np.add.reduceat(codes, np.searchsorted(at, starts))
    owner = row[starts]
    count = np.bincount(owner, minlength=rows)
    first = np.r_[0, np.cumsum(count)[:-1]]
    out_row, out_hash = [], []
    if len(word) >= n:
        h = word[: len(word) - n + 1].copy()
        for j in range(1, n):
            h = h * _STEP + word[j : len(word) - n + 1 + j]
        whole = owner[: len(h)] == owner[n - 1 :]
        out_row.append(owner[: len(h)][whole])
        out_hash.append(mix(h[whole]))
    for c in range(1, n):
        few = np.flatnonzero(count == c)
        if len(few):
            h = word[first[few]].copy()
            for j in range(1, c):
                h = h * _STEP + word[first[few] + j]
            out_row.append(few)
            out_hash.append(mix(h + np.uint64(c)))
    o, h = np.concatenate(out_row), np.concatenate(out_hash)
    order = np.lexsort((h, o))
    o, h = o[order], h[order]
    new = np.r_[True, (h[1:] != h[:-1]) | (o[1:] != o[:-1])]
    return o[new], h[new]


def signatures_of(owner: np.ndarray, h: np.ndarray, rows: int, bands: int, per_band: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """For each row: two class hashes, number of shingles, band keys, one byte of each minimum."""
    count = np.bincount(owner, minlength=rows)
    some = np.flatnonzero(count)
    starts = np.r_[0, np.cumsum(count[some])[:-1]]
    rng = np.random.default_rng(11)
    mult = rng.integers(1, 1 << 63, bands * per_band, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    plus = rng.integers(0, 1 << 63, bands * per_band, dtype=np.uint64)
    keys = np.zeros((rows, bands), np.uint64)
    brief = np.zeros((rows, bands * per_band), np.uint8)
    node, other = np.zeros(rows, np.uint64), np.zeros(rows, np.uint64)
    if len(some):
        other[some] = mix(np.add.reduceat(mix(h * _STEP + np.uint64(1)), starts) + count[some].astype(np.uint64))
        node[some] = mix(np.add.reduceat(mix(h), starts) + np.uint64(3) * count[some].astype(np.uint64) + mix(np.bitwise_xor.reduceat(h, starts)))
        for b in range(bands):
            key = np.full(len(some), b, np.uint64)
            for i in range(b * per_band, (b + 1) * per_band):
                low = np.minimum.reduceat((h * mult[i] + plus[i]) >> np.uint64(32), starts)
                key = key * _STEP + low
                brief[some, i] = mix(low) & np.uint64(255)
            keys[some, b] = mix(key)
    return node, other, count, keys, brief


def signatures(documents: DataFrame, bands: int, per_band: int, n: int = 5, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc, t (text hash), node (class of equal sets) and a second hash of the set, n, bands, brief of every row."""
    ship(documents.sparkSession)
    src = documents.select(F.col(key).cast("long").alias("doc"), text, F.xxhash64(text).alias("t"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = text_buffer(batch.column(1))
            for a, b in row_runs(offsets, RUN_BYTES):
                owner, h = shingles_of(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], n)
                node, other, count, keys, brief = signatures_of(owner, h, b - a, bands, per_band)
                lists = pa.ListArray.from_arrays(pa.array(np.arange(0, (b - a + 1) * bands, bands), pa.int32()), pa.array(keys.view(np.int64).ravel()))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), batch.column(2).slice(a, b - a), pa.array(node.view(np.int64)), pa.array(other.view(np.int64)), pa.array(count.astype(np.int64)), lists, pa.array([x.tobytes() for x in brief], pa.binary())], ["doc", "t", "node", "other", "n", "bands", "brief"])

    return src.mapInArrow(run, "doc long, t long, node long, other long, n long, bands array<long>, brief binary")


def told_apart(rows: DataFrame) -> DataFrame:
    """``rows`` (node, other) with a node of its own for every (node, other): the 128 bits together name a class."""
    clash = rows.groupBy("node").agg(F.min("other").alias("a"), F.max("other").alias("b")).where("a <> b").select("node", F.lit(True).alias("_clash"))
    if clash.isEmpty():
        return rows
    found = rows.join(clash, "node", "left")
    return found.withColumn("node", F.when(F.col("_clash"), F.xxhash64("node", "other")).otherwise(F.col("node"))).select(*rows.columns)


def _forest(near: np.ndarray) -> np.ndarray:
    """Of a symmetric boolean matrix, each row's component as its smallest index."""
    g = len(near)
    label = np.arange(g)
    while True:
        low = np.concatenate([np.where(near[a : a + 256], label[None, :], g).min(1) for a in range(0, g, 256)]) if g else label
        low = np.minimum(label, low)
        low = low[low]
        if (low == label).all():
            return label
        label = low


def links_of(near: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """For each row of a boolean matrix, the weights of its true columns summed."""
    return np.concatenate([near[a : a + 256].astype(np.float64) @ weight for a in range(0, len(near), 256)] or [np.zeros(0)]).astype(np.int64)


def candidate_edges(classes: DataFrame, least_match: float) -> DataFrame:
    """(src, dst): a spanning forest, bucket by bucket, of the classes that may be similar."""
    members = classes.select("node", F.explode("bands").alias("key"))
    buckets = members.groupBy("key").agg(F.count("*").alias("g"), F.min("node").alias("low"), F.bit_xor("node").alias("x"), F.bit_xor(F.xxhash64("node")).alias("y")).where("g > 1")
    # bands that gather the same classes count once
    buckets = materialise(buckets.groupBy("g", "low", "x", "y").agg(F.min("key").alias("key")), "buckets")
    # written, so that the join below has two plain exchanges, which adaptive execution can split at a hot bucket
    large = members.join(buckets.where(F.col("g") > LARGE_BUCKET).select("key", "low"), "key").select(F.col("node").alias("src"), F.col("low").alias("dst"))
    small = buckets.where(F.col("g") <= LARGE_BUCKET).select("key", "g")
    packs = max(1, (small.agg(F.sum("g")).first()[0] or 0) // 20_000) * 8
    held = members.join(small.select("key"), "key").join(classes.select("node", "brief"), "node")
    held = held.select(F.pmod(F.xxhash64("key"), F.lit(packs)).alias("pack"), "key", "node", "brief")

    def look(table: pa.Table) -> pa.Table:
        key = table["key"].to_numpy()
        order = np.argsort(key, kind="stable")
        node = table["node"].to_numpy()[order]
        brief = np.frombuffer(b"".join(table["brief"].to_pylist()), np.uint8).reshape(len(key), -1)[order]
        cuts = np.flatnonzero(np.r_[True, np.diff(key[order]) != 0, True])
        src, dst = [], []
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):
            part = brief[a:b]
            if b - a == 2:
                if (part[0] == part[1]).mean() >= least_match:
                    src.append(node[a])
                    dst.append(node[a + 1])
                continue
            near = np.stack([(part == p).mean(1) >= least_match for p in part])
            label = _forest(near)
            for i in np.flatnonzero(label != np.arange(b - a)):
                src.append(node[a + i])
                dst.append(node[a + label[i]])
        return pa.table({"src": pa.array(src, pa.int64()), "dst": pa.array(dst, pa.int64())})

    return large.unionByName(held.groupBy("pack").applyInArrow(lambda t: look(t), "src long, dst long"))


def compare_sets(sets: list[np.ndarray], left: np.ndarray, right: np.ndarray, similarity: float) -> np.ndarray:
    """len(left) x len(right): whether these sets' Jaccard similarity reaches the threshold."""
    sizes = np.array([len(s) for s in sets])
    rows = np.repeat(np.arange(len(sets)), sizes)
    _, column, seen = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    shared = seen[column] > 1
    rows, column = rows[shared], column[shared]
    _, column = np.unique(column, return_inverse=True)
    order = np.argsort(column, kind="stable")
    rows, column = rows[order], column[order]
    common = np.zeros((len(left), len(right)), np.float64)
    width, last = 4096, int(column[-1]) + 1 if len(column) else 0
    for c in range(0, last, width):
        a, b = np.searchsorted(column, [c, c + width])
        grid = np.zeros((len(sets), min(width, last - c)), np.float32)
        grid[rows[a:b], column[a:b] - c] = 1
        common += grid[left] @ grid[right].T
    union = sizes[left][:, None] + sizes[right][None, :] - common
    return common >= similarity * union - 1e-9


def verified(clustered: DataFrame, similarity: float) -> DataFrame:
    """(node, links, root) from rows cluster, node, weight, shingles.

    ``links`` sums the weights of the classes linked with the node in one
    comparison of blocks; ``root`` is the smallest node joined with it there.
    Blocks of a large cluster hold sets of about one size and meet only blocks
    whose sets are not too large or small to be similar.
    """
    # sets whose sizes are more than two bands apart cannot reach the similarity
    width = -math.log(similarity) / 2 * (1 + 1e-9) if 0 < similarity < 1 else 1e-9
    size = F.floor(F.log(F.length("shingles") / 8.0) / F.lit(width)).cast("long")
    counted = materialise(clustered.groupBy("cluster", size.alias("s")).agg(F.count("*").alias("g")), "sizes")
    whole = counted.groupBy("cluster").agg(F.sum("g").alias("all"))
    # a cluster that one comparison holds is a single band
    parts = counted.join(whole, "cluster").select("cluster", "s", "g", (F.col("all") <= BLOCK).alias("one"), F.ceil(F.col("g") / BLOCK).alias("nb"))
    blocks = parts.select("cluster", F.when(F.col("one"), F.lit(0)).otherwise(F.col("s")).alias("s2"), F.when(F.col("one"), F.lit(1)).otherwise(F.col("nb")).alias("nb2")).distinct()
    near = F.when(F.col("one"), F.array(F.lit(0).cast("long"))).otherwise(F.sequence(F.col("s") - 2, F.col("s") + 2))
    meets = parts.select("cluster", "s", "one", "g", "nb", F.explode(near).alias("s2")).join(blocks, ["cluster", "s2"])
    total = meets.agg(F.sum(F.col("g") * F.col("nb2"))).first()[0] or 0
    meets = meets.groupBy("cluster", "s", "one", "nb").agg(F.collect_list(F.struct("s2", "nb2")).alias("meets"))
    rows = clustered.withColumn("s", size).join(meets, ["cluster", "s"])
    own = F.when(F.col("one"), F.lit(0)).otherwise(F.col("s") * _BAND + F.pmod(F.xxhash64("node"), F.col("nb")))
    rows = rows.select("cluster", "node", "weight", "shingles", own.alias("b"), F.explode("meets").alias("m"))
    rows = rows.select("cluster", "node", "weight", "shingles", "b", F.explode(F.sequence(F.col("m.s2") * _BAND, F.col("m.s2") * _BAND + F.col("m.nb2") - 1)).alias("o"))
    rows = rows.select("cluster", "node", "weight", "shingles", "b", F.least("b", "o").alias("i"), F.greatest("b", "o").alias("j"))
    pack = F.pmod(F.xxhash64("cluster", "i", "j"), F.lit(max(8, total // 2_000)))
    rows = rows.select(pack.alias("pack"), "cluster", "i", "j", "b", "node", "weight", "shingles")

    def check(table: pa.Table) -> pa.Table:
        ids = np.stack([table[c].to_numpy() for c in ("cluster", "i", "j")], 1)
        order = np.lexsort(ids.T[::-1])
        ids = ids[order]
        node, weight, block = (table[c].to_numpy()[order] for c in ("node", "weight", "b"))
        held = table["shingles"].to_pylist()
        sets = [np.frombuffer(held[k], "<i8") for k in order]
        cuts = np.flatnonzero(np.r_[True, (np.diff(ids, axis=0) != 0).any(1), True])
        out_node, out_links, out_root = [], [], []
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):
            i, j = ids[a, 1:]
            mine, names = sets[a:b], node[a:b]
            if i == j:
                left = right = np.arange(b - a)
            else:
                left, right = np.flatnonzero(block[a:b] == i), np.flatnonzero(block[a:b] == j)
            near = np.zeros((b - a, b - a), bool)
            if len(left) and len(right):
                near[np.ix_(left, right)] = compare_sets(mine, left, right, similarity)
                near |= near.T
            np.fill_diagonal(near, False)
            some = np.flatnonzero(near.any(1))
            root = _forest(near)
            out_node.append(names[some])
            out_links.append(links_of(near[some], weight[a:b]))
            out_root.append(names[root[some]])
        cat = lambda x: pa.array(np.concatenate(x) if x else np.zeros(0, np.int64), pa.int64())
        return pa.table({"node": cat(out_node), "links": cat(out_links), "root": cat(out_root)})

    return rows.groupBy("pack").applyInArrow(lambda t: check(t), "node long, links long, root long")


def placed(rows: DataFrame, classes: DataFrame, found: DataFrame) -> DataFrame:
    """``rows`` with n_links and ``least``, the smallest low of the connected group; both null for rows of no class.

    ``found`` is a stored table.
    """
    joined = components(found.where("node <> root"), "node", "root")
    links = found.groupBy("node").agg(F.sum("links").alias("links"))
    info = classes.join(links, "node", "left").join(joined, "node", "left").select("node", "weight", "low", F.coalesce("links", F.lit(0)).alias("links"), F.coalesce("component", "node").alias("component"))
    info = materialise(info, "classes")
    discard(found)
    least = info.groupBy("component").agg(F.min("low").alias("least"))
    info = info.join(least, "component").select("node", "least", (F.col("weight") - 1 + F.col("links")).alias("n_links"))
    return rows.join(info, "node", "left").select(*[rows[c] for c in rows.columns], "least", "n_links")


def _result(whole: DataFrame, least: Column) -> DataFrame:
    class_id = F.when(F.col("alone"), F.col("doc")).otherwise(least)
    return whole.select("doc", class_id.alias("class_id"), F.when(F.col("alone"), F.lit(0)).otherwise(F.col("n_links")).cast("long").alias("n_links"), F.col("doc").eqNullSafe(class_id).alias("kept"))


def group_result(rows: DataFrame, classes: DataFrame, found: DataFrame) -> DataFrame:
    """doc, class_id, n_links, kept from rows (doc, node, alone), classes (node, weight, low) and links found.

    ``class_id`` is the smallest doc of the connected group; rows that stand
    alone by definition are their own class.
    """
    return _result(placed(rows, classes, found), F.col("least"))


def _judged(documents: DataFrame, similarity: float = 0.8, n: int = 5, recall: float = 0.9999, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc, t, node, alone, least, n_links of every row; ``least`` is the group's first (no_doc, doc, t), null docs last."""
    bands, per_band = bands_for(similarity, recall)
    signed = told_apart(materialise(signatures(documents, bands, per_band, n, key, text), "signatures"))
    rows = signed.select("doc", "t", "node", (F.col("n") == 0).alias("alone"))
    full = signed.where("n > 0")
    counted = full.groupBy("node").agg(F.count("*").alias("weight"), F.min(F.struct(F.col("doc").isNull().alias("no_doc"), "doc", "t")).alias("low"), F.any_value("other").alias("other"))
    shown = full.groupBy("node").agg(F.any_value("bands").alias("bands"), F.any_value("brief").alias("brief"))
    classes = materialise(counted.join(shown, "node"), "sets")
    deviation = (similarity * (1 - similarity) / (bands * per_band)) ** 0.5
    edges = candidate_edges(classes, similarity - 6.5 * deviation)
    clusters = components(edges).select("node", F.col("component").alias("cluster"))
    wanted = materialise(clusters.join(classes.select("node", "weight", "other", "low.doc", "low.t"), "node"), "wanted")
    shingled = _with_shingles(documents, wanted, n, key, text)
    discard(wanted)
    found = materialise(verified(shingled, similarity), "links")
    discard(shingled)
    return placed(rows, classes.select("node", "weight", "low"), found)


def similar_documents(documents: DataFrame, similarity: float = 0.8, n: int = 5, recall: float = 0.9999, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc, class_id, n_links and kept of every row of ``documents``.

    ``n_links`` counts the other rows whose shingle sets have at least
    ``similarity``; ``class_id`` is the smallest ``key`` reachable by links.
    A row whose ``key`` is null is its own class_id only if nothing links to it.
    """
    return _result(_judged(documents, similarity, n, recall, key, text), F.col("least.doc"))


def _with_shingles(documents: DataFrame, wanted: DataFrame, n: int, key: str, text: str) -> DataFrame:
    """cluster, node, weight, shingles of the wanted classes, read again from one document (doc, t) each."""
    n_wanted = wanted.count()
    rules = wanted.where("doc is not null").select(F.col("doc").alias("host"), F.lit("").alias("path"))
    words, n_words = build_filter(rules, n_wanted)
    hashed = F.xxhash64(F.col(key).cast("long"), F.lit(""))
    possible = F.element_at(words, _block(hashed, n_words) + 1).bitwiseAND(_mask(hashed)) == _mask(hashed)
    source = documents.select(F.col(key).cast("long").alias("doc"), F.col(text).alias("text")).where(possible | F.col("doc").isNull())
    source = source.withColumn("t", F.xxhash64("text")).alias("s").join(wanted.alias("w"), F.col("s.doc").eqNullSafe(F.col("w.doc")) & (F.col("s.t") == F.col("w.t"))).select("cluster", "node", "weight", "other", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = text_buffer(batch.column(4))
            for a, b in row_runs(offsets, RUN_BYTES):
                owner, h = shingles_of(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], n)
                _, other, count, _, _ = signatures_of(owner, h, b - a, 0, 0)
                ends = np.cumsum(count)
                right = np.flatnonzero(other.view(np.int64) == batch.column(3).slice(a, b - a).to_numpy())
                part = batch.slice(a, b - a).take(pa.array(right))
                sets = [h[ends[k] - count[k] : ends[k]].tobytes() for k in right]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), part.column(2), pa.array(sets, pa.binary())], ["cluster", "node", "weight", "shingles"])

    flat = source.mapInArrow(run, "cluster long, node long, weight long, shingles binary")
    # repeated rows of a document give its class more than once
    return materialise(flat.groupBy("cluster", "node", "weight").agg(F.any_value("shingles").alias("shingles")), "shingles")


def one_of_each(documents: DataFrame, **how: object) -> DataFrame:
    """The rows of ``documents`` that stand for their group, with all columns.

    The verdict goes by doc_id and text hash: of every group exactly one row
    stays, the one of smallest doc_id (null last), then text hash.  Of rows
    repeated with doc_id and text one stays; rows that link with nothing all
    stay but for such repeats, and a null doc_id repeats no other.
    """
    names = documents.columns
    first = (F.col("least.doc").eqNullSafe(F.col("doc")) & (F.col("least.t") == F.col("t"))) | F.col("alone")
    seen = _judged(documents, **how).groupBy("doc", "t").agg(F.count("*").alias("c"), F.max("alone").alias("alone"), F.max(first).alias("first"))
    again = F.col("first") & (F.col("c") > 1) & (~F.col("alone") | F.col("doc").isNotNull())
    marks = materialise(seen.select("doc", "t", again.alias("again")).where(again | ~F.col("first")), "verdict")
    packed = documents.select(F.col("doc_id").cast("long").alias("_k"), F.xxhash64("text").alias("_t"), F.struct(*[F.col(f"`{c}`") for c in names]).alias("_doc"))
    same = F.col("_k").eqNullSafe(F.col("doc")) & (F.col("_t") == F.col("t"))
    left = packed.join(marks, same, "left_anti").select("_doc")
    repeated = marks.where("again")
    if not repeated.isEmpty():
        one = packed.join(repeated, same, "left_semi").groupBy("_k", "_t").agg(F.min("_doc").alias("_doc"))
        left = left.unionByName(one.select("_doc"))
    return left.select("_doc.*")
