"""Removal of repeated byte strings by distributed prefix doubling.

A byte goes if it lies in a string of ``n`` bytes that also starts in a document
with a smaller id.  The rank of a position is the name of the bytes that follow
it; every round names longer strings by pairs of ranks at an offset, Spark sorts
the pairs with the document id, and positions whose name no other document has
leave.  For 50 bytes the lengths are 18, then 34, then 50, the last offsets
overlapping (rank 34 at p is the pair of ranks 18 at p and p + 16, rank 50 the
pair of ranks 34 at p and p + 16):

1. Rank ``k``.  Every window of ``n`` bytes contains the smallest of its
   ``k``-grams by hash, its anchor (about one position in seventeen is one).  A
   window repeats only if its anchor does, so only anchors are ranked at first.
2. Whole contexts.  All windows of an anchor span a context of at most
   ``2 n - k`` bytes, named by the ranks ``k`` that cover it.  Of the sorted
   rows with one name, those of later documents are removed as a whole; those of
   the first document go on, so that copies weigh no more in later rounds.
3. Rank ``k + (n - k) / 2`` of the strings that end and that begin at the
   anchor's far sides.  Each window contains one of the two.
4. Rank ``n`` of the windows that are left: the first document of each run of
   equal pairs keeps its window, later ones lose it.

A round is one exchange by name and one sort inside partitions; a task reads its
sorted rows once and holds a batch.  Names are 64-bit fingerprints of content
(pairs have 128 bits), so no numbering has to be agreed on and equal names meet
wherever they come from.  A batch first settles what it can see itself, as a
partial aggregation does: a name that it holds from two documents goes on as
one marker row, so a string that a third of all documents share costs a row per
batch and not a row per document.

Defined results: null and empty texts have 0 bytes and nothing removed; rows
with the same id (null too) never remove each other, whatever their texts; a
null id counts as larger than any; repeated rows are each reported; other
columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blocksketch.llm.common import discard, materialise, mix, row_runs, ship, text_buffer

RUN_BYTES = 1 << 18
#: Length of the anchors' grams for windows of 50 bytes.
K = 18
#: Rows that a task of a text scan gathers before it settles and sends them.
MOST_HELD = 300_000
_BASE = np.uint64(0x9E3779B97F4A7C15)
_BYTE = mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0xD6E8FEB86659FD93))
_LAST = (1 << 63) - 1
# A place is one long: 6 bits from the first window to the anchor, 6 bits of windows less one, then the first window's start.
_W, _START, _SIDE, _DONE, _MARK, _NULL = 6, 12, 1 << 58, 1 << 59, 1 << 60, 1 << 62
_PLACE = (1 << 58) - 1
_ROWS = "a long, b long, doc long, tag long, at long, also binary"


def gram_hash(x: np.ndarray, k: int) -> np.ndarray:
    """Hash of the k values from each place on, by doubling: log k passes."""
    acc, acc_len, cur, cur_len, power = None, 0, x, 1, int(_BASE)
    while True:
        if k & 1:
            if acc is None:
                acc, acc_len = cur, cur_len
            else:
                m = len(x) - acc_len - cur_len + 1
                acc = acc[:m] * np.uint64(power) + cur[acc_len : acc_len + m]
                acc_len += cur_len
        k >>= 1
        if not k:
            return mix(acc)
        m = len(x) - 2 * cur_len + 1
        cur = cur[:m] * np.uint64(power) + cur[cur_len : cur_len + m]
        power, cur_len = power * power & 0xFFFFFFFFFFFFFFFF, 2 * cur_len


def anchors_of(data: np.ndarray, offsets: np.ndarray, n: int, k: int) -> tuple[np.ndarray, ...]:
    """For each anchor: row, place, first and last window start it owns, hash of its gram."""
    none = np.zeros(0, np.int64)
    sizes = np.diff(offsets)
    long_ = np.flatnonzero(sizes >= n)
    if not len(long_):
        return none, none, none, none, none.astype(np.uint64)
    h = gram_hash(_BYTE[data], k)
    low = np.uint64((1 << max(20, int(len(data)).bit_length())) - 1)
    m = (h & ~low) | np.arange(len(h), dtype=np.uint64)
    width, w = 1, n - k + 1
    while 2 * width <= w:
        m = np.minimum(m[:-width], m[width:])
        width *= 2
    if w > width:
        m = np.minimum(m[: len(m) - (w - width)], m[w - width :])
    owner = (m & low).astype(np.int64)
    mark = np.zeros(len(owner) + 1, np.int32)
    mark[offsets[long_]] += 1
    np.add.at(mark, np.minimum(offsets[long_ + 1] - n + 1, len(owner)), -1)
    starts = np.flatnonzero(np.cumsum(mark[:-1]) > 0)
    own = owner[starts]
    new = np.flatnonzero(np.r_[True, own[1:] != own[:-1]])
    place = own[new]
    last = starts[np.r_[new[1:], len(starts)] - 1]
    return np.searchsorted(offsets, place, "right") - 1, place, starts[new], last, h[place]


def _documents(documents: DataFrame, key: str, text: str) -> tuple[DataFrame, DataFrame]:
    """doc, tag, none, text of every row, and the same with rows equal in id and text once.

    (doc, tag) is a row's identity: the tag is a hash of the text where some id
    is repeated, so that rows of one id are told apart; ``none`` marks null
    ids, which take the largest number.
    """
    ids = documents.select(F.col(key).cast("long").alias("doc"))
    repeated = not ids.groupBy("doc").count().where("count > 1").isEmpty()
    none = F.col(key).isNull()
    told = F.xxhash64(text) if repeated else F.lit(0).cast("long")
    rows = documents.select(F.coalesce(F.col(key).cast("long"), F.lit(_LAST)).alias("doc"), F.when(none, F.bitwise_not(told)).otherwise(told).alias("tag"), none.alias("none"), F.col(text).alias("text"))
    once = rows.groupBy("doc", "tag", "none").agg(F.any_value("text").alias("text")) if repeated else rows
    return rows, once


def _starts(*keys: np.ndarray) -> np.ndarray:
    """True where a run of equal keys begins."""
    change = np.zeros(len(keys[0]), bool)
    change[:1] = True
    for k in keys:
        change[1:] |= k[1:] != k[:-1]
    return change


def _sent(cols: list[np.ndarray], named: np.ndarray, more: np.ndarray | None = None) -> pa.RecordBatch:
    """Rows to be sorted, from rows in order of name and document.

    Rows not ``named`` are settled: they get a name of their own, so that they
    do not meet at a hot one, and are marked.  Of the named rows of one name and
    document the first carries the places of the others in ``also``: a string
    that a document repeats weighs one row.
    """
    a, b, doc, tag, at = cols
    away = ~named
    a[away] = mix(doc[away].view(np.uint64) * _BASE + tag[away].view(np.uint64) + mix(at[away].view(np.uint64)))
    b[away] = 0
    at[away] |= _DONE
    first = _starts(a, b, doc, tag)
    rows = [pa.array(x[first].view(np.int64)) for x in cols]
    also = pa.nulls(len(rows[0]), pa.binary())
    if not first.all():
        at_first = np.flatnonzero(first)
        size = np.diff(np.r_[at_first, len(a)])
        lists = np.full(len(at_first), None, object)
        for i in np.flatnonzero(size > 1):
            lists[i] = at[at_first[i] + 1 : at_first[i] + size[i]].tobytes()
        also = pa.array(lists, pa.binary())
    extra = [] if more is None else [pa.array(more[first].view(np.int64))]
    return pa.RecordBatch.from_arrays([*rows, also, *extra], ["a", "b", "doc", "tag", "at", "also", *["more"] * len(extra)])


def _opened(cols: list[np.ndarray], also: np.ndarray) -> list[np.ndarray]:
    """The rows (the fifth column is the place) with those that ``also`` stands for."""
    some = np.flatnonzero(also != None)  # noqa: E711  an array of objects
    if not len(some):
        return cols
    places = [np.frombuffer(x, "<i8") for x in also[some]]
    size = [len(x) for x in places]
    out = [np.r_[c, np.repeat(c[some], size)] for c in cols]
    out[4][len(also) :] = np.concatenate(places)
    return out


def _by_name(a: np.ndarray, b: np.ndarray, *others: np.ndarray) -> list[np.ndarray]:
    """The rows with equal names side by side; rows of one document stay together."""
    order = np.argsort(a + b * _BASE, kind="stable")
    return [x[order] for x in (a, b, *others)]


def settle_repeated(a: np.ndarray, b: np.ndarray, doc: np.ndarray, tag: np.ndarray, at: np.ndarray) -> pa.RecordBatch:
    """The rows to sort for "does another document have this name": names seen twice send a marker and are settled."""
    cols = _by_name(a, b, doc, tag, at)
    first = np.flatnonzero(_starts(*cols[:2]))
    none = cols[4] & _NULL
    several = _differ(cols[2], first) | _differ(none, first)
    marks = [x[first[several]].copy() for x in cols]
    marks[4] = (marks[4] & _NULL) | _MARK
    named = np.repeat(~several, np.diff(np.r_[first, len(none)]))
    return _sent([np.concatenate(x) for x in zip(cols, marks, strict=True)], np.r_[named, np.ones(len(marks[0]), bool)])


def _differ(x: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Whether a run holds more than one value."""
    return np.minimum.reduceat(x, first) != np.maximum.reduceat(x, first)


def settle_later(a: np.ndarray, b: np.ndarray, doc: np.ndarray, tag: np.ndarray, at: np.ndarray, more: np.ndarray | None = None) -> pa.RecordBatch:
    """The rows to sort for "does an earlier document have this name": later ones of the batch are settled."""
    cols = _by_name(a, b, doc, tag, at, *([] if more is None else [more]))
    starts = _starts(*cols[:2])
    first, run = np.flatnonzero(starts), np.cumsum(starts) - 1
    none = cols[4] & _NULL
    low = np.minimum.reduceat(cols[2], first)[run]
    # among rows of the largest number, those with an id come before those without
    low_none = np.minimum.reduceat(np.where(cols[2] == low, none, _NULL), first)[run]
    later = (cols[2] > low) | (none > low_none)
    return _sent(cols[:5], ~later, *cols[5:])


def repeated(rows: DataFrame) -> DataFrame:
    """doc, tag, at of the rows (from settle_repeated) whose name a second document has."""
    ordered = rows.select("a", "doc", "tag", "at", "also").repartition("a").sortWithinPartitions("a")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, several, last = None, False, None
        for batch in batches:
            if not batch.num_rows:
                continue
            cols = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(5)]
            new = _starts(cols[0])
            new[0] = last is None or cols[0][0] != last
            last = cols[0][-1]
            if held is not None:  # the rows of the one document that the open run has shown so far
                cols, new = [np.r_[h, c] for h, c in zip(held, cols, strict=True)], np.r_[np.zeros(len(held[0]), bool), new]
            a, doc, tag, at, also = cols
            first = np.flatnonzero(np.r_[True, new[1:]])
            many = _differ(doc, first) | _differ(at & _NULL, first) | (np.bitwise_or.reduceat(at, first) & _MARK != 0)
            if not new[0]:
                many[0] |= several
            several = bool(many[-1])
            settled = at & _DONE != 0
            keep = (np.repeat(many, np.diff(np.r_[first, len(a)])) | settled) & (at & _MARK == 0)
            held = None if several else [c[first[-1] :][~settled[first[-1] :]] for c in cols]
            _, _, doc, tag, at = _opened([a[keep], a[keep], doc[keep], tag[keep], at[keep]], also[keep])
            yield pa.RecordBatch.from_arrays([pa.array(doc), pa.array(tag), pa.array(at & ~_DONE)], ["doc", "tag", "at"])

    return ordered.mapInArrow(run, "doc long, tag long, at long")


class _Judge:
    """Reads sorted rows batch by batch: the columns with all places, and which rows an earlier document precedes in their run."""

    def __init__(self) -> None:
        self.last, self.low = None, [0, 0]

    def __call__(self, batch: pa.RecordBatch) -> tuple[list[np.ndarray], np.ndarray]:
        cols = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
        also = cols.pop(5)
        new = _starts(*cols[:2])
        new[0] = self.last is None or (cols[0][0], cols[1][0]) != self.last
        self.last = (cols[0][-1], cols[1][-1])
        none = cols[4] & _NULL
        run = np.cumsum(new)
        low, low_none = np.r_[self.low[0], cols[2][new]], np.r_[self.low[1], none[new]]
        self.low = [low[-1], low_none[-1]]
        later = (cols[2] > low[run]) | (none > low_none[run]) | (cols[4] & _DONE != 0)
        out = _opened([*cols, later], also)
        return out[:-1], out[-1]


def _ordered(rows: DataFrame) -> DataFrame:
    """By name, then document; a null id has the largest number and a place beyond all others, so it comes last."""
    return rows.repartition("a", "b").sortWithinPartitions("a", "b", "doc", "at")


def anchor_rows(docs: DataFrame, n: int, k: int) -> DataFrame:
    """The anchors of every text, named by their rank k; texts shorter than n have none."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            doc, tag, none = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(3))
            none = none.astype(np.int64) * _NULL
            data, offsets = text_buffer(batch.column(3))
            parts, held = [], 0
            for i, j in row_runs(offsets, RUN_BYTES):
                off = offsets[i : j + 1] - offsets[i]
                row, place, s1, s2, h = anchors_of(data[offsets[i] : offsets[j]], off, n, k)
                at = (s1 - off[row]) << _START | (s2 - s1) << _W | (place - s1)
                parts.append((h, doc[i:j][row], tag[i:j][row], at | none[i:j][row]))
                held += len(h)
                if held > MOST_HELD or j == len(doc):
                    if held:
                        h, d, t, at = (np.concatenate(x) for x in zip(*parts, strict=True))
                        yield settle_repeated(h, np.zeros(len(h), np.uint64), d, t, at)
                    parts, held = [], 0

    return docs.where(F.octet_length("text") >= n).mapInArrow(run, _ROWS)


def _with_places(docs: DataFrame, places: DataFrame) -> DataFrame:
    """doc, tag, text, places (list of longs) of the rows that have any."""
    held = places.groupBy("doc", "tag").agg(F.collect_list("at").alias("places"))
    return docs.join(held, ["doc", "tag"]).select("doc", "tag", "text", "places")


def _scan(batches: Iterator[pa.RecordBatch], k: int) -> Iterator[tuple]:
    """For runs of rows with places: ranks k of the run's bytes, text offsets, and row, doc, tag, place of every place."""
    for batch in batches:
        doc, tag = (batch.column(i).to_numpy() for i in range(2))
        data, offsets = text_buffer(batch.column(2))
        lists = batch.column(3)
        ends = np.r_[0, np.cumsum(lists.value_lengths().to_numpy())]
        flat = lists.flatten().to_numpy()
        runs = row_runs(offsets, RUN_BYTES)
        for i, j in runs:
            at = flat[ends[i] : ends[j]]
            row = np.repeat(np.arange(j - i), np.diff(ends[i : j + 1]))
            rank = gram_hash(_BYTE[data[offsets[i] : offsets[j]]], k)
            yield rank, offsets[i : j + 1] - offsets[i], row, doc[i:j][row], tag[i:j][row], at, j == runs[-1][1]


def _name(rank: np.ndarray, start: np.ndarray, length: int | np.ndarray, k: int, upto: int) -> np.ndarray:
    """Names of strings of at most ``upto`` bytes by the ranks k that cover them, the last one overlapping."""
    out = np.zeros(len(start), np.uint64)
    for step in range(0, upto, k):
        out = out * _BASE + rank[start + np.minimum(step, length - k)]
    return mix(out + np.uint64(upto))


def context_rows(docs: DataFrame, places: DataFrame, n: int, k: int) -> DataFrame:
    """The contexts of the anchors left, named by (anchor, whole context); ``more`` has 32 bits for each side's next rank."""
    half = (n - k + 1) // 2

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, held = [], 0
        for rank, off, row, doc, tag, at, end in _scan(batches, k):
            s = ((at & _PLACE) >> _START) + off[row]
            w, back = (at >> _W) & 63, at & 63
            place = s + back
            g = _name(rank, s, w + n, k, 2 * n - k) + w.astype(np.uint64)
            # outside the text the sides are not used
            right = rank[np.minimum(place + half, len(rank) - 1)] >> np.uint64(32)
            left = rank[np.maximum(place - half, 0)] >> np.uint64(32)
            parts.append((rank[place], mix(g), doc, tag, at, right << np.uint64(32) | left))
            held += len(at)
            if held and (held > MOST_HELD or end):
                yield settle_later(*(np.concatenate(x) for x in zip(*parts, strict=True)))
                parts, held = [], 0

    return _with_places(docs, places).mapInArrow(run, f"{_ROWS}, more long")


def judged_contexts(contexts: DataFrame, n: int, k: int) -> DataFrame:
    """kind, and rows: kind 0 are places of contexts that an earlier document has, kind 1 the sides of the others, to be ranked."""
    room = n - k
    half = (room + 1) // 2

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        judge = _Judge()
        for batch in batches:
            if not batch.num_rows:
                continue
            (a, _, doc, tag, at, more), gone = judge(batch)
            yield pa.RecordBatch.from_arrays([pa.array(np.zeros(int(gone.sum()), np.int32)), *(pa.nulls(int(gone.sum()), pa.int64()),) * 2, pa.array(doc[gone]), pa.array(tag[gone]), pa.array(at[gone] & ~_DONE), pa.nulls(int(gone.sum()), pa.binary())], ["kind", "a", "b", "doc", "tag", "at", "also"])
            a, doc, tag, at, more = (x[~gone] for x in (a, doc, tag, at, more))
            w, back = (at >> _W) & 63, at & 63
            sides = []
            for side, has, bits in ((0, back - w <= room - half, more.view(np.uint64) >> np.uint64(32)), (1, back >= half, more.view(np.uint64) & np.uint64(0xFFFFFFFF))):
                name = mix(a[has].view(np.uint64) * _BASE + ((bits[has] << np.uint64(1)) | np.uint64(side)))
                sides.append((name, np.zeros(len(name), np.uint64), doc[has], tag[has], at[has] | side * _SIDE))
            if any(len(x[0]) for x in sides):
                out = settle_repeated(*(np.concatenate(x) for x in zip(*sides, strict=True)))
                yield out.add_column(0, "kind", pa.array(np.ones(out.num_rows, np.int32)))

    return _ordered(contexts).mapInArrow(run, f"kind int, {_ROWS}")


def window_rows(docs: DataFrame, places: DataFrame, n: int, k: int) -> DataFrame:
    """The windows left, one by one, named by the pair of their middle ranks."""
    room = n - k
    half = (room + 1) // 2

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, held = [], 0
        for rank, off, row, doc, tag, at, end in _scan(batches, k):
            order = np.lexsort((at & ~_SIDE, row))
            row, doc, tag, at = (x[order] for x in (row, doc, tag, at))
            plain = at & ~_SIDE
            first = np.flatnonzero(_starts(row, plain))
            right = np.bitwise_or.reduceat(np.where(at & _SIDE, 1, 2), first)
            row, doc, tag, at = (x[first] for x in (row, doc, tag, plain))
            s = ((at & _PLACE) >> _START) + off[row]
            place, last = s + (at & 63), s + ((at >> _W) & 63)
            low = np.where(right == 2, np.maximum(s, place - half + 1), s)
            last = np.where(right == 1, np.minimum(last, place - (room - half) - 1), last)
            count = np.maximum(last - low + 1, 0)
            which = np.repeat(np.arange(len(row)), count)
            start = low[which] + np.arange(len(which)) - np.repeat(np.cumsum(count) - count, count)
            middle = lambda x: mix(rank[x] * _BASE + rank[x + half])  # noqa: E731, B023
            parts.append((middle(start), middle(start + room - half), doc[which], tag[which], (start - off[row][which]) << _START | (at[which] & _NULL)))
            held += len(start)
            if held and (held > MOST_HELD or end):
                yield settle_later(*(np.concatenate(x) for x in zip(*parts, strict=True)))
                parts, held = [], 0

    return _with_places(docs, places).mapInArrow(run, _ROWS)


def later_of_equal_names(rows: DataFrame) -> DataFrame:
    """doc, tag, at of the rows (from settle_later) whose name also stands in a row of a smaller document."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        judge = _Judge()
        for batch in batches:
            if batch.num_rows:
                (_, _, doc, tag, at), gone = judge(batch)
                yield pa.RecordBatch.from_arrays([pa.array(doc[gone]), pa.array(tag[gone]), pa.array(at[gone] & ~_DONE)], ["doc", "tag", "at"])

    return _ordered(rows).mapInArrow(run, "doc long, tag long, at long")


def repeated_strings(docs: DataFrame, n: int = 50, k: int | None = None) -> DataFrame:
    """doc, tag, at: the window ranges to remove, from rows doc, tag, none, text whose (doc, tag) are distinct."""
    k = k or max(1, min(n // 2, max(K, -(-n // 3))))
    if n < 2 or n - k > min(62, 2 * k):
        raise ValueError("n is at least 2, n - k at most 62 and at most 2 k")
    ship(docs.sparkSession)
    anchors = materialise(repeated(anchor_rows(docs, n, k)), "anchors")
    judged = materialise(judged_contexts(context_rows(docs, anchors, n, k), n, k), "contexts")
    discard(anchors)
    whole = judged.where("kind = 0").select("doc", "tag", "at")
    sides = materialise(repeated(judged.where("kind = 1")), "sides")
    gone = materialise(whole.unionByName(later_of_equal_names(window_rows(docs, sides, n, k))), "spans")
    discard(judged)
    discard(sides)
    return gone


def remove_repeats(documents: DataFrame, n: int = 50, key: str = "doc_id", text: str = "text", with_text: bool = False) -> DataFrame:
    """``key``, n_bytes, n_removed, n_spans, kept_sha256 of every row (and the kept bytes)."""
    docs, once = _documents(documents, key, text)
    spans = repeated_strings(once, n).groupBy("doc", "tag").agg(F.collect_list("at").alias("gone"))
    base = docs.join(spans, ["doc", "tag"], "left").select(F.when(~F.col("none"), F.col("doc")).alias("doc"), "text", "gone")
    schema = f"`{key}` long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", kept binary" * with_text

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column(2)
            data, offsets = text_buffer(batch.column(1))
            removed, spans_, sums, kept_all = [], [], [], []
            for i in range(batch.num_rows):
                part = data[offsets[i] : offsets[i + 1]]
                if lists[i].is_valid:
                    span = lists[i].values.to_numpy()
                    start = (span & _PLACE) >> _START
                    depth = np.zeros(len(part) + 1, np.int32)
                    np.add.at(depth, start, 1)
                    np.add.at(depth, start + ((span >> _W) & 63) + n, -1)
                    gone = np.cumsum(depth[:-1]) > 0
                    removed.append(int(gone.sum()))
                    spans_.append(int((gone[1:] & ~gone[:-1]).sum() + gone[0]))
                    kept = part[~gone].tobytes()
                else:
                    removed.append(0)
                    spans_.append(0)
                    kept = part.tobytes()
                sums.append(hashlib.sha256(kept).hexdigest())
                if with_text:
                    kept_all.append(kept)
            columns = [batch.column(0), pa.array(np.diff(offsets)), pa.array(removed, pa.int64()), pa.array(spans_, pa.int64()), pa.array(sums, pa.string()), *([pa.array(kept_all, pa.binary())] if with_text else [])]
            yield pa.RecordBatch.from_arrays(columns, [key, "n_bytes", "n_removed", "n_spans", "kept_sha256", *(["kept"] if with_text else [])])

    return base.mapInArrow(run, schema)
