"""Best-fit packing of token sequences with Martello-Toth dominance reduction.

What has to be packed is a histogram: the number of pieces of each length up
to the capacity, so the plan of which lengths share a sequence is a bounded
computation on the driver whatever the size of the corpus.  The reduction
fixes sets that provably belong to some optimal packing (a piece with its only
or perfectly filling partners, or two partners that fill it), for all pieces
of that length at once; best fit by decreasing length packs what remains.
Pieces then find their slot from their number among pieces of the same length.

Defined results: a null text is an empty document (end mark only); repeated
rows are packed each; an empty table packs nothing; other columns are ignored.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, bisect_right, insort
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blocksketch.llm.common import materialise, ship
from blocksketch.llm.tokens import piece_table, runs_of_texts

Pattern = tuple[int, ...]
#: Slots of one length in a cell of the look-up, at least, and cells of all lengths, about.
LEAST_CELL, MOST_CELLS = 1 << 12, 1 << 16


def token_pieces(documents: DataFrame, keep: tuple[str, ...] = ("doc_id",), text: str = "text", tokenizer: str = "byte_bpe_50k.json", capacity: int = 1024, end_id: int = 2, with_ids: bool = False) -> DataFrame:
    """``keep`` plus piece, start, length, ids_crc32 (and ids as little-endian bytes).

    A document longer than ``capacity`` is cut so that only its first piece is
    shorter than the capacity.
    """
    ship(documents.sparkSession)
    src = documents.select(*keep, text)
    names = [*keep, "piece", "start", "length", "ids_crc32", *(["ids"] if with_ids else [])]
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in src.schema.fields[:-1]), "piece int, start long, length long, ids_crc32 long", *(["ids binary"] if with_ids else [])])
    end = end_id.to_bytes(4, "little")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = piece_table(tokenizer, True)
        for batch in batches:
            for a, _, texts, _ in runs_of_texts(batch.column(len(keep))):
                row, piece, start, length, crc, held = [], [], [], [], [], []
                for i, ids in enumerate(table.of(texts)):
                    ids += end
                    n = len(ids) // 4
                    first = n % capacity or capacity
                    bounds = [0, *range(first, n + 1, capacity)]
                    for k in range(len(bounds) - 1):
                        part = ids[4 * bounds[k] : 4 * bounds[k + 1]]
                        row.append(a + i)
                        piece.append(k)
                        start.append(bounds[k])
                        length.append(bounds[k + 1] - bounds[k])
                        crc.append(zlib.crc32(part))
                        if with_ids:
                            held.append(part)
                at = pa.array(row, pa.int64())
                made = [pa.array(piece, pa.int32()), *(pa.array(x, pa.int64()) for x in (start, length, crc)), *([pa.array(held, pa.binary())] if with_ids else [])]
                yield pa.RecordBatch.from_arrays([*(batch.column(k).take(at) for k in range(len(keep))), *made], names)

    return src.mapInArrow(cut, schema)


def reduce_by_dominance(counts: Counter, capacity: int) -> tuple[list[tuple[Pattern, int]], Counter]:
    """Fixes dominating sets; returns (pattern, number) pairs and what is left.

    For the longest piece i left: alone if nothing fits with it; with j if j
    fills the rest exactly, or if j is the longest that fits and no two pieces
    fit together; with a pair (j, k) if it fills the rest exactly, j is the longest
    that fits, no three pieces fit, and no two longer than k fit (so every
    other pair is at most (j, k) piece by piece).  Each is applied to as
    many pieces of these lengths as exist.  Lengths without a dominating set
    are passed over and left to best fit.
    """
    left = Counter({k: v for k, v in counts.items() if v > 0})
    lengths = sorted(left)
    fixed: list[tuple[Pattern, int]] = []

    def use(pattern: Pattern, number: int) -> None:
        fixed.append((pattern, number))
        for k, each in Counter(pattern).items():
            left[k] -= each * number
            if left[k] == 0:
                del left[k]
                lengths.pop(bisect_left(lengths, k))

    def smallest(m: int, without: int, least: int = 0) -> list[int]:
        """The m smallest pieces of ``least`` or more, one piece of length ``without`` apart."""
        out: list[int] = []
        for k in lengths[bisect_left(lengths, least) :]:
            out += [k] * min(m, left[k] - (k == without))
            if len(out) >= m:
                break
        return out[:m]

    changed = True
    while changed:
        changed = False
        for i in sorted(left, reverse=True):
            while left[i] > 0:
                rest = capacity - i
                few = smallest(3, i)
                if not few or few[0] > rest:
                    use((i,), left[i])
                    changed = True
                    continue
                j = lengths[bisect_right(lengths, rest) - 1] if lengths[0] <= rest else 0
                if j == i and left[i] < 2:
                    at = bisect_left(lengths, i)
                    j = lengths[at - 1] if at else 0
                if j and (j == rest or len(few) < 2 or few[0] + few[1] > rest):
                    use((i, j), left[i] // 2 if i == j else min(left[i], left[j]))
                    changed = True
                    continue
                if len(few) < 3 or sum(few) > rest:
                    k = rest - j
                    need, above = Counter((i, j, k)), smallest(2, i, k + 1)
                    if k > 0 and (len(above) < 2 or sum(above) > rest) and all(left[x] >= n for x, n in need.items()):
                        use((i, j, k), min(left[x] // n for x, n in need.items()))
                        changed = True
                        continue
                break
    return fixed, left


def best_fit(counts: Counter, capacity: int) -> list[tuple[Pattern, int]]:
    """Best fit by decreasing length on a histogram; open sequences are kept in groups alike."""
    groups: dict[int, list[tuple[Pattern, int]]] = {}
    free: list[int] = []
    done: list[tuple[Pattern, int]] = []

    def put(pattern: Pattern, number: int) -> None:
        room = capacity - sum(pattern)
        if room == 0:
            done.append((pattern, number))
            return
        if room not in groups:
            groups[room] = []
            insort(free, room)
        groups[room].append((pattern, number))

    for length in sorted(counts, reverse=True):
        todo = counts[length]
        while todo:
            at = bisect_left(free, length)
            if at == len(free):
                each = capacity // length
                full, last = divmod(todo, each)
                if full:
                    put((length,) * each, full)
                if last:
                    put((length,) * last, 1)
                break
            room = free[at]
            pattern, number = groups[room].pop()
            if not groups[room]:
                del groups[room]
                free.pop(at)
            each = min(room // length, todo)
            n = min(number, todo // each)
            if n < number:
                put(pattern, number - n)
            put((*pattern, *(length,) * each), n)
            todo -= n * each
    return done + [x for g in groups.values() for x in g]


def plan(counts: Counter, capacity: int) -> list[tuple[Pattern, int]]:
    """Patterns of lengths and how many sequences follow each; every piece of the histogram once."""
    fixed, rest = reduce_by_dominance(counts, capacity)
    return fixed + best_fit(rest, capacity)


def lower_bound(counts: Counter, capacity: int) -> int:
    """No packing has fewer sequences (the public L2 bound: L1 refined by a split of the lengths)."""
    best = -(-sum(k * v for k, v in counts.items()) // capacity)
    for cut in sorted({0, *(k for k in counts if k <= capacity // 2)}):
        big = sum(v for k, v in counts.items() if k > capacity - cut)
        mid = {k: v for k, v in counts.items() if capacity // 2 < k <= capacity - cut}
        small = sum(k * v for k, v in counts.items() if cut <= k <= capacity // 2)
        room = sum((capacity - k) * v for k, v in mid.items())
        best = max(best, big + sum(mid.values()) + max(0, -(-(small - room) // capacity)))
    return best


def slots(patterns: list[tuple[Pattern, int]]) -> list[tuple[int, int, int, int, int]]:
    """(length, first number, first sequence, offset, slots) of each run of slots, numbers by length from 0."""
    out, used, base = [], Counter(), 0
    for pattern, number in patterns:
        offset = 0
        for length in pattern:
            out.append((length, used[length], base, offset, number))
            used[length] += number
            offset += length
        base += number
    return out


def assign(pieces: DataFrame, capacity: int = 1024, order: tuple[str, ...] = ("doc_id", "piece"), rows_per_salt: int = 200_000, most_salts: int = 4096) -> DataFrame:
    """``pieces`` (a stored table with ``length``) plus sequence_id and offset.

    A piece's number among its length is its number among (length, salt) plus
    the counts of lower salts, so a length that many pieces share is numbered
    by many tasks; those counts stay in a table, dealt like the pieces.  The
    driver holds a count for each length.  The runs of slots are cut into cells
    of numbers, so a piece looks at the runs of its own cell only.
    """
    spark = pieces.sparkSession
    salts = min(most_salts, max(32, pieces.count() // rows_per_salt))
    salted = pieces.withColumn("_salt", F.pmod(F.xxhash64(*order), F.lit(salts)).cast("int"))
    by_salt = materialise(salted.groupBy("length", "_salt").agg(F.count("*").alias("n")), "lengths")
    counts = Counter({r["length"]: r["n"] for r in by_salt.groupBy("length").agg(F.sum("n").alias("n")).collect()})  # at most capacity rows
    cell = max(LEAST_CELL, 1 << (sum(counts.values()) // MOST_CELLS).bit_length())
    cells = cells_of(slots(plan(counts, capacity)), cell)
    table = spark.createDataFrame([(*k, v) for k, v in cells.items()], "length long, _cell long, _runs array<struct<a:long,s:long,o:long>>")
    lower = Window.partitionBy("length").orderBy("_salt").rowsBetween(Window.unboundedPreceding, -1)
    before = by_salt.select("length", "_salt", F.coalesce(F.sum("n").over(lower), F.lit(0)).alias("_before"))
    ranked = salted.withColumn("_r", F.row_number().over(Window.partitionBy("length", "_salt").orderBy(*order)) - 1)
    numbered = ranked.join(before, ["length", "_salt"]).withColumn("_number", F.col("_r") + F.col("_before"))
    found = numbered.withColumn("_cell", F.floor(F.col("_number") / cell)).join(F.broadcast(table), ["length", "_cell"])  # runs and MOST_CELLS cells, from the driver's plan
    last = F.element_at(F.filter("_runs", lambda x: x["a"] <= F.col("_number")), -1)
    return found.select(*pieces.columns, (last["s"] + F.col("_number") - last["a"]).alias("sequence_id"), last["o"].alias("offset"))


def cells_of(runs: list[tuple[int, int, int, int, int]], cell: int) -> dict[tuple[int, int], list[tuple[int, int, int]]]:
    """(length, cell) -> the runs (number, sequence, offset) that reach into the cell, in order; runs as from ``slots``."""
    by_length: dict[int, list[tuple[int, int, int, int]]] = {}
    for length, number, sequence, offset, many in runs:
        by_length.setdefault(length, []).append((number, sequence, offset, many))
    out: dict[tuple[int, int], list[tuple[int, int, int]]] = {}
    for length, held in by_length.items():
        for number, sequence, offset, many in held:
            for c in range(number // cell, (number + many - 1) // cell + 1):
                out.setdefault((length, c), []).append((number, sequence, offset))
    return out


def pack(documents: DataFrame, keep: tuple[str, ...] = ("doc_id",), capacity: int = 1024, **how: object) -> DataFrame:
    """Cuts, numbers and places every document: the pieces with sequence_id and offset."""
    pieces = materialise(token_pieces(documents, keep, capacity=capacity, **how), "pieces")
    return assign(pieces, capacity, (*keep, "piece"))


def exact_minimum(items: list[int], capacity: int) -> int:
    """Fewest sequences by branch and bound; for tests on small sets."""
    items, best = sorted(items, reverse=True), len(items)

    def go(i: int, rooms: list[int]) -> None:
        nonlocal best
        if len(rooms) >= best:
            return
        if i == len(items):
            best = len(rooms)
            return
        for room in {r for r in rooms if r >= items[i]}:
            at = rooms.index(room)
            go(i + 1, [*rooms[:at], room - items[i], *rooms[at + 1 :]])
        go(i + 1, [*rooms, capacity - items[i]])

    go(0, [])
    return best

