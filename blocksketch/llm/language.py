"""Language identification with bit-sliced n-gram Bloom filters.

Each slot of one Bloom filter is a mask with a bit per language, so one look-up
(the AND of a few slots) returns all languages that contain an n-gram.  A
language contains an n-gram if its relative frequency there is at least a
share of the highest over languages.  A text's n-grams are looked up, bits are
counted per language, each count is corrected for the filter's false positives
in that language, and the highest decides.

N-grams are four bytes of lower-cased UTF-8, runs of other ASCII bytes reading
as a space.  Learning counts n-grams over all documents: tasks merge their
counts, which are summed by hash bucket.  A language's n-grams need a least
rate, so their number is bounded by its inverse whatever the corpus, and the
filter gets its slots from the number of n-grams that were chosen.

Defined results: null texts and texts without a letter give ``und`` and 0;
with nothing learned every text gives ``und``; ties go to the first language
by name; very long texts are read whole, in one run of their own; repeated rows
are each reported; a null id is kept like any other; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blocksketch.llm.common import discard, materialise, mix, row_runs, ship, text_buffer

RUN_BYTES = 1 << 20
#: Slots of the filter for each n-gram that any language holds, and the least and most slots (by powers of two).
SLOTS_PER_GRAM, LEAST_LOG2, MOST_LOG2 = 8, 16, 25
BUCKETS = 64
_LETTER = regex.compile(r"\p{L}")
_FOLD = np.full(256, 32, np.uint8)
_FOLD[0x41:0x5B] = np.arange(0x61, 0x7B)
_FOLD[0x61:0x7B] = np.arange(0x61, 0x7B)
_FOLD[0x80:] = np.arange(0x80, 0x100)


def grams_of(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, four-byte key) of every n-gram; each row is padded with a space on both sides."""
    n, sizes = len(offsets) - 1, np.diff(offsets)
    row = np.repeat(np.arange(n), sizes)
    padded = np.full(len(data) + 3 * n + 3, 32, np.uint8)
    padded[np.arange(len(data)) + 3 * row + 1] = _FOLD[data]
    owner = np.repeat(np.arange(n), sizes + 3)
    wide = padded.astype(np.uint64)
    key = wide[:-3] << np.uint64(24) | wide[1:-2] << np.uint64(16) | wide[2:-1] << np.uint64(8) | wide[3:]
    blank = padded == 32
    double = blank[:-1] & blank[1:]
    good = ~(double[:-2] | double[1:-1] | double[2:])
    key, owner = key[: len(owner)], owner[: len(key)]
    good = good[: len(owner)]
    return owner[good], key[good]


def count_grams(documents: DataFrame, lang: str = "lang", text: str = "text") -> DataFrame:
    """Packed counts: bucket, lang, keys and counts as little-endian 64-bit numbers."""
    ship(documents.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, list[tuple[np.ndarray, np.ndarray]]] = {}
        for batch in batches:
            langs = np.array(batch.column(0).to_pylist(), object)
            data, offsets = text_buffer(batch.column(1))
            for a, b in row_runs(offsets, RUN_BYTES):
                owner, key = grams_of(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
                part = langs[a:b]
                for name in set(part):
                    of = np.unique(key[(part == name)[owner]], return_counts=True)
                    have = held.setdefault(name, [])
                    have.append(of)
                    if len(have) >= 8:
                        held[name] = [_merge(have)]
        rows = []
        for name, have in held.items():
            key, count = _merge(have)
            at = (mix(key) % np.uint64(BUCKETS)).astype(int)
            for b in range(BUCKETS):
                if (mine := at == b).any():
                    rows.append((b, name, key[mine].astype("<i8").tobytes(), count[mine].astype("<i8").tobytes()))
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.int32(), pa.string(), pa.binary(), pa.binary()))], ["bucket", "lang", "keys", "counts"])

    return documents.select(lang, text).mapInArrow(run, "bucket int, lang string, keys binary, counts binary")


def _merge(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    key = np.concatenate([k for k, _ in parts])
    count = np.concatenate([c for _, c in parts])
    out, inverse = np.unique(key, return_inverse=True)
    return out, np.bincount(inverse, count, len(out)).astype(np.int64)


@dataclass
class LanguageFilter:
    """The learned filter: names, masks (slots x words of 64 languages), false positive rates."""

    names: list[str]
    masks: np.ndarray
    rates: np.ndarray

    def predict(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Index of each row's language and its score; -1 where nothing decides."""
        n, k = len(offsets) - 1, len(self.names)
        owner, key = grams_of(data, offsets)
        one, two = _slots(key, len(self.masks))
        total = np.bincount(owner, minlength=n)
        counts = np.zeros((n, k))
        for word in range(self.masks.shape[1]):
            table = self.masks[:, word]
            seen = table[one] & table[two]
            for bit in range(min(64, k - 64 * word)):
                hit = (seen >> np.uint64(bit)) & np.uint64(1)
                counts[:, 64 * word + bit] = np.bincount(owner, hit, n)
        fixed = np.maximum(0, (counts - total[:, None] * self.rates) / np.maximum(1 - self.rates, 1e-9))
        best = fixed.argmax(1) if k else np.full(n, -1)
        most = fixed[np.arange(n), best] if k else np.zeros(n)
        score = most / np.maximum(fixed.sum(1), 1e-12)
        return best, np.where(most > 0, score, 0.0)


def _slots(key: np.ndarray, slots: int) -> tuple[np.ndarray, np.ndarray]:
    h = mix(key + np.uint64(0x9E3779B97F4A7C15))
    low = np.uint64(slots - 1)
    return (h & low).astype(np.int64), ((h >> np.uint64(32)) & low).astype(np.int64)


def learn(documents: DataFrame, lang: str = "lang", text: str = "text", share: float = 0.3, least: int = 3, least_rate: float = 1e-6) -> LanguageFilter:
    """The filter learned from the rows with a language.

    A language holds an n-gram that it shows ``least`` times, at a rate of at
    least ``least_rate`` of its n-grams and ``share`` of the highest rate of any
    language.
    """
    known = documents.where(F.col(lang).isNotNull())
    packed = count_grams(known, lang, text)
    sums = packed.groupBy("bucket", "lang").agg(F.collect_list(F.struct("keys", "counts")).alias("parts"))

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = {"bucket": [], "lang": [], "keys": [], "counts": [], "total": []}
            for r in batch.to_pylist():
                key, count = _merge([(np.frombuffer(p["keys"], "<i8").astype(np.uint64), np.frombuffer(p["counts"], "<i8")) for p in r["parts"]])
                out["bucket"].append(r["bucket"])
                out["lang"].append(r["lang"])
                out["keys"].append(key.astype("<i8").tobytes())
                out["counts"].append(count.astype("<i8").tobytes())
                out["total"].append(int(count.sum()))
            yield pa.RecordBatch.from_arrays([pa.array(out["bucket"], pa.int32()), pa.array(out["lang"], pa.string()), pa.array(out["keys"], pa.binary()), pa.array(out["counts"], pa.binary()), pa.array(out["total"], pa.int64())], list(out))

    summed = materialise(sums.mapInArrow(add, "bucket int, lang string, keys binary, counts binary, total long"), "grams")
    totals = {r["lang"]: r["t"] for r in summed.groupBy("lang").agg(F.sum("total").alias("t")).collect()}
    names = sorted(n for n, t in totals.items() if t)
    if not names:
        discard(summed)
        return LanguageFilter([], np.zeros((1 << LEAST_LOG2, 1), np.uint64), np.zeros(0))
    words = (len(names) + 63) // 64
    per = np.array([1.0 / totals[n] for n in names])
    index = {n: i for i, n in enumerate(names)}

    def choose(key: tuple, table: pa.Table) -> pa.Table:
        held = [(index[r["lang"]], np.frombuffer(r["keys"], "<i8").astype(np.uint64), np.frombuffer(r["counts"], "<i8")) for r in table.to_pylist() if r["lang"] in index]
        grams = np.unique(np.concatenate([k for _, k, _ in held]))
        counts = np.zeros((len(grams), len(names)))
        for i, k, c in held:
            counts[np.searchsorted(grams, k), i] = c
        rate = counts * per
        has = (counts >= least) & (rate >= least_rate) & (rate >= share * rate.max(1, keepdims=True))
        some = has.any(1)
        grams, has = grams[some], has[some]
        which, masks = [], []
        for w in range(words):
            masks.append((has[:, 64 * w : 64 * w + 64].astype(np.uint64) << np.arange(min(64, len(names) - 64 * w), dtype=np.uint64)).sum(1).astype(np.uint64))
            which.append(np.full(len(grams), w, np.int32))
        return pa.table({"gram": pa.array(np.tile(grams, words).view(np.int64)), "word": pa.array(np.concatenate(which)), "mask": pa.array(np.concatenate(masks).view(np.int64))})

    chosen = materialise(summed.groupBy("bucket").applyInArrow(choose, "gram long, word int, mask long"), "chosen")
    discard(summed)
    n = chosen.count() // words
    size = 1 << min(MOST_LOG2, max(LEAST_LOG2, int(SLOTS_PER_GRAM * n).bit_length()))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            one, two = _slots(batch.column(0).to_numpy().view(np.uint64), size)
            word = batch.column(1).to_numpy()
            yield pa.RecordBatch.from_arrays([pa.array(np.r_[one, two] * words + np.r_[word, word]), pa.array(np.tile(batch.column(2).to_numpy(), 2))], ["slot", "mask"])

    merged = chosen.mapInArrow(place, "slot long, mask long").groupBy("slot").agg(F.bit_or("mask").alias("mask")).toArrow()  # two rows an n-gram and word at most
    discard(chosen)
    masks = np.zeros(size * words, np.uint64)
    masks[merged["slot"].to_numpy()] = merged["mask"].to_numpy().view(np.uint64)
    masks = masks.reshape(-1, words)
    filled = np.array([((masks[:, i // 64] >> np.uint64(i % 64)) & np.uint64(1)).mean() for i in range(len(names))])
    return LanguageFilter(names, masks, filled**2)


def identify(documents: DataFrame, learned: LanguageFilter, keep: tuple[str, ...] = ("doc_id",), text: str = "text") -> DataFrame:
    """``keep`` plus lang_pred and score of every row."""
    spark = documents.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(learned)  # slots from the counted n-grams, at most 2**MOST_LOG2
    src = documents.select(*keep, text)
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in src.schema.fields[:-1]), "lang_pred string, score double"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        names = np.array([*model.names, "und"], object)
        for batch in batches:
            column = batch.column(len(keep))
            data, offsets = text_buffer(column)
            best, score = [np.zeros(0, int)], [np.zeros(0)]
            for a, b in row_runs(offsets, RUN_BYTES):
                i, s = model.predict(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
                letters = np.array([t is not None and _LETTER.search(t) is not None for t in column.slice(a, b - a).to_pylist()], bool)
                best.append(np.where(letters, i, -1))
                score.append(np.where(letters, s, 0.0))
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], pa.array(names[np.concatenate(best)], pa.string()), pa.array(np.concatenate(score))], [*keep, "lang_pred", "score"])

    return src.mapInArrow(run, schema)
