"""Quality scores learned from preference pairs (Bradley-Terry).

Every text becomes a row of features: a few shape measures (shares of byte
classes, entropy, word repetition, line and word lengths) and its word and
word-pair counts, hashed to a fixed width and taken as square roots of shares.
From labelled documents, pairs of a good and a bad one are drawn; weights
minimise the logistic loss on the differences of their features.  The threshold
is a quantile of the training scores, at the share of bad ones among them, and
scores are mapped so that it lies at ``at``.

Defined results: null and empty texts have all features 0 and are scored like
any other; very long texts are read whole; labels that are null, or that
contradict each other for a document, are not learned from; with no pair to
learn from every score is 0.5; a null id is held out or not as the empty string
is; repeated rows are each reported; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from blocksketch.llm.common import mix, row_runs, ship, text_buffer

RUN_BYTES = 1 << 21
_CLASSES = {
    "upper": range(0x41, 0x5B),
    "digit": range(0x30, 0x3A),
    "space": (0x20,),
    "line": (0x0A,),
    "bang": (0x21, 0x3F),
    "stop": (0x2C, 0x2E, 0x3A, 0x3B),
    "mark": tuple(b"#$%&*+<=>@^_`{}~\\/"),
    "bar": (0x7C,),
    "quote": tuple(b"\"'()[]-"),
    "high": range(0x80, 0x100),
    "control": (*range(0, 10), *range(11, 32), 0x7F),
}
#: Pairs whose differences are held at a time.
PAIRS = 1 << 12
#: Hashed counts of words and of word pairs.
HASHED = 128
MEASURES = [*_CLASSES, "entropy", "log_bytes", "word_bytes", "same_next", "distinct", "line_bytes", "top_word"]
_INDICATOR = np.zeros((256, len(_CLASSES)))
for _i, _v in enumerate(_CLASSES.values()):
    _INDICATOR[list(_v), _i] = 1
_IS_WORD = np.zeros(256, bool)
for _r in (range(0x30, 0x3A), range(0x41, 0x5B), range(0x61, 0x7B), range(0x80, 0x100)):
    _IS_WORD[list(_r)] = True


WIDTH = len(MEASURES) + HASHED


def features_of(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """The features of each row of a run of texts: rows x WIDTH, the measures first."""
    n, sizes = len(offsets) - 1, np.diff(offsets)
    row = np.repeat(np.arange(n), sizes)
    counts = np.bincount(row * 256 + data, minlength=n * 256).reshape(n, 256)
    total = np.maximum(sizes, 1)
    share = counts / total[:, None]
    out = np.zeros((n, WIDTH))
    k = len(_CLASSES)
    out[:, :k] = np.sqrt(share @ _INDICATOR)
    out[:, k] = -(share * np.log2(np.where(share > 0, share, 1))).sum(1)
    out[:, k + 1] = np.log1p(sizes)
    out[:, k + 5] = np.log1p(sizes / (counts[:, 0x0A] + 1))
    inside = _IS_WORD[data]
    before = np.zeros(len(data), bool)
    before[1:] = inside[:-1]
    before[offsets[:-1][sizes > 0]] = False
    starts = np.flatnonzero(inside & ~before)
    if len(starts):
        at = np.flatnonzero(inside)
        word = np.cumsum((inside & ~before)[at]) - 1
        place = at - starts[word]
        codes = mix(data[at].astype(np.uint64) + np.uint64(257) * (place.astype(np.uint64) + np.uint64(1)))
        hashes = np.add.reduceat(codes, np.searchsorted(at, starts))
        owner = row[starts]
        words = np.bincount(owner, minlength=n)
        many = np.maximum(words, 1)
        out[:, k + 2] = np.log1p(np.bincount(row[at], minlength=n) / many)
        same = (hashes[1:] == hashes[:-1]) & (owner[1:] == owner[:-1])
        out[:, k + 3] = np.bincount(owner[1:][same], minlength=n) / many
        order = np.lexsort((hashes, owner))
        h, o = hashes[order], owner[order]
        first = np.flatnonzero(np.r_[True, (h[1:] != h[:-1]) | (o[1:] != o[:-1])])
        out[:, k + 4] = np.bincount(o[first], minlength=n) / many**0.8
        top = np.zeros(n)
        np.maximum.at(top, o[first], np.diff(np.r_[first, len(h)]))
        out[:, k + 6] = top / many
        pair = mix(hashes[:-1] * np.uint64(3) + hashes[1:])[owner[1:] == owner[:-1]]
        at = np.r_[owner * HASHED + (hashes % np.uint64(HASHED)).astype(np.int64), owner[1:][owner[1:] == owner[:-1]] * HASHED + (pair % np.uint64(HASHED)).astype(np.int64)]
        out[:, len(MEASURES) :] = np.sqrt(np.bincount(at, minlength=n * HASHED).reshape(n, HASHED) / (2 * many)[:, None])
    out[sizes == 0] = 0
    return out


def _rows_of(batch: pa.RecordBatch, column: int) -> Iterator[np.ndarray]:
    data, offsets = text_buffer(batch.column(column))
    for a, b in row_runs(offsets, RUN_BYTES):
        yield features_of(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])


def featured(documents: DataFrame, keep: tuple[str, ...], text: str = "text") -> DataFrame:
    """``keep`` plus ``x``, the features as packed 32-bit numbers."""
    ship(documents.sparkSession)
    src = documents.select(*[F.col(f"`{c}`") for c in keep], F.col(text).alias("_text"))
    schema = T.StructType([*src.schema.fields[:-1], T.StructField("x", T.BinaryType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            packed = [r.astype("<f4").tobytes() for rows in _rows_of(batch, len(keep)) for r in rows]
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], pa.array(packed, pa.binary())], [*keep, "x"])

    return src.mapInArrow(run, schema)


@dataclass
class Ranker:
    """Centres, scales and weights of the features; slope and offset of the score."""

    centre: np.ndarray
    scale: np.ndarray
    weights: np.ndarray
    slope: float
    offset: float

    def score(self, x: np.ndarray) -> np.ndarray:
        """Scores in 0..1 of rows of features."""
        z = ((x - self.centre) / self.scale) @ self.weights * self.slope + self.offset
        return 1 / (1 + np.exp(-np.clip(z, -700, 700)))


def scored(documents: DataFrame, ranker: Ranker, keep: tuple[str, ...], text: str = "text") -> DataFrame:
    """``keep`` plus ``score`` of every row."""
    ship(documents.sparkSession)
    src = documents.select(*[F.col(f"`{c}`") for c in keep], F.col(text).alias("_text"))
    schema = T.StructType([*src.schema.fields[:-1], T.StructField("score", T.DoubleType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [ranker.score(rows) for rows in _rows_of(batch, len(keep))]
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], pa.array(np.concatenate([np.zeros(0), *found]))], [*keep, "score"])

    return src.mapInArrow(run, schema)


def learn(x: np.ndarray, y: np.ndarray, pairs_per_row: int = 8, penalty: float = 1e-3, at: float = 0.3, seed: int = 7) -> Ranker:
    """Weights from pairs (a row of label 1, a row of label 0), and the score's threshold."""
    good, bad = np.flatnonzero(y == 1), np.flatnonzero(y == 0)
    d = x.shape[1]
    if not len(good) or not len(bad):
        # the score 0.5 whatever the features
        return Ranker(np.zeros(d), np.ones(d), np.zeros(d), 1.0, 0.0)
    centre, scale = x.mean(0, dtype=np.float64), x.std(0, dtype=np.float64)
    scale = np.where(scale > 1e-6, scale, 1.0)
    rng = np.random.default_rng(seed)
    fewer, more = (good, bad) if len(good) < len(bad) else (bad, good)
    a = np.repeat(fewer, pairs_per_row * max(1, min(4, len(more) // len(fewer))))
    b = rng.choice(more, len(a))
    up, down = (a, b) if fewer is good else (b, a)
    w = np.zeros(d)
    for _ in range(20):
        grad, hess = penalty * w, penalty * np.eye(d)
        for i in range(0, len(up), PAIRS):  # differences of some pairs at a time; the centre falls out
            diff = (x[up[i : i + PAIRS]] - x[down[i : i + PAIRS]]) / scale
            p = 1 / (1 + np.exp(-np.clip(diff @ w, -60, 60)))
            grad -= diff.T @ (1 - p) / len(up)
            hess += (diff * (p * (1 - p))[:, None]).T @ diff / len(up)
        step = np.linalg.solve(hess, grad)
        w -= step
        if np.abs(step).max() < 1e-7:
            break
    s = x @ (w / scale) - centre @ (w / scale)
    spread = max(float(s[good].mean() - s[bad].mean()), 1e-6)
    slope = 6.0 / spread
    return Ranker(centre, scale, w, slope, float(np.log(at / (1 - at)) - slope * quantile_cut(s, len(bad) / (len(good) + len(bad)))))


def quantile_cut(s: np.ndarray, share: float) -> float:
    """The score quantile below which ``share`` of the scores lie: midway between its two neighbours."""
    ordered = np.sort(s)
    below = min(max(int(round(share * len(s))), 1), len(s) - 1) if len(s) > 1 else 0
    return float((ordered[max(below - 1, 0)] + ordered[below]) / 2)


def learned(documents: DataFrame, labels: DataFrame, key: str = "doc_id", label: str = "quality", folds: int = 5, held: int = 0, most_labelled: int = 40_000, at: float = 0.3) -> Ranker:
    """The ranker from at most ``most_labelled`` labelled documents outside the held-out fold.

    They are those of lowest hashed id.  This bounded list is broadcast to find
    their texts, so the documents are never shuffled.
    """
    fold = F.pmod(F.crc32(F.col("_k").cast("string")), F.lit(folds))
    known = labels.select(F.col(key).alias("_k"), F.col(label).alias("_y")).where("_k is not null and _y is not null")
    known = known.groupBy("_k").agg(F.min("_y").alias("_y"), F.max("_y").alias("_z")).where("_y = _z and _y in (0, 1)").where(fold != held)
    sample = known.orderBy(F.xxhash64("_k"), "_k").limit(most_labelled).select("_k", "_y")
    found = documents.select(F.col(key).alias("_id"), F.col("text").alias("_t")).join(F.broadcast(sample), F.col("_id") == F.col("_k"))
    # of rows with one id the least text counts, so the sample stays bounded
    found = found.groupBy("_k").agg(F.min("_t").alias("_t"), F.min("_y").alias("_y"))
    rows = featured(found, ("_k", "_y"), "_t").toArrow()  # at most WIDTH x most_labelled small numbers
    packed, _ = text_buffer(rows["x"])
    order = np.argsort(rows["_k"].to_numpy(), kind="stable")  # the same pairs however the rows arrive
    return learn(packed.view("<f4").reshape(-1, WIDTH)[order], rows["_y"].to_numpy()[order], at=at)


def score_documents(documents: DataFrame, labels: DataFrame, keep: tuple[str, ...] = ("doc_id",), label: str = "quality", folds: int = 5, held: int = 0, most_labelled: int = 40_000, at: float = 0.3) -> DataFrame:
    """``keep`` plus held_out, score and predicted for every row; ``keep`` begins with the id.

    Learns from at most ``most_labelled`` labelled documents outside the held-out fold.
    """
    fold = F.pmod(F.crc32(F.coalesce(F.col(keep[0]).cast("string"), F.lit(""))), F.lit(folds))
    ranker = learned(documents, labels, keep[0], label, folds, held, most_labelled, at)
    return scored(documents, ranker, keep).select(*keep, (fold == held).alias("held_out"), "score", (F.col("score") >= at).cast("int").alias("predicted"))


def keep_good(documents: DataFrame, labels: DataFrame, folds: int = 5, held: int = 0, most_labelled: int = 40_000, at: float = 0.3) -> DataFrame:
    """The rows of ``documents`` whose score reaches ``at``, with all their columns."""
    ranker = learned(documents, labels, folds=folds, held=held, most_labelled=most_labelled, at=at)
    packed = documents.select(F.struct(*[F.col(f"`{c}`") for c in documents.columns]).alias("_doc"), "text")
    return scored(packed, ranker, ("_doc",)).where(F.col("score") >= at).select("_doc.*")
