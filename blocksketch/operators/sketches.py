"""Competing sketches: dense Gaussian and sign sketches, hashed sums, Hadamard-based and uniform block draws.

A sketch is returned as rows ``sketch_row, features, label``: S A and S b.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blocksketch.functions.core import hash_int
from blocksketch.operators import sampling, scores
from blocksketch.operators.stats import Total, block_stats, collect_total

#: Rows of a sign sketch whose signs in one column are one word (sums of all words fit a core's first cache), and rows that share a stream of random bits.
WORD, RUN = 12, 252
#: The signs that each half of a word stands for, the highest bit first.
HALF_SIGNS = np.unpackbits(np.arange(64, dtype=np.uint8)[:, None], axis=1)[:, 2:] * 2.0 - 1


def dense_sketch(design: DataFrame, d: int, r: int, kind: str = "gaussian", seed: int = 0) -> DataFrame:
    """r rows of S [A | b] for an r x N matrix of independent entries of variance 1/r.

    O(N r d) whatever the layout: a task makes its columns of S from hashes of
    the row ids and returns one r x (d+1) partial product; the partials are
    summed by row.  Meant as a baseline, not for the largest inputs.
    """
    if kind not in ("gaussian", "rademacher"):
        raise ValueError("kind is 'gaussian' or 'rademacher'")

    def entries(ids: np.ndarray) -> np.ndarray:
        def bits(salt: int) -> np.ndarray:
            x = (ids.astype(np.uint64)[None, :] * np.uint64(0x9E3779B97F4A7C15)) ^ (np.arange(r, dtype=np.uint64)[:, None] * np.uint64(0xD6E8FEB86659FD93) + np.uint64(salt + 1000 * seed + 1))
            x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
            x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
            return x ^ (x >> np.uint64(31))

        if kind == "rademacher":
            return np.where(bits(0) >> np.uint64(63), 1.0, -1.0)
        u = ((bits(0) >> np.uint64(11)).astype(float) + 1) / 2.0**53
        v = (bits(1) >> np.uint64(11)).astype(float) / 2.0**53
        return np.sqrt(-2 * np.log(u)) * np.cos(2 * np.pi * v)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = np.zeros((r, d + 1))
        for batch in batches:
            for a in range(0, batch.num_rows, 512):
                part = batch.slice(a, 512)
                rows = np.column_stack([part.column(1).flatten().to_numpy().reshape(-1, d), part.column(2).to_numpy()])
                held += entries(part.column(0).to_numpy()) @ rows
        held /= math.sqrt(r)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(r, dtype=np.int32)), *(pa.array(np.ascontiguousarray(held[:, i])) for i in range(d + 1))], ["sketch_row", *(f"v{i}" for i in range(d + 1))])

    parts = design.select("row_id", "features", "label").mapInArrow(run, "sketch_row int, " + ", ".join(f"v{i} double" for i in range(d + 1)))
    sums = parts.groupBy("sketch_row").agg(*[F.sum(f"v{i}").alias(f"v{i}") for i in range(d + 1)])
    return sums.select("sketch_row", F.array(*[f"v{i}" for i in range(d)]).alias("features"), F.col(f"v{d}").alias("label"))


def rademacher_rows(design: DataFrame, d: int, r: int, seed: str = "sign") -> DataFrame:
    """A small sign sketch as plain expressions (one hashed bit per entry); r is a handful."""
    sign = [F.when(hash_int(f"{seed}{i}", F.col("row_id")) % 2 == 0, 1.0).otherwise(-1.0) / F.lit(math.sqrt(r)) for i in range(r)]
    sums = design.agg(*[F.sum(sign[i] * F.get("features", F.lit(j))).alias(f"s{i}_{j}") for i in range(r) for j in range(d)], *[F.sum(sign[i] * F.col("label")).alias(f"b{i}") for i in range(r)])
    rows = F.array(*[F.struct(F.lit(i).alias("sketch_row"), F.array(*[F.col(f"s{i}_{j}") for j in range(d)]).alias("features"), F.col(f"b{i}").alias("label")) for i in range(r)])
    return sums.select(F.explode(rows).alias("x")).select("x.*")


def countsketch(design: DataFrame, d: int, r: int, seed: int = 0) -> DataFrame:
    """Every row goes to one of r hashed sums with a hashed sign: one pass, r rows."""
    bucket = (hash_int(f"cs{seed}", F.col("row_id")) % r).cast("int")
    sign = F.when(hash_int(f"sg{seed}", F.col("row_id")) % 2 == 0, 1.0).otherwise(-1.0)
    sums = design.groupBy(bucket.alias("sketch_row")).agg(*[F.sum(sign * F.get("features", F.lit(i))).alias(f"s{i}") for i in range(d)], F.sum(sign * F.col("label")).alias("label"))
    return sums.select("sketch_row", F.array(*[f"s{i}" for i in range(d)]).alias("features"), "label")


def hadamard(x: np.ndarray) -> np.ndarray:
    """Walsh-Hadamard transform along the first axis (a power of two long), unscaled."""
    h, n = 1, len(x)
    x = x.copy()
    while h < n:
        y = x.reshape(n // (2 * h), 2, h, -1)
        x = np.stack([y[:, 0] + y[:, 1], y[:, 0] - y[:, 1]], 1).reshape(n, -1)
        h *= 2
    return x


def block_srht(design: DataFrame, d: int, k: int, q: int, seed: int = 0) -> DataFrame:
    """Random signs, Hadamard transform, uniform draw of q blocks, scale sqrt(k/q)/sqrt(N).

    The transform of N = k tau rows is split as (k x k) by (tau x tau): each
    block is transformed where it lies, and only drawn output blocks are then
    summed over the input blocks with signs (parity of the common bits).  Rows
    must be numbered 0..N-1 in ``row_id`` with block_id = row_id // tau; both
    counts are padded to powers of two.
    """
    n = design.agg(F.max("row_id")).first()[0] + 1
    kk = 1 << max(0, (k - 1).bit_length())
    tau = 1 << max(0, (-(-n // kk) - 1).bit_length())
    drawn = np.random.default_rng(seed).integers(0, kk, q)
    # an output block is all its rows: trial t has the sketch rows t tau .. t tau + tau - 1
    out, i = np.repeat(drawn, tau), np.tile(np.arange(tau), q)
    return _hadamard_sums(design, d, tau, seed, out, i, math.sqrt(kk / q) / math.sqrt(kk * tau))


def _hadamard_sums(design: DataFrame, d: int, tau: int, seed: int, out: np.ndarray, i: np.ndarray, scale: float) -> DataFrame:
    """sketch_row, features, label: for each pair (out, i) the signed sum over the blocks of their i-th transformed row.

    Rows meet their block, nothing else is shuffled but sums: a task transforms
    its blocks one by one and adds them to its own copy of the sketch.
    """
    sign = F.when(hash_int(f"srht{seed}", F.col("row_id")) % 2 == 0, 1.0).otherwise(-1.0)
    placed = design.select(F.floor(F.col("row_id") / tau).alias("blk"), (F.col("row_id") % tau).cast("int").alias("i"), F.transform("features", lambda v: v * sign).alias("f"), (F.col("label") * sign).alias("y"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, block, rows = np.zeros((len(out), d + 1)), None, np.zeros((tau, d + 1))

        def add() -> None:
            if block is not None:
                parity = 1.0 - 2.0 * (np.bitwise_count(out & block) & 1)
                held[:] += parity[:, None] * hadamard(rows)[i]

        for batch in batches:
            if not batch.num_rows:
                continue
            blk, at = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            x = np.column_stack([batch.column(2).flatten().to_numpy().reshape(-1, d), batch.column(3).to_numpy()])
            cuts = np.flatnonzero(np.r_[True, np.diff(blk) != 0, True])
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                if blk[a] != block:
                    add()
                    block, rows = int(blk[a]), np.zeros((tau, d + 1))
                rows[at[a:b]] = x[a:b]
        add()
        if block is not None:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(out), dtype=np.int64)), *(pa.array(np.ascontiguousarray(held[:, j]) * scale) for j in range(d + 1))], ["sketch_row", *(f"v{j}" for j in range(d + 1))])

    parts = placed.repartition("blk").sortWithinPartitions("blk").mapInArrow(run, "sketch_row long, " + ", ".join(f"v{j} double" for j in range(d + 1)))
    sums = parts.groupBy("sketch_row").agg(*[F.sum(f"v{j}").alias(f"v{j}") for j in range(d + 1)])
    return sums.select("sketch_row", F.array(*[f"v{j}" for j in range(d)]).alias("features"), F.col(f"v{d}").alias("label"))


def srht_rows(design: DataFrame, d: int, r: int, seed: int = 0, tau: int = 256) -> DataFrame:
    """The same with single rows as blocks, on the whole design.

    A drawn output row takes one row of each run of ``tau`` transformed rows,
    so runs of any length give the same sketch.
    """
    n = 1 << max(0, int(design.agg(F.max("row_id")).first()[0]).bit_length())
    tau = min(tau, n)
    drawn = np.random.default_rng(seed).integers(0, n, r)
    return _hadamard_sums(design, d, tau, seed, drawn // tau, drawn % tau, 1 / math.sqrt(r))


def uniform_block_draws(design: DataFrame, k: int, q: int, iterations: int, seed: int) -> DataFrame:
    """Draws with equal chances: the data-oblivious block baseline."""
    return sampling.draw_blocks(scores.uniform_scores(design.sparkSession, k), q, iterations, seed)


def gaussian_totals(total: Total, r: int, seeds: list[tuple[int, ...]]) -> list[Total]:
    """Statistics of one new Gaussian sketch of r rows for each seed.

    The rows of S [A | b] are independent normal vectors whose covariance is
    the Gram matrix of [A | b] over r, so that of the sketch follows a Wishart
    law and is drawn from it: the same distribution as forming S, without N r
    normal numbers for every iteration.
    """
    values, vectors = np.linalg.eigh(sampling.with_label(total))
    half = vectors * np.sqrt(np.clip(values, 0, None) / r)
    m, out = len(values), []
    for seed in seeds:
        rng = np.random.default_rng(seed)
        if r >= m:
            z = np.tril(rng.normal(size=(m, m)), -1) + np.diag(np.sqrt(rng.chisquare(r - np.arange(m))))
        else:
            z = rng.normal(size=(m, r))
        out.append(_as_total((half @ z) @ (half @ z).T, r))
    return out


def _as_total(gram: np.ndarray, rows: int) -> Total:
    d = len(gram) - 1
    return Total(gram[:d, :d], gram[:d, d], float(gram[d, d]), rows)


def srht_gram(x: np.ndarray, kk: int, q: int, seed: tuple[int, ...], signs: tuple[int, ...] | None = None) -> np.ndarray:
    """Gram matrix of one block SRHT of the padded rows x: kk blocks, q of them drawn; ``signs`` seeds the signs alone."""
    rng = np.random.default_rng(seed)
    sign = rng.integers(0, 2, len(x)) * 2.0 - 1
    drawn = rng.integers(0, kk, q)
    if signs is not None:
        sign = np.random.default_rng(signs).integers(0, 2, len(x)) * 2.0 - 1
    # the transform inside a block turns its rows by an orthogonal matrix (times sqrt(tau)), which the Gram matrix does not see;
    # that across blocks is two factors, the second of which only drawn blocks need
    low = 1 << (kk.bit_length() - 1) // 2
    first, second = hadamard(np.eye(low)), hadamard(np.eye(kk // low))
    z = first @ (x * sign[:, None]).reshape(kk // low, low, -1)
    gram = np.zeros((x.shape[1], x.shape[1]))
    for i in range(low):
        y = (second[drawn[drawn % low == i] // low] @ z[:, i]).reshape(-1, x.shape[1])
        gram += y.T @ y
    return gram / q


def _totals_of_copies(design: DataFrame, d: int, rows: int, seeds: list[tuple], gram: Callable[[np.ndarray, tuple], np.ndarray], n: int) -> list[Total]:
    """Statistics of one new sketch of n rows for each seed, in one job.

    A task holds the design, padded to ``rows`` rows numbered from 0, and makes
    its share of the sketches: for baselines whose design fits a task.
    """
    parts = min(len(seeds), 2 * design.sparkSession.sparkContext.defaultParallelism)
    copies = design.select("row_id", "features", "label", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        x, part = np.zeros((rows, d + 1)), None
        for batch in batches:
            if batch.num_rows:
                at, part = batch.column(0).to_numpy(), batch.column(3)[0].as_py()
                x[at, :d] = batch.column(1).flatten().to_numpy().reshape(-1, d)
                x[at, d] = batch.column(2).to_numpy()
        for i in range(part, len(seeds), parts) if part is not None else ():
            yield pa.RecordBatch.from_arrays([pa.array([i], pa.int32()), pa.array([gram(x, seeds[i]).ravel().tolist()], pa.list_(pa.float64()))], ["i", "gram"])

    # a copy is a task of its own
    made = copies.repartitionById(parts, "part").mapInArrow(run, "i int, gram array<double>").collect()  # d^2 numbers a seed
    return [_as_total(np.array(r["gram"]).reshape(d + 1, d + 1), n) for r in sorted(made, key=lambda r: r["i"])]


def srht_totals(design: DataFrame, d: int, k: int, q: int, seeds: list[tuple[int, ...]], resign: str = "every") -> list[Total]:
    """Statistics of one block SRHT for each seed, padded as in block_srht.

    ``resign`` says what is new in each: signs and drawn blocks (``every``), or
    the drawn blocks only, the signs being those of the first seed (``once``).
    """
    if resign not in ("once", "every"):
        raise ValueError("resign is 'once' or 'every'")
    n = design.agg(F.max("row_id")).first()[0] + 1
    kk = 1 << max(0, (k - 1).bit_length())
    tau = 1 << max(0, (-(-n // kk) - 1).bit_length())
    signs = seeds[0] if resign == "once" else None
    return _totals_of_copies(design, d, kk * tau, seeds, lambda x, seed: srht_gram(x, kk, q, seed, signs), q * tau)


def _sign_words(seed: tuple[int, ...], run: int, r: int, n: int) -> Iterator[tuple[int, np.ndarray]]:
    """A run of RUN rows of an r x n sign sketch: for each WORD rows how many the sketch has, and for every column their signs as one word, the first row in the highest bit."""
    bits = np.random.SFC64((*seed, run))
    for first in range(run * RUN, min(r, (run + 1) * RUN), WORD):
        yield min(WORD, r - first), bits.random_raw(-(-n // 4)).view(np.uint16)[:n] & np.uint16((1 << WORD) - 1)


def sign_rows(seed: tuple[int, ...], run: int, r: int, n: int) -> np.ndarray:
    """The same run as rows of zeros (for -1) and ones."""
    place = np.arange(WORD - 1, -1, -1, dtype=np.uint16)[:, None]
    return np.vstack([((word >> place[:rows]) & np.uint16(1)).astype(np.uint8) for rows, word in _sign_words(seed, run, r, n)])


def sign_normal(values: np.ndarray, seed: tuple[int, ...], runs: range, r: int) -> np.ndarray:
    """S'S V for the rows of S in these runs and V of n x c numbers, without a multiplication for each sign.

    WORD rows of S are one word a column: numbers are summed by word, and the
    products of the WORD rows follow from the sums of the 2^WORD words; on the
    way back a column looks its word's number up.
    """
    n, c = values.shape
    out, found, at, u = np.zeros((n, c)), np.empty((n, c)), np.empty(n, np.intp), np.empty((WORD, c))
    columns, numbers, half = np.ascontiguousarray(values.T), np.empty((1 << WORD, c)), WORD // 2
    for run in runs:
        for rows, word in _sign_words(seed, run, r, n):
            np.copyto(at, word)
            for j in range(c):
                sums = np.bincount(at, columns[j], 1 << WORD).reshape(1 << half, -1)
                u[:half, j], u[half:, j] = sums.sum(1) @ HALF_SIGNS, sums.sum(0) @ HALF_SIGNS
            u[rows:] = 0  # beyond the sketch's last row
            high, low = HALF_SIGNS @ u[:half], HALF_SIGNS @ u[half:]
            for j in range(c):
                np.add.outer(high[:, j], low[:, j], out=numbers.reshape(1 << half, -1, c)[:, :, j])
            out += np.take(numbers, at, axis=0, out=found, mode="wrap")
    return out


def rademacher_totals(design: DataFrame, d: int, r: int, seeds: list[tuple[int, ...]]) -> list[Total]:
    """Statistics of one new sign sketch of r rows for each seed: N r d multiplications each.

    Few seeds are split among the tasks by runs of rows.
    """
    n = design.agg(F.max("row_id")).first()[0] + 1
    runs, parts = -(-r // RUN), 2 * design.sparkSession.sparkContext.defaultParallelism
    split = 1 if len(seeds) >= parts else min(runs, parts)

    def gram(x: np.ndarray, piece: tuple[tuple[int, ...], int]) -> np.ndarray:
        seed, first = piece
        out = np.zeros((d + 1, d + 1))
        for run in range(first, runs, split):
            signs, y = sign_rows(seed, run, r, n), 0
            for a in range(0, n, 4096):  # some columns of S at a time
                y += (signs[:, a : a + 4096] * 2.0 - 1) @ x[a : a + 4096]
            out += y.T @ y / r
        return out

    made = _totals_of_copies(design, d, n, [(seed, first) for seed in seeds for first in range(split)], gram, r)
    each = [made[i : i + split] for i in range(0, len(made), split)]
    return [Total(sum(t.gram for t in some), sum(t.atb for t in some), sum(t.btb for t in some), r) for some in each]


class SignGradients:
    """Gradients under one new sign sketch of r rows for each seed, those of ``rademacher_totals``, without their Gram matrices.

    A gradient needs S (A x - b) and the way back through S only, so a sketch
    that one step uses costs 2 N r sums a point, d times less than its
    statistics.  One job a call; a worker keeps the design from the first call
    on, which the driver hands out: for baselines whose design fits a task.
    """

    def __init__(self, design: DataFrame, d: int, r: int, seeds: list[tuple[int, ...]]) -> None:
        got = design.select("row_id", "features", "label").toArrow().combine_chunks()
        at = got["row_id"].to_numpy()
        x = np.zeros((at.max() + 1, d + 1))
        x[at, :d] = pc.list_flatten(got["features"]).to_numpy().reshape(-1, d)
        x[at, d] = got["label"].to_numpy()
        self.spark, self.r, self.seeds = design.sparkSession, r, seeds
        self.held = self.spark.sparkContext.broadcast(x)

    def __call__(self, s: int, xs: np.ndarray) -> np.ndarray:
        """points x d: the gradients at the points xs under sketch s."""
        held, seed, r, runs = self.held, self.seeds[s], self.r, -(-self.r // RUN)
        parts = min(runs, self.spark.sparkContext.defaultParallelism)
        points = np.column_stack([xs, np.full(len(xs), -1.0)]).T

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for part in batch.column(0).to_pylist():
                    x = held.value
                    g = x[:, :-1].T @ sign_normal(x @ points, seed, range(part, runs, parts), r)
                    yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([g.T.ravel().tolist()], pa.list_(pa.float64()))], ["part", "g"])

        made = self.spark.range(parts, numPartitions=parts).mapInArrow(run, "part int, g array<double>").collect()  # d numbers a point and task
        return 2 / r * np.sum([m["g"] for m in sorted(made, key=lambda m: m["part"])], 0).reshape(xs.shape)

    def free(self) -> None:
        """Ends the copies on the executors and the driver."""
        self.held.destroy()


def sketch_total(sketch: DataFrame, d: int) -> Total:
    """Gram matrix and right side of a sketch."""
    return collect_total(block_stats(sketch.select(F.lit(0).alias("block_id"), "features", "label"), d), d)


def sketch_and_solve(sketch: DataFrame, d: int) -> np.ndarray:
    """The optimum of the sketched problem: one pass, no iteration."""
    return sketch_total(sketch, d).solution()


def half_sketch_solution(total: Total, sketched: Total) -> np.ndarray:
    """The second classical estimate: sketched Gram matrix, full right side."""
    return np.linalg.lstsq(sketched.gram, total.atb, rcond=None)[0]


def srht_trials(d: int, tau: int, n: int, eps: float, delta: float, form: str = "printed") -> int:
    """Blocks that the Hadamard-based sketch needs, printed form (with 1/tau) or without."""
    if not (0 < eps < 1 and 0 < delta < 1):
        raise ValueError("eps and delta in (0, 1)")
    rate = d * math.log(n * d / delta) * math.log(2 * d / delta) / eps**2
    return math.ceil(rate / tau if form == "printed" else rate)
