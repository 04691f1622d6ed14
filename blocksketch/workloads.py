"""The published experiments, re-expressed on the given tables."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blocksketch.fixtures import load
from blocksketch.functions.core import hash_normal, hash_uniform
from blocksketch.operators import descent, design, sampling, scores, sketches, stats
from blocksketch.operators.descent import Stop, fixed_step
from blocksketch.sources.tables import stored, t_matrix

#: Fixed values of the published setting: blocks, draws, columns, iterations, instances.
K, DRAWS, COLUMNS, ITERATIONS, INSTANCES = 100, 50, 40, 600, 6
#: Steps as multiples of 2 / sigma_max^2, by powers of ten as in the published sweep; the last ones stay stable.
SHARES = [0.00025, 0.0025, 0.025, 0.25]
#: Weights (iterations x blocks) that the driver holds at once, 32 MB.
MOST_WEIGHTS = 1 << 22
#: Signs of a sketch beyond which only the products that a step needs are made, a job a step, instead of its statistics.
MOST_SIGNS = 1 << 27


def heavy_matrix(spark: SparkSession, n: int = 2000, instance: int = 0) -> DataFrame:
    """n x 40 entries of a t-distribution with planted labels and unit noise."""
    rows = t_matrix(spark, n, COLUMNS, seed=instance, blocks=K)
    return design.plant_labels(rows, [0.2 * (i % 9 - 4) for i in range(COLUMNS)], 1.0, f"noise{instance}")


def scaled_matrix(spark: SparkSession, kind: str, n: int = 2000, instance: int = 0) -> DataFrame:
    """n x 40 normal entries under a row scale: ``lognormal`` (sigma 1.5) or ``cauchy`` (absolute values)."""
    if kind not in ("lognormal", "cauchy"):
        raise ValueError("kind is 'lognormal' or 'cauchy'")
    i, seed = F.col("id"), f"{kind}{instance}"
    scale = F.exp(1.5 * hash_normal(f"scale{seed}", i)) if kind == "lognormal" else F.abs(F.tan(F.pi() * (hash_uniform(f"scale{seed}", i) - 0.5)))
    rows = spark.range(n).select(i.alias("row_id"), F.floor(i * F.lit(K) / F.lit(n)).cast("int").alias("block_id"), F.array(*[scale * hash_normal(seed, i, F.lit(j)) for j in range(COLUMNS)]).alias("features"))
    return design.plant_labels(rows, [0.2 * (j % 9 - 4) for j in range(COLUMNS)], 1.0, f"noise{seed}")


def half_the_blocks(rows: DataFrame) -> int:
    """The published number of draws: half of the blocks."""
    return max(4, rows.agg(F.count_distinct("block_id").alias("k")).first()["k"] // 2)


def weights_for(method: str, dist: DataFrame, iterations: int, seed: int, q: int) -> DataFrame:
    """Weights of every iteration for block leverage, uniform blocks, or plain stochastic blocks."""
    if method == "leverage":
        return sampling.weights(sampling.draw_blocks(dist, q, iterations, seed), q)
    even = dist.select("block_id", F.lit(1.0 / dist.count()).alias("p"))
    if method == "uniform":
        return sampling.weights(sampling.draw_blocks(even, q, iterations, seed), q)
    return sampling.draw_poisson(even, q, iterations, seed).select("iteration", "block_id", "w")


@dataclass
class Blocks:
    """Block statistics of a design: the stored table, its total and leverage distribution, and on the driver a row of K x (d^2 / 2) numbers for each block."""

    held: DataFrame
    total: stats.Total
    dist: DataFrame
    names: np.ndarray
    numbers: np.ndarray

    def totals(self, weights: DataFrame, iterations: int) -> list[stats.Total]:
        """The weighted sum of the blocks' statistics for every iteration: a product of the weights, some iterations at a time, with the statistics."""
        drawn = weights.select("iteration", "block_id", "w").toArrow()  # iterations x q numbers
        at, col, w = drawn["iteration"].to_numpy(), np.searchsorted(self.names, drawn["block_id"].to_numpy()), drawn["w"].to_numpy()
        d, made, each = len(self.total.gram), [], max(1, MOST_WEIGHTS // len(self.names))
        upper = np.triu_indices(d)
        for first in range(0, iterations, each):
            some = (at >= first) & (at < first + each)
            table = np.zeros((min(each, iterations - first), len(self.names)))
            np.add.at(table, (at[some] - first, col[some]), w[some])
            for row in table @ self.numbers:
                gram = np.zeros((d, d))
                gram[upper] = row[:-d]
                made.append(stats.Total(gram + np.triu(gram, 1).T, row[-d:].copy(), 0.0, 0))
        return made


def block_table(rows: DataFrame, d: int) -> Blocks:
    """One scan: all that the iterations on block statistics need."""
    held = stored(stats.block_stats(rows, d), "stats")
    total = stats.collect_total(held, d)
    got = held.select("block_id", "gram", "atb").toArrow().combine_chunks()  # K d^2 numbers
    names = got["block_id"].to_numpy()
    order = np.argsort(names)
    numbers = np.hstack([pc.list_flatten(got[c]).to_numpy().reshape(len(names), -1) for c in ("gram", "atb")])
    return Blocks(held, total, stored(scores.block_leverage(held, d, total), "dist"), names[order], numbers[order])


def compare_methods(rows: DataFrame, d: int, q: int, iterations: int, shares: list[float], seed: int = 0, line: bool = False, dense: bool = False, signs: bool = False, fixed: bool = False, blocks: Blocks | None = None) -> list[tuple]:
    """(method, share, log residual) of plain, leverage, uniform, fixed leverage and stochastic sketches.

    Iterations run on block statistics: one scan for all methods and steps, or
    none where ``blocks`` has them already.
    ``dense`` adds a new Gaussian sketch and a new block SRHT in every
    iteration, ``signs`` a new sign sketch, and ``fixed`` each of these with
    the first sketch throughout.  Large sign sketches are multiplied with the
    residuals of all steps' runs instead of the whole design; the sketches are
    the same.
    """
    blocks = blocks or block_table(rows, d)
    total, dist, k = blocks.total, blocks.dist, len(blocks.names)
    best, out = total.solution(), []
    unit = 2 / total.spectrum()["sigma_max"] ** 2

    def log(x: np.ndarray) -> float:
        return math.log10(max(float(np.linalg.norm(x - best)), 1e-300) / math.sqrt(total.n))

    sketched = {m: blocks.totals(weights_for(m, dist, iterations, seed, q), iterations) for m in ("leverage", "uniform", "stochastic")}
    if dense:
        sketched |= dense_totals(rows, total, d, k, q, iterations, seed)
    steps = [descent.line_search() if line else fixed_step(share * unit) for share in shares]
    ends: dict[str, list[float]] = {}
    if signs:
        r, seeds = max(1, round(q * total.n / k)), [(seed, s) for s in range(iterations)]
        large = r * total.n > MOST_SIGNS
        sketched["rademacher"] = sketches.rademacher_totals(rows, d, r, seeds[: 1 if large else None])
        if large:
            gradients = sketches.SignGradients(rows, d, r, seeds)
            ends["rademacher"] = [log(x) for x in descent.descend_together(total, gradients, [0.0] * d, steps, Stop(iterations))]
            gradients.free()
    for i, (share, step) in enumerate(zip(shares, steps, strict=True)):
        run = lambda s, fixed=False: log(descent.descend_on_stats(total, s, [0.0] * d, step, Stop(iterations), fixed).xs[-1])  # noqa: E731, B023
        out.append(("plain", share, run(None)))
        out += [(m, share, ends[m][i] if m in ends else run(s)) for m, s in sketched.items()]
        once = [m for m in sketched if m == "leverage" or fixed and m in ("gaussian", "block srht", "rademacher")]
        out += [(f"{m} fixed", share, run(sketched[m], True)) for m in once]
    return out


def dense_totals(rows: DataFrame, total: stats.Total, d: int, k: int, q: int, iterations: int, seed: int) -> dict[str, list[stats.Total]]:
    """Statistics of a Gaussian sketch (of as many rows as q blocks have) and a block SRHT for every iteration."""
    seeds = [(seed, s) for s in range(iterations)]
    return {"gaussian": sketches.gaussian_totals(total, max(1, round(q * total.n / k)), seeds), "block srht": sketches.srht_totals(rows, d, k, q, seeds)}


def curves(rows: DataFrame, d: int, q: int, iterations: int, share: float, every: int, seed: int = 0) -> list[tuple]:
    """(method, s, log residual) of plain descent, of leverage and uniform draws, and of new dense sketches."""
    held = stored(stats.block_stats(rows, d), "stats")
    total = stats.collect_total(held, d)
    dist = stored(scores.block_leverage(held, d, total), "dist")
    step, best, out = fixed_step(share * 2 / total.spectrum()["sigma_max"] ** 2), total.solution(), []
    made = {m: descent.sketch_totals(held, weights_for(m, dist, iterations, seed, q), d) for m in ("leverage", "uniform")}
    made |= dense_totals(rows, total, d, held.count(), q, iterations, seed)
    runs = {"plain": (None, False), "gaussian": (made["gaussian"], False), "block srht": (made["block srht"], False), "leverage": (made["leverage"], False), "uniform": (made["uniform"], False), "leverage fixed": (made["leverage"], True)}
    for name, (sketched, fixed) in runs.items():
        xs = descent.descend_on_stats(total, sketched, [0.0] * d, step, Stop(iterations), fixed).xs
        out += [(name, s, math.log10(max(float(np.linalg.norm(xs[s] - best)), 1e-300) / math.sqrt(total.n))) for s in range(0, len(xs), every)]
    return out


def residual_table(spark: SparkSession, sf_dir: str, source: str = "embeddings", iterations: int = ITERATIONS, instances: int = INSTANCES) -> DataFrame:
    """method, share, log_residual: the published sweep on the embeddings view, or on t-distributed matrices.

    The mean over the instances: seeds of the draws, and on ``t`` of the matrix too.
    """
    found: dict[tuple, list[float]] = {}
    for i in range(instances):
        if i == 0 or source != "embeddings":
            rows = stored(load(spark, sf_dir, "embeddings") if source == "embeddings" else heavy_matrix(spark, instance=i), "design")
            q, blocks = half_the_blocks(rows), block_table(rows, COLUMNS)
        for method, share, value in compare_methods(rows, COLUMNS, q, iterations, SHARES, i, dense=True, blocks=blocks):
            found.setdefault((method, share), []).append(value)
    out = [(m, share, float(np.mean(v))) for (m, share), v in found.items()]
    return spark.createDataFrame(out, "method string, share double, log_residual double")
