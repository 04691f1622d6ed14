"""Drawing blocks, sketches of drawn blocks, and how good they are.

Draws come from hashed uniforms of (seed, iteration, trial): the same whatever
the partitioning, independent between iterations.
"""

from __future__ import annotations

import math
from collections.abc import Sequence

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blocksketch.functions.core import add, dot, hash_uniform
from blocksketch.operators.stats import Total, packed, unpack
from blocksketch.plans.rewrites import small

#: Distributions of up to this many blocks, and of up to this many pairs with the draws, meet the draws by a broadcast range join.
MOST_BROADCAST_BLOCKS, MOST_BROADCAST_PAIRS = 20_000, 50_000_000


def cumulative(dist: DataFrame) -> DataFrame:
    """block_id, p, lo, hi: consecutive intervals of [0, 1). K rows, one task."""
    w = Window.orderBy("block_id")
    hi = F.sum("p").over(w)
    last = F.lead("block_id").over(w).isNull()
    return dist.select("block_id", "p", (hi - F.col("p")).alias("lo"), F.when(last, F.lit(1.0)).otherwise(hi).alias("hi"))


def draw_blocks(dist: DataFrame, q: int, iterations: int, seed: int) -> DataFrame:
    """iteration, trial, block_id, p: q draws with replacement in each iteration.

    Few blocks and draws: a broadcast range join. Many: both sides meet on 1/4096 bins of
    [0, 1), so that no nested loop is left.
    """
    if q < 1 or iterations < 1:
        raise ValueError("q and iterations are at least 1")
    spark = dist.sparkSession
    trials = spark.range(iterations * q).select(F.floor(F.col("id") / q).cast("int").alias("iteration"), (F.col("id") % q).cast("int").alias("trial"))
    trials = trials.withColumn("u", hash_uniform(str(seed), F.col("iteration"), F.col("trial")))
    cdf = cumulative(dist)
    k = dist.count()
    if k <= MOST_BROADCAST_BLOCKS and k * q * iterations <= MOST_BROADCAST_PAIRS:
        found = trials.join(F.broadcast(cdf), (F.col("u") >= F.col("lo")) & (F.col("u") < F.col("hi")))
    else:
        bins = 4096
        spread = cdf.withColumn("bin", F.explode(F.sequence(F.floor(F.col("lo") * bins), F.least(F.floor(F.col("hi") * bins), F.lit(bins - 1)))))
        found = trials.withColumn("bin", F.floor(F.col("u") * bins)).join(small(spread), "bin").where((F.col("u") >= F.col("lo")) & (F.col("u") < F.col("hi")))
    return found.select("iteration", "trial", "block_id", "p")


def draw_fastest(responses: DataFrame, q: int) -> DataFrame:
    """The q fastest replies of each iteration: draws without replacement among replicas."""
    w = Window.partitionBy("iteration").orderBy("t", "server_id")
    return responses.withColumn("trial", F.row_number().over(w) - 1).where(F.col("trial") < q)


def draw_deadline(responses: DataFrame, ending: float) -> DataFrame:
    """All replies up to the ending time, with the number that came (q varies)."""
    came = responses.where(F.col("t") <= ending)
    return came.withColumn("q", F.count("*").over(Window.partitionBy("iteration")))


def draw_poisson(dist: DataFrame, q: float, iterations: int, seed: int) -> DataFrame:
    """Independent inclusion with chance min(1, q p), weight 1 / chance: needs no global count."""
    spark = dist.sparkSession
    chance = F.least(F.lit(1.0), F.col("p") * q)
    each = dist.crossJoin(spark.range(iterations).select(F.col("id").cast("int").alias("iteration")))  # K x iterations rows
    return each.withColumn("chance", chance).where(hash_uniform(f"poisson{seed}", F.col("iteration"), F.col("block_id")) < F.col("chance")).select("iteration", "block_id", "p", (1 / F.col("chance")).alias("w"))


def weights(draws: DataFrame, q: int | None = None) -> DataFrame:
    """iteration, block_id, times (draws of the block), w = times / (q p): repeated draws merged before any join."""
    q_col = F.lit(q) if q else F.first("q")
    return draws.groupBy("iteration", "block_id", "p").agg(F.count("*").alias("times"), q_col.alias("q")).select("iteration", "block_id", "times", (F.col("times") / (F.col("q") * F.col("p"))).alias("w"))




def block_sketch(design: DataFrame, draws: DataFrame, q: int) -> DataFrame:
    """Rows of the sketch: drawn blocks (with repeats) scaled by 1/sqrt(q p)."""
    scale = 1 / F.sqrt(q * F.col("p"))
    held = small(draws.select("iteration", "trial", "block_id", "p"))
    return design.join(held, "block_id").select("iteration", "trial", "row_id", "block_id", F.transform("features", lambda v: v * scale).alias("features"), (F.col("label") * scale).alias("label"))


def weighted_sketch(design: DataFrame, weights_: DataFrame) -> DataFrame:
    """The same sketch with each distinct block once, scaled by sqrt(w)."""
    scale = F.sqrt("w")
    return design.join(small(weights_), "block_id").select("iteration", "row_id", "block_id", F.transform("features", lambda v: v * scale).alias("features"), (F.col("label") * scale).alias("label"))


def row_sketch(rows: DataFrame, r: int, seed: int) -> DataFrame:
    """Rows kept independently with chance min(1, r pi), weight 1/chance: blocks of one row, without a global draw."""
    chance = F.least(F.lit(1.0), F.col("pi") * r)
    return rows.withColumn("w", 1 / chance).where(hash_uniform(f"row{seed}", F.col("row_id")) < chance)


def draw_rows(rows: DataFrame, r: int, iterations: int, seed: int) -> DataFrame:
    """iteration, trial, row_id, pi, w = 1/(r pi): r draws of single rows with replacement, by ``pi``.

    A draw takes its block by the block's share, then a row inside it, so no
    running sum goes over all rows: it goes over the rows of one block.
    """
    shares = rows.groupBy("block_id").agg(F.sum("pi").alias("p"))
    draws = draw_blocks(shares, r, iterations, seed).withColumn("v", hash_uniform(f"row{seed}", F.col("iteration"), F.col("trial")) * F.col("p"))
    inside = Window.partitionBy("block_id").orderBy("row_id")
    hi = F.sum("pi").over(inside)
    spans = rows.select("block_id", "row_id", "pi", (hi - F.col("pi")).alias("lo"), F.when(F.lead("row_id").over(inside).isNull(), F.lit(2.0)).otherwise(hi).alias("hi"))
    found = draws.join(spans, "block_id").where((F.col("v") >= F.col("lo")) & (F.col("v") < F.col("hi")))
    return found.select("iteration", "trial", "row_id", "pi", (1 / (F.lit(float(r)) * F.col("pi"))).alias("w"))


def compression(draws: DataFrame) -> DataFrame:
    """iteration, q, distinct, zeta = q / distinct."""
    return draws.groupBy("iteration").agg(F.count("*").alias("q"), F.count_distinct("block_id").alias("distinct_blocks")).withColumn("zeta", F.col("q") / F.col("distinct_blocks"))


def expected_distinct(dist: DataFrame, q: int) -> DataFrame:
    """Expected number of distinct blocks of q draws with replacement."""
    return dist.agg(F.sum(1 - F.pow(1 - F.col("p"), q)).alias("expected"))


def expected_distinct_fastest(counts: DataFrame, q: int) -> DataFrame:
    """The same for the q fastest of m replicas: 1 - C(m - r, q) / C(m, q), as a product of q factors."""
    m = counts.agg(F.sum("r").cast("long").alias("m"))
    miss = F.aggregate(F.sequence(F.lit(0), F.lit(q - 1)), F.lit(1.0), lambda s, i: s * F.greatest(F.lit(0.0), (F.col("m") - F.col("r") - i) / (F.col("m") - i)))
    return counts.crossJoin(F.broadcast(m)).agg(F.sum(1 - miss).alias("expected"))


def hit_probability(dist: DataFrame, q: int) -> DataFrame:
    """h = 1 - (1 - p)^q, with its bounds q p and alpha q / K."""
    top = F.max("p").over(Window.partitionBy())
    return dist.select("block_id", (1 - F.pow(1 - F.col("p"), q)).alias("h"), (q * F.col("p")).alias("linear"), (q * top).alias("uniform_bound"))


def sketched_stats(stats: DataFrame, weights_: DataFrame, d: int, by: tuple[str, ...] = ("iteration",)) -> DataFrame:
    """``by``, gram, atb, btb of the sketch: weighted sums of K-row statistics."""
    both = stats.join(small(weights_), "block_id")
    m = len(packed(d))
    sums = both.groupBy(*by).agg(*[F.sum(F.col("w") * F.get("gram", F.lit(k))).alias(f"g{k}") for k in range(m)], *[F.sum(F.col("w") * F.get("atb", F.lit(k))).alias(f"c{k}") for k in range(d)], F.sum(F.col("w") * F.col("btb")).alias("btb"))
    return sums.select(*by, F.array(*[f"g{k}" for k in range(m)]).alias("gram"), F.array(*[f"c{k}" for k in range(d)]).alias("atb"), "btb")


def with_label(total: Total) -> np.ndarray:
    """Gram matrix of [A | b]."""
    c = total.atb[:, None]
    return np.block([[total.gram, c], [c.T, np.array([[total.btb]])]])


def embedding_error(total: Total, sketched: Sequence, d: int, augmented: bool = True) -> list[float]:
    """||I - U'S'SU||_2 of each sketched statistics row, on the basis of [A | b] or of A."""
    base = with_label(total) if augmented else total.gram
    values, vectors = np.linalg.eigh(base)
    keep = values > 1e-12 * max(values.max(), 1e-300)
    half = vectors[:, keep] / np.sqrt(values[keep])
    out = []
    for r in sketched:
        one = Total(unpack(r["gram"], d), np.array(r["atb"]), r["btb"], 0)
        m = half.T @ (with_label(one) if augmented else one.gram) @ half
        out.append(float(np.abs(np.linalg.eigvalsh(np.eye(len(m)) - m)).max()))
    return out


def embedding_ratio(design: DataFrame, weights_: DataFrame, probes: Sequence[Sequence[float]]) -> DataFrame:
    """iteration, probe, ratio = ||S A x||^2 / ||A x||^2 for given vectors, straight from the rows."""
    squares = [F.pow(dot(F.col("features"), x), 2) for x in probes]
    full = design.agg(*[F.sum(s).alias(f"f{i}") for i, s in enumerate(squares)])
    part = design.join(small(weights_), "block_id").groupBy("iteration").agg(*[F.sum(F.col("w") * s).alias(f"s{i}") for i, s in enumerate(squares)])
    both = part.crossJoin(F.broadcast(full))  # one row
    ratios = F.array(*[F.struct(F.lit(i).alias("probe"), (F.col(f"s{i}") / F.col(f"f{i}")).alias("ratio")) for i in range(len(probes))])
    return both.select("iteration", F.explode(ratios).alias("x")).select("iteration", "x.probe", "x.ratio")


def trials_needed(d: int, eps: float, delta: float, beta: float = 1.0, tau: int = 1, form: str = "proved") -> int:
    """Draws for an embedding with failure chance delta.

    ``proved``: from the matrix tail bound with gamma = 1 + d/beta and variance
    d/beta - 1; ``printed``: the printed asymptotic form with constant 1, which
    divides by the block size as well and is kept for comparison only.
    """
    if not (0 < eps < 1 and 0 < delta < 1 and 0 < beta <= 1):
        raise ValueError("eps, delta in (0, 1), beta in (0, 1]")
    if form == "proved":
        return math.ceil(2 * (d / beta - 1 + (1 + d / beta) * eps / 3) / eps**2 * math.log(2 * d / delta))
    if form == "printed":
        return math.ceil(d / tau * math.log(2 * d / delta) / (beta * eps**2))
    raise ValueError("form is 'proved' or 'printed'")


def failure_bound(d: int, q: int, eps: float, beta: float = 1.0) -> float:
    """Chance that q draws miss eps, by the same tail bound (at most 1)."""
    return min(1.0, 2 * d * math.exp(-q * eps**2 / (2 * (d / beta - 1 + (1 + d / beta) * eps / 3))))


def mean_weights(weights_: DataFrame, iterations: int) -> DataFrame:
    """block_id, mean_weight over real draws: 1 in expectation, as E[S'S] = I says for every block."""
    return weights_.groupBy("block_id").agg((F.sum("w") / F.lit(float(iterations))).alias("mean_weight"))


def sketch_dims(n: int, k: int, q: int, m: int) -> dict[str, float]:
    """Rows of the sketch, share of the rows, and share of late workers."""
    tau = -(-n // k)
    return {"tau": tau, "rows": q * tau, "share": q * tau / n, "late_share": (m - q) / m}


__all__ = [n for n in dir() if not n.startswith("_") and n not in ("add", "annotations")]
