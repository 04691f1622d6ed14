"""Leverage scores of rows and blocks, exact and approximate, and other block scores.

A score table is ``block_id, score, p`` with p summing to 1.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from blocksketch.functions.core import add, dot, hash_int, hash_normal, hash_uniform, quadratic
from blocksketch.operators.stats import MOST_SQL_COLUMNS, Total, block_stats, collect_total, packed, tsqr
from blocksketch.sources.tables import stored


def _row_norms(design: DataFrame, half: np.ndarray, name: str) -> DataFrame:
    """Adds ||a . half||^2 of every row; the small matrix travels in the plan."""
    d = len(half)
    if d <= MOST_SQL_COLUMNS:
        return design.withColumn(name, quadratic(F.col("features"), (half @ half.T).tolist()))
    schema = T.StructType([*design.schema.fields, T.StructField(name, T.DoubleType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = batch.column(batch.schema.get_field_index("features")).flatten().to_numpy().reshape(-1, d) if batch.num_rows else np.zeros((0, d))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(((rows @ half) ** 2).sum(1))], [*batch.schema.names, name])

    return design.mapInArrow(run, schema)


def row_leverage(design: DataFrame, d: int, method: str = "gram", total: Total | None = None) -> DataFrame:
    """Adds leverage (squared row norms of an orthonormal basis) and pi, its share.

    ``gram``: two passes over the Gram matrix's pseudo-inverse; ``tsqr``: a
    triangular factor without squaring the condition number.
    """
    if method == "gram":
        total = total or collect_total(block_stats(design, d), d)
        values, vectors = np.linalg.eigh(total.inverse())
        half, rank = vectors * np.sqrt(np.clip(values, 0, None)), total.rank()
    elif method == "tsqr":
        r = tsqr(design, d)
        half = np.linalg.pinv(r, rcond=1e-12)
        rank = int(np.linalg.matrix_rank(r))
    else:
        raise ValueError("method is 'gram' or 'tsqr'")
    return _row_norms(design, half, "leverage").withColumn("pi", F.col("leverage") / F.lit(float(max(rank, 1))))


def block_leverage(stats: DataFrame, d: int, total: Total | None = None) -> DataFrame:
    """Block scores from block statistics alone: tr((A'A)^+ A_l'A_l), in one pass over K rows."""
    total = total or collect_total(stats, d)
    inverse, rank = total.inverse(), max(total.rank(), 1)
    held = [(1.0 if i == j else 2.0) * float(inverse[i, j]) for i, j in packed(d)]
    score = F.greatest(dot(F.col("gram"), held), F.lit(0.0))
    return stats.select("block_id", score.alias("score")).withColumn("p", F.col("score") / F.lit(float(rank)))


def block_leverage_by_rows(design: DataFrame, d: int, method: str = "gram") -> DataFrame:
    """The same by summing row scores: the definition, for checks and for the stable factor."""
    rows = row_leverage(design, d, method)
    return rows.groupBy("block_id").agg(F.sum("leverage").alias("score"), F.sum("pi").alias("p"))


def approx_leverage(design: DataFrame, d: int, sketch_rows: int, jl_dim: int, seed: int = 0, kind: str = "countsketch") -> DataFrame:
    """Approximate block scores: a sketch of the rows gives R, a random projection the norms.

    ``kind`` is the sketch: ``countsketch`` (hashed signed row sums, one pass),
    ``gaussian`` (dense) or ``srht`` (single rows of the Hadamard transform;
    rows numbered from 0).  ``jl_dim`` 0 takes exact row norms.
    """
    from blocksketch.operators import sketches

    made = {"countsketch": lambda: sketches.countsketch(design, d, sketch_rows, seed), "gaussian": lambda: sketches.dense_sketch(design, d, sketch_rows, seed=seed), "srht": lambda: sketches.srht_rows(design, d, sketch_rows, seed)}
    if kind not in made:
        raise ValueError(f"kind is one of {sorted(made)}")
    held = np.array([r["features"] for r in made[kind]().collect()])  # at most sketch_rows rows
    r = np.linalg.qr(held, mode="r")
    rng = np.random.default_rng(seed)
    half = np.linalg.pinv(r) @ (rng.normal(size=(d, jl_dim)) / np.sqrt(jl_dim) if jl_dim else np.eye(d))
    rows = _row_norms(design, half, "leverage")
    return normalise(rows.groupBy("block_id").agg(F.sum("leverage").alias("score")))


def sampled_scores(design: DataFrame, d: int, fraction: float, seed: int = 0) -> DataFrame:
    """Block scores from a hashed sample of rows in each block, scaled by the block's own fraction."""
    u = hash_uniform(f"sample{seed}", F.col("row_id"))
    sample = block_stats(design.where(u < fraction), d)
    sizes = design.groupBy("block_id").agg(F.count("*").alias("rows"))
    scaled = sizes.join(sample, "block_id", "left").select("block_id", F.coalesce("n", F.lit(0)).alias("n"), F.transform(F.coalesce("gram", F.array_repeat(F.lit(0.0), len(packed(d)))), lambda g: g * F.col("rows") / F.greatest(F.coalesce("n", F.lit(0)), F.lit(1))).alias("gram"), F.array_repeat(F.lit(0.0), d).alias("atb"), F.lit(0.0).alias("btb"))
    return normalise(block_leverage(scaled, d).select("block_id", F.greatest("score", F.lit(1e-12)).alias("score")))


def frobenius_scores(stats: DataFrame, d: int) -> DataFrame:
    """Squared Frobenius norms of the blocks: the Gram diagonals."""
    at = [k for k, (i, j) in enumerate(packed(d)) if i == j]
    return normalise(stats.select("block_id", add([F.get("gram", F.lit(k)) for k in at]).alias("score")))


def uniform_scores(spark: SparkSession, k: int) -> DataFrame:
    return spark.range(k).select(F.col("id").cast("int").alias("block_id"), F.lit(1.0).alias("score"), F.lit(1.0 / k).alias("p"))


def uniform_scores_of(design: DataFrame) -> DataFrame:
    """The same for the blocks that a design has."""
    blocks = stored(design.select("block_id").distinct(), "blocks")
    return blocks.select("block_id", F.lit(1.0).alias("score"), F.lit(1.0 / max(1, blocks.count())).alias("p"))


def normalise(scores: DataFrame) -> DataFrame:
    """p = score over the sum of scores; equal shares if all are zero. One row per block goes through one task."""
    w = Window.partitionBy()
    total = F.sum("score").over(w)
    return scores.select("block_id", "score", F.when(total > 0, F.col("score") / total).otherwise(1.0 / F.count("*").over(w)).alias("p"))


def rank_blocks(dist: DataFrame) -> DataFrame:
    """Adds position 1..K in ascending order of p, ties by block."""
    return dist.withColumn("position", F.row_number().over(Window.orderBy("p", "block_id")))


def balance(dist: DataFrame) -> DataFrame:
    """alpha = K max p: 1 for uniform scores."""
    return dist.agg((F.count("*") * F.max("p")).alias("alpha"), F.max("p").alias("largest"), F.min("p").alias("smallest"))


def hashed_heavy_tail(row: str = "row_id", seed: str = "tail"):
    """A positive row scale with a heavy tail: root of 2 over a chi-square of two degrees."""
    return F.sqrt(F.lit(2.0) / (-2.0 * F.log((hash_int(seed, F.col(row)) + 1) / F.lit(4294967297.0))))


__all__ = ["approx_leverage", "balance", "block_leverage", "block_leverage_by_rows", "frobenius_scores", "hash_normal", "hashed_heavy_tail", "normalise", "rank_blocks", "row_leverage", "sampled_scores", "uniform_scores"]
