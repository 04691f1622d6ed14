"""Objectives, gradients and Hessians: exact, per block, encoded and sketched.

The gradient carries its factor 2: g = 2 A'(Ax - b).  Parameters travel in the
plan as literals; each task returns one partial sum per group.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blocksketch.functions.core import dot
from blocksketch.operators.stats import packed
from blocksketch.plans.rewrites import small

BY_BLOCK = ("block_id",)


def residual(x: Sequence[float]):
    return dot(F.col("features"), x) - F.col("label")


def objective(design: DataFrame, x: Sequence[float]) -> DataFrame:
    """One row: ||Ax - b||^2."""
    return design.agg(F.sum(F.pow(residual(x), 2)).alias("objective"))


def partial_gradients(design: DataFrame, x: Sequence[float], by: Sequence[str] = BY_BLOCK) -> DataFrame:
    """``by``, g (array): the blocks' own gradients, whose sum is the full one."""
    d = len(x)
    rows = design.withColumn("_e", 2.0 * residual(x))
    sums = rows.groupBy(*by).agg(*[F.sum(F.col("_e") * F.get("features", F.lit(i))).alias(f"g{i}") for i in range(d)])
    return sums.select(*by, F.array(*[f"g{i}" for i in range(d)]).alias("g"))


def gradient(design: DataFrame, x: Sequence[float]) -> DataFrame:
    """One row: g."""
    return partial_gradients(design, x, ())


def encoded_partials(design: DataFrame, x: Sequence[float], encoded: DataFrame) -> DataFrame:
    """Blocks' gradients times scale^2 = 1/(q p): what a worker sends; nothing is left to decode."""
    parts = partial_gradients(design, x)
    return parts.join(small(encoded.select("block_id", "scale")), "block_id").select("block_id", F.transform("g", lambda v: v * F.col("scale") * F.col("scale")).alias("g"))


def sketched_gradient(design: DataFrame, x: Sequence[float], weights: DataFrame, by: Sequence[str] = ("iteration",), step_sums: bool = False) -> DataFrame:
    """``by``, g: the weighted sum over the drawn blocks only.

    ``weights`` (iteration, block_id, w; at most K rows an iteration) is
    broadcast, so blocks that were not drawn are dropped in the scan's stage.
    """
    d = len(x)
    rows = design.join(small(weights), "block_id").withColumn("_e", 2.0 * residual(x) * F.col("w"))
    extra = [F.count("*").alias("rows_read"), F.count_distinct("block_id").alias("blocks_read")] if step_sums else []
    sums = rows.groupBy(*by).agg(*[F.sum(F.col("_e") * F.get("features", F.lit(i))).alias(f"g{i}") for i in range(d)], *extra)
    return sums.select(*by, F.array(*[f"g{i}" for i in range(d)]).alias("g"), *(["rows_read", "blocks_read"] if step_sums else []))


def sketched_hessian(stats: DataFrame, weights: DataFrame, d: int) -> DataFrame:
    """iteration, h (packed): 2 A'S'SA from block statistics."""
    both = stats.join(small(weights), "block_id")
    m = len(packed(d))
    sums = both.groupBy("iteration").agg(*[F.sum(2.0 * F.col("w") * F.get("gram", F.lit(k))).alias(f"h{k}") for k in range(m)])
    return sums.select("iteration", F.array(*[f"h{k}" for k in range(m)]).alias("h"))


def line_sums(design: DataFrame, x: Sequence[float], direction: Sequence[float]) -> DataFrame:
    """One row: <A g, Ax - b> and ||A g||^2, from which the exact step follows."""
    ag = dot(F.col("features"), direction)
    return design.agg(F.sum(ag * residual(x)).alias("along"), F.sum(ag * ag).alias("length"))


def encoded_objective(design: DataFrame, x: Sequence[float], encoded: DataFrame, expanded: bool = False) -> DataFrame:
    """||G(Ax - b)||^2 of the encoded blocks, or of all replicas when ``expanded``."""
    times = F.col("r") if expanded else F.lit(1)
    rows = design.join(small(encoded), "block_id")
    return rows.agg(F.sum(F.col("scale") * F.col("scale") * times * F.pow(residual(x), 2)).alias("objective"))
