"""Accuracy and cost measures of runs, sketches and designs."""

from __future__ import annotations

import math
import time
import uuid
from collections.abc import Iterator, Sequence
from contextlib import contextmanager

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blocksketch.functions.core import dot
from blocksketch.operators.descent import Trace
from blocksketch.operators.stats import Total


def distance(x: str, target: Sequence[float]):
    """Euclidean distance of an array column to a vector."""
    held = F.array(*[F.lit(float(v)) for v in target])
    return F.sqrt(F.aggregate(F.zip_with(x, held, lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v))


def log_residual(trace: DataFrame, target: Sequence[float], n: int) -> DataFrame:
    """mean log10(||x* - x||_2 / sqrt(N)) over runs, at each run's last iterate."""
    last = trace.groupBy("run").agg(F.max_by("x", "s").alias("x"))
    return last.agg(F.avg(F.log10(distance("x", target) / F.lit(math.sqrt(n)))).alias("log_residual"))


def convergence(trace: DataFrame, target: Sequence[float], n: int) -> DataFrame:
    """run, s, log_residual: the curve."""
    return trace.select("run", "s", F.log10(distance("x", target) / F.lit(math.sqrt(n))).alias("log_residual"))


def objective_ratio(design: DataFrame, x: Sequence[float], best: Sequence[float]) -> DataFrame:
    """||Ax - b|| / ||Ax* - b|| in one scan."""
    e = lambda v: F.sum(F.pow(dot(F.col("features"), v) - F.col("label"), 2))
    return design.agg((F.sqrt(e(x)) / F.sqrt(e(best))).alias("ratio"))


def solution_bounds(eps: float) -> dict[str, float]:
    """What an embedding error eps on [A | b] allows: objective ratio, and in-span error over ||b_perp||."""
    return {"ratio": math.sqrt((1 + eps) / (1 - eps)), "ratio_printed": (1 + eps) / (1 - eps), "in_span": eps / (1 - eps)}


def in_span_error(design: DataFrame, x: Sequence[float], best: Sequence[float]) -> DataFrame:
    """||A(x* - x)|| and ||b_perp|| = ||Ax* - b|| in one scan."""
    gap = [float(a) - float(b) for a, b in zip(best, x, strict=True)]
    return design.agg(F.sqrt(F.sum(F.pow(dot(F.col("features"), gap), 2))).alias("in_span"), F.sqrt(F.sum(F.pow(dot(F.col("features"), best) - F.col("label"), 2))).alias("b_perp"))


def gradient_error_bound(total: Total, x: np.ndarray, eps: float) -> float:
    """2 eps ||A|| ||Ax - b||, with eps measured on [A | b]."""
    return 2 * eps * total.spectrum()["sigma_max"] * math.sqrt(max(0.0, total.objective(x)))


def decay_slope(values: Sequence[float]) -> float:
    """Least-squares slope of log value against log position: -1/2 or steeper for a vanishing regret."""
    v = np.array([x for x in values if x > 0])
    s = np.log(np.arange(1, len(v) + 1))
    return float(np.polyfit(s, np.log(v), 1)[0])


def regret(total: Total, trace: Trace, best: np.ndarray) -> list[float]:
    """Mean excess objective up to each step."""
    excess = [total.objective(x) - total.objective(best) for x in trace.xs[1:]]
    return list(np.cumsum(excess) / np.arange(1, len(excess) + 1))


def bias_and_variance(gradients: np.ndarray, full: np.ndarray) -> tuple[float, float]:
    """(distance of the mean from the full gradient, mean squared distance from the mean)."""
    mean = gradients.mean(0)
    return float(np.linalg.norm(mean - full)), float(((gradients - mean) ** 2).sum(1).mean())


def prediction_error(design: DataFrame, x: Sequence[float], planted: Sequence[float]) -> DataFrame:
    """Mean squared error of predictions against the planted vector."""
    gap = [float(a) - float(b) for a, b in zip(x, planted, strict=True)]
    return design.agg(F.avg(F.pow(dot(F.col("features"), gap), 2)).alias("prediction_error"))


def prediction_floor(sigma: float, d: int, r: int, n: int) -> float:
    """No estimate from r rows does better: sigma^2 d / min(r, N)."""
    return sigma**2 * d / min(r, n)


def costs(trace: Trace, q: int, d: int, waits: Sequence[float] = ()) -> dict[str, float]:
    """Files, rows and blocks read, master additions and simulated waiting time of a run."""
    read = [c for c in trace.costs if c]
    summed = {k: sum(c.get(k, 0) for c in read) for k in ("files_read", "rows_read", "blocks_read")}
    return {"iterations": len(trace.xs) - 1, **summed, "master_additions": q * d * (len(trace.xs) - 1), "waited": float(sum(waits))}


@contextmanager
def measured_jobs(spark: SparkSession) -> Iterator[dict[str, float]]:
    """Counts the Spark jobs and the seconds of what runs inside, as Spark's own tracker saw them."""
    group, began, seen = f"measured-{uuid.uuid4().hex}", time.perf_counter(), {}
    spark.sparkContext.setJobGroup(group, "measured")
    try:
        yield seen
    finally:
        seen |= {"jobs": len(spark.sparkContext.statusTracker().getJobIdsForGroup(group)), "seconds": time.perf_counter() - began}
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)


def waiting_times(replies: DataFrame, q: int) -> DataFrame:
    """iteration, waited: the time of the q-th reply."""
    return replies.groupBy("iteration").agg(F.element_at(F.array_sort(F.collect_list("t")), q).alias("waited"))
