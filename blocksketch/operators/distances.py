"""How far replica counts and approximate scores are from the wanted distribution.

Inputs are K-row tables: ``block_id, p`` and ``block_id, r``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def _pair(p: DataFrame, q: DataFrame, name: str) -> DataFrame:
    left = p.select("block_id", F.col("p").alias("a"))
    right = q.select("block_id", F.col(name).cast("double").alias("b"))
    return left.join(right, "block_id", "full").select("block_id", F.coalesce("a", F.lit(0.0)).alias("a"), F.coalesce("b", F.lit(0.0)).alias("b"))


def distortion(p: DataFrame, counts: DataFrame) -> DataFrame:
    """d: mean absolute gap between p and the counts' shares."""
    total = counts.agg(F.sum("r").cast("double").alias("_total"))
    both = _pair(p, counts, "r").crossJoin(F.broadcast(total))  # one row
    return both.agg(F.avg(F.abs(F.col("a") - F.col("b") / F.col("_total"))).alias("d"))


def channel_distortion(p: DataFrame, counts: DataFrame, phi: float) -> DataFrame:
    """Delta: mean absolute gap between p and the chance of at least one reply, 1 - phi**r."""
    return _pair(p, counts, "r").agg(F.avg(F.abs(F.col("a") - (1 - F.pow(F.lit(phi), F.col("b"))))).alias("delta"))


def misestimation(p: DataFrame, approx: DataFrame) -> DataFrame:
    """beta = least approx/p over p > 0 (what the guarantees use), and the printed inverse ratio."""
    both = _pair(p, approx, "p").where("a > 0")
    return both.agg(F.least(F.lit(1.0), F.min(F.col("b") / F.col("a"))).alias("beta"), F.least(F.lit(1.0), F.min(F.when(F.col("b") > 0, F.col("a") / F.col("b")))).alias("beta_printed"))


def additive_error(p: DataFrame, approx: DataFrame) -> DataFrame:
    """Largest absolute gap."""
    return _pair(p, approx, "p").agg(F.max(F.abs(F.col("a") - F.col("b"))).alias("error"))


def rounding_loss(ideal: DataFrame, phi: float) -> DataFrame:
    """What rounding the real counts rho to r costs against the channel, with two bounds.

    ``ideal`` has block_id, rho, r.  ``gap`` is the mean |phi**r - phi**rho|;
    ``per_block`` bounds each term by its own smaller exponent; ``printed``
    uses the largest factor of any block for all.
    """
    term = F.pow(F.lit(phi), F.least("r", "rho"))
    step = 1 - F.lit(phi) ** 0.5
    return ideal.agg(
        F.avg(F.abs(F.pow(F.lit(phi), F.col("r")) - F.pow(F.lit(phi), F.col("rho")))).alias("gap"),
        (step * F.avg(term)).alias("per_block"),
        (step * F.max(term)).alias("printed"),
    )


def rounding_bounds(p: DataFrame, counts: DataFrame) -> DataFrame:
    """Bounds of d from the whole parts of the gaps |m p - r|, with d between them."""
    total = counts.agg(F.sum("r").cast("double").alias("m"))
    both = _pair(p, counts, "r").crossJoin(F.broadcast(total)).withColumn("gap", F.abs(F.col("m") * F.col("a") - F.col("b")))
    return both.agg((F.min(F.floor("gap")) / F.first("m")).alias("lower"), F.avg(F.col("gap") / F.col("m")).alias("d"), (F.max(F.ceil("gap")) / F.first("m")).alias("upper"))


def expanded_uniformity(p: DataFrame, counts: DataFrame) -> DataFrame:
    """Shares of single replicas after expansion, p / (R share): uniform where counts match p."""
    total = counts.agg(F.sum("r").cast("double").alias("m"))
    both = _pair(p, counts, "r").crossJoin(F.broadcast(total)).where("b > 0")
    share = F.col("a") / (F.col("m") * (F.col("b") / F.col("m")))
    beta = F.least(F.lit(1.0), F.min((F.col("b") / F.col("m")) / F.when(F.col("a") > 0, F.col("a"))))
    return both.withColumn("share", share).agg(F.max(F.abs(F.col("share") - 1 / F.col("m"))).alias("gap"), (1 / (F.first("m") * beta)).alias("bound"))
