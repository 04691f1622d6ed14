"""Joins and roll-ups around designs: as-of and interval joins, statistics over grouping sets."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blocksketch.operators.stats import packed


def asof_join(left: DataFrame, right: DataFrame, on: str, by: Sequence[str], values: Sequence[str]) -> DataFrame:
    """Each left row with the last right row of its group at or before its time.

    Both sides are unioned and carried forward in one window per group, so no
    pair of rows is formed; a hot group costs one sorted pass.
    """
    keys = [*by, on]
    nulls = [F.lit(None).cast(right.schema[v].dataType).alias(f"_r_{v}") for v in values]
    a = left.select(*keys, F.lit(1).alias("_side"), F.struct(*left.columns).alias("_l"), *nulls)
    b = right.select(*keys, F.lit(0).alias("_side"), F.lit(None).cast(a.schema["_l"].dataType).alias("_l"), *[F.col(v).alias(f"_r_{v}") for v in values])
    w = Window.partitionBy(*by).orderBy(on, "_side").rowsBetween(Window.unboundedPreceding, 0)
    carried = a.unionByName(b).select("_side", "_l", *[F.last(f"_r_{v}", ignorenulls=True).over(w).alias(v) for v in values])
    return carried.where("_side = 1").select("_l.*", *values)


def interval_join(points: DataFrame, spans: DataFrame, at: str, lo: str, hi: str, width: float) -> DataFrame:
    """Points inside [lo, hi): an equi-join on bins of ``width``, then the exact condition."""
    spread = spans.withColumn("_bin", F.explode(F.sequence(F.floor(F.col(lo) / width).cast("long"), F.floor(F.col(hi) / width).cast("long"))))
    binned = points.withColumn("_bin", F.floor(F.col(at) / width).cast("long"))
    return binned.join(spread, "_bin").where((F.col(at) >= F.col(lo)) & (F.col(at) < F.col(hi))).drop("_bin")


def grouped_stats(design: DataFrame, d: int, sets: str, *by: str) -> DataFrame:
    """Gram sums over ``rollup``, ``cube`` or plain groups: statistics add, so scores roll up."""
    at = [F.get("features", F.lit(i)) for i in range(d)]
    grouped = {"rollup": design.rollup, "cube": design.cube, "group": design.groupBy}[sets](*by)
    return grouped.agg(F.count("*").alias("n"), *[F.sum(at[i] * at[j]).alias(f"g{i}{j}") for i, j in packed(d)])


def salted_sum(df: DataFrame, key: str, value: str, salts: int = 16) -> DataFrame:
    """Two-step sum for hot keys: by (key, salt), then by key."""
    part = df.groupBy(key, F.pmod(F.xxhash64(*df.columns), F.lit(salts)).alias("_salt")).agg(F.sum(value).alias("_s"), F.count("*").alias("_n"))
    return part.groupBy(key).agg(F.sum("_s").alias("total"), F.sum("_n").alias("n"))
