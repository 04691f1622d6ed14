"""SQL surface: functions, aggregates and table functions registered under ``bs_`` names."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def gram_udaf(features: pd.Series) -> list:
    """Packed upper triangle of the Gram matrix of a group's rows."""
    if not len(features):
        return []
    x = np.array(features.tolist())
    g = x.T @ x
    return g[np.triu_indices(len(g))].tolist()


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def solve_udf(gram: pd.Series, atb: pd.Series) -> pd.Series:
    """Least-squares solution of each row's normal equations."""

    def one(g: np.ndarray, c: np.ndarray) -> list:
        d = len(c)
        m = np.zeros((d, d))
        m[np.triu_indices(d)] = g
        m = m + m.T - np.diag(np.diag(m))
        return np.linalg.lstsq(m, np.array(c), rcond=None)[0].tolist()

    return pd.Series([one(np.array(g), c) for g, c in zip(gram, atb, strict=True)])


@F.udtf(returnType="trial int, block_id int")
class DrawBlocks:
    """bs_draw(k, q, seed): q hashed uniform draws of k blocks."""

    def eval(self, k: int, q: int, seed: int) -> Iterator[tuple[int, int]]:
        import hashlib

        for trial in range(q):
            u = int(hashlib.md5(f"{seed}|0|{trial}".encode()).hexdigest()[:8], 16) / 4294967296.0
            yield trial, int(u * k)


@F.udtf(returnType="block_id int, r long")
class Replicas:
    """bs_replicas(p, m): counts of m servers by whole shares, then largest remainders; blocks from 0."""

    def eval(self, p: list, m: int) -> Iterator[tuple[int, int]]:
        whole = [int(v * m + 1e-12) for v in p]
        order = sorted(range(len(p)), key=lambda i: (whole[i] - p[i] * m, i))
        more = set(order[: m - sum(whole)])
        for i, r in enumerate(whole):
            yield i, r + (i in more)


def register(spark: SparkSession) -> None:
    """Registers bs_dot, bs_hash_uniform, bs_gram, bs_solve and the table functions bs_draw and bs_replicas."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION bs_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, v) -> s + v)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION bs_axpy(c DOUBLE, a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE> RETURN zip_with(a, b, (x, y) -> c * x + y)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION bs_hash_uniform(s STRING) RETURNS DOUBLE RETURN cast(conv(substring(md5(s), 1, 8), 16, 10) AS BIGINT) / 4294967296D")
    spark.udf.register("bs_gram", gram_udaf)
    spark.udf.register("bs_solve", solve_udf)
    spark.udtf.register("bs_draw", DrawBlocks)
    spark.udtf.register("bs_replicas", Replicas)
