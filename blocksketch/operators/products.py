"""Sampled matrix products, CUR and column choice: other uses of the same draws."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from blocksketch.operators import network, sampling, scores
from blocksketch.operators.stats import Total
from blocksketch.plans.rewrites import small


def product_scores(a: DataFrame, b: DataFrame, la: int, lb: int) -> DataFrame:
    """p proportional to ||A_i||_F ||B_i||_F per block: least variance."""
    norm = lambda df, d, name: df.groupBy("block_id").agg(F.sqrt(F.sum(sum((F.pow(F.get("features", F.lit(i)), 2) for i in range(d)), F.lit(0.0)))).alias(name))
    both = norm(a, la, "x").join(norm(b, lb, "y"), "block_id")
    return scores.normalise(both.select("block_id", (F.col("x") * F.col("y")).alias("score")))


def block_products(a: DataFrame, b: DataFrame, la: int, lb: int) -> DataFrame:
    """block_id, i, j, v of A_l' B_l; rows meet on row_id, sums are combined before the shuffle."""
    both = a.select("row_id", "block_id", F.col("features").alias("fa")).join(b.select("row_id", F.col("features").alias("fb")), "row_id")
    sums = both.groupBy("block_id").agg(*[F.sum(F.get("fa", F.lit(i)) * F.get("fb", F.lit(j))).alias(f"p{i}_{j}") for i in range(la) for j in range(lb)])
    cells = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j"), F.col(f"p{i}_{j}").alias("v")) for i in range(la) for j in range(lb)])
    return sums.select("block_id", F.explode(cells).alias("x")).select("block_id", "x.i", "x.j", "x.v")


def cr_product(a: DataFrame, b: DataFrame, la: int, lb: int, q: int, seed: int, iterations: int = 1, dist: DataFrame | None = None) -> DataFrame:
    """iteration, i, j, v: A'B from q drawn blocks, each over q p; reads the drawn blocks only."""
    dist = dist if dist is not None else product_scores(a, b, la, lb)
    w = sampling.weights(sampling.draw_blocks(dist, q, iterations, seed), q)
    drawn = small(w.select("block_id").distinct())
    parts = block_products(a.join(drawn, "block_id", "left_semi"), b, la, lb)
    return parts.join(small(w), "block_id").groupBy("iteration", "i", "j").agg(F.sum(F.col("w") * F.col("v")).alias("v"))


def exact_product(a: DataFrame, b: DataFrame, la: int, lb: int) -> DataFrame:
    return block_products(a, b, la, lb).groupBy("i", "j").agg(F.sum("v").alias("v"))


def coded_cr(a: DataFrame, b: DataFrame, la: int, lb: int, m: int, responses_law: DataFrame, q: int, seed: int) -> DataFrame:
    """The same with replicas on a network: the q fastest servers' blocks, scaled by their own shares."""
    counts = network.apportion_exact(product_scores(a, b, la, lb), m)
    replies = network.simulate_responses(network.allocate(counts), responses_law, 1, seed)
    share = small(counts.select("block_id", (F.col("r") / F.lit(float(m))).alias("p")))
    w = sampling.weights(sampling.draw_fastest(replies, q).join(share, "block_id"), q)
    return block_products(a, b, la, lb).join(small(w), "block_id").groupBy("i", "j").agg(F.sum(F.col("w") * F.col("v")).alias("v"))


def sketched_product(a: DataFrame, b: DataFrame, sketch) -> np.ndarray:
    """(SA)'(SB) for any sketch given as a function design -> sketch rows with the same S."""
    left = {r["sketch_row"]: r["features"] for r in sketch(a).collect()}  # r rows
    right = {r["sketch_row"]: r["features"] for r in sketch(b).collect()}
    keys = sorted(left)
    return np.array([left[k] for k in keys]).T @ np.array([right[k] for k in keys])


def column_leverage(total: Total, rank: int) -> np.ndarray:
    """Leverage of each column within the best rank-``rank`` subspace."""
    values, vectors = np.linalg.eigh(total.gram)
    top = vectors[:, np.argsort(values)[::-1][:rank]]
    return (top**2).sum(1)


def select_columns(total: Total, rank: int, c: int) -> list[int]:
    """The c columns of largest leverage, ties to the lower index."""
    return [int(i) for i in np.argsort(-column_leverage(total, rank), kind="stable")[:c]]


def cur(rows: DataFrame, total: Total, rank: int, c: int, r: int) -> tuple[list[int], list[list[float]], np.ndarray]:
    """Columns, rows and the middle matrix of A ~ C U R; rows are those of largest leverage.

    ``rows`` carries leverage; U = pinv(C) A pinv(R) is formed from C'C and C'A,
    which are parts of the Gram matrix, so A is not read again.
    """
    columns = select_columns(total, rank, c)
    top = rows.orderBy(F.col("leverage").desc(), "row_id").limit(r).select("features").collect()
    picked = np.array([x["features"] for x in top])
    ctc, cta = total.gram[np.ix_(columns, columns)], total.gram[columns]
    return columns, picked.tolist(), np.linalg.pinv(ctc) @ cta @ np.linalg.pinv(picked)


def cur_error(total: Total, columns: list[int], picked: list[list[float]], u: np.ndarray) -> float:
    """||A - C U R||_F from the Gram matrix."""
    m = np.zeros((len(total.gram), len(total.gram)))
    m[columns] = u @ np.array(picked)
    e = np.eye(len(m)) - m
    return float(np.sqrt(max(0.0, np.trace(e.T @ total.gram @ e))))


def top_rows(rows: DataFrame, k: int) -> DataFrame:
    """The k rows of largest leverage in each block."""
    w = Window.partitionBy("block_id").orderBy(F.col("leverage").desc(), "row_id")
    return rows.withColumn("place", F.row_number().over(w)).where(F.col("place") <= k)
