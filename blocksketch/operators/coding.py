"""Coding baselines: no coding, exact group coding, optimal decoding, uniform replication."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from blocksketch.operators import network, scores
from blocksketch.plans.rewrites import small


def uncoded(partials: DataFrame, responses: DataFrame | None = None) -> DataFrame:
    """iteration, g: waits for every block, or (with responses) sums whatever came, uncorrected."""
    if responses is None:
        return partials.select(F.posexplode("g").alias("i", "v")).groupBy("i").agg(F.sum("v").alias("v")).agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "v"))), lambda x: x["v"]).alias("g")).select(F.lit(0).alias("iteration"), "g")
    came = responses.select("iteration", "block_id").distinct()
    flat = partials.join(came, "block_id").select("iteration", F.posexplode("g").alias("i", "v"))
    return flat.groupBy("iteration", "i").agg(F.sum("v").alias("v")).groupBy("iteration").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "v"))), lambda x: x["v"]).alias("g"))


def group_code(spark: SparkSession, m: int, q: int) -> DataFrame:
    """server_id, group_id: fractional repetition; any q of m replies hold every group.

    Needs (m - q + 1) to divide m; a group's servers all compute the same blocks.
    """
    size = m - q + 1
    if not 0 < q <= m or m % size:
        raise ValueError("m - q + 1 must divide m")
    return spark.range(m).select(F.col("id").cast("int").alias("server_id"), F.floor(F.col("id") / size).cast("int").alias("group_id"))


def group_decode(partials: DataFrame, code: DataFrame, replies: DataFrame, blocks_per_group: int) -> DataFrame:
    """iteration, g: one reply of each group, summed; exact for any q replies."""
    w = Window.partitionBy("iteration", "group_id").orderBy("server_id")
    first = replies.join(small(code), "server_id").withColumn("r", F.row_number().over(w)).where("r = 1").select("iteration", "group_id")
    of_group = partials.withColumn("group_id", F.floor(F.col("block_id") / blocks_per_group).cast("int"))
    flat = of_group.join(small(first), "group_id").select("iteration", F.posexplode("g").alias("i", "v"))
    return flat.groupBy("iteration", "i").agg(F.sum("v").alias("v")).groupBy("iteration").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "v"))), lambda x: x["v"]).alias("g"))


def replies_needed(m: int, q: int) -> int:
    """Copies of each block without which some q replies lack it."""
    return m - q + 1


def optimal_decode(code: np.ndarray, replies: Sequence[int]) -> np.ndarray:
    """Weights of the replies that come closest to the all-ones row: 1 pinv(G_I)."""
    part = np.asarray(code, float)[list(replies)]
    return np.ones(part.shape[1]) @ np.linalg.pinv(part)


def code_matrix(code: DataFrame, m: int, k: int) -> np.ndarray:
    """The m x k matrix of a code given as rows server_id, block_id, c (m k numbers: metadata)."""
    out = np.zeros((m, k))
    for r in code.collect():
        out[r["server_id"], r["block_id"]] = r["c"]
    return out


def replies_by_iteration(replies: DataFrame) -> dict[int, list[int]]:
    """The servers that came in each iteration (at most m an iteration: metadata)."""
    out: dict[int, list[int]] = {}
    for r in replies.select("iteration", "server_id").collect():
        out.setdefault(r["iteration"], []).append(r["server_id"])
    return {i: sorted(v) for i, v in out.items()}


def decode_replies(partials: DataFrame, code: DataFrame, replies: DataFrame) -> DataFrame:
    """iteration, g: what came, weighted to lie closest to the sum of all blocks.

    The weights of an iteration are a small least-squares problem on the
    driver; a server's message is the sum of its blocks' gradients by the code,
    so the decoded gradient is one join of blocks with (server, weight) rows.
    """
    size = code.agg(F.max("server_id").alias("m"), F.max("block_id").alias("k")).first()
    matrix = code_matrix(code, size["m"] + 1, size["k"] + 1)
    rows = []
    for iteration, came in replies_by_iteration(replies).items():
        rows += [(iteration, s, float(a)) for s, a in zip(came, optimal_decode(matrix, came), strict=True)]
    weights = code.sparkSession.createDataFrame(rows, "iteration int, server_id int, a double")
    each = code.join(small(weights), "server_id").groupBy("iteration", "block_id").agg(F.sum(F.col("a") * F.col("c")).alias("w"))
    flat = partials.join(small(each), "block_id").select("iteration", F.posexplode("g").alias("i", "v"), "w")
    return flat.groupBy("iteration", "i").agg(F.sum(F.col("w") * F.col("v")).alias("v")).groupBy("iteration").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "v"))), lambda x: x["v"]).alias("g"))


def decoding_error(code: np.ndarray, replies: Sequence[int]) -> float:
    """||I - pinv(G_I) G_I||: 0 if the replies span all blocks, else 1."""
    part = np.asarray(code, float)[list(replies)]
    return float(np.linalg.norm(np.eye(part.shape[1]) - np.linalg.pinv(part) @ part, 2))


def decoded_gradient_bound(code: np.ndarray, replies: Sequence[int], partials: np.ndarray) -> tuple[float, float]:
    """(error of the decoded gradient, its bound sqrt(K) err ||stacked partials||)."""
    a = optimal_decode(code, replies)
    part = np.asarray(code, float)[list(replies)]
    error = float(np.linalg.norm(partials.sum(0) - a @ part @ partials))
    k = part.shape[1]
    return error, float(np.sqrt(k) * decoding_error(code, replies) * np.linalg.norm(partials))


def uniform_code(spark: SparkSession, k: int, m: int) -> DataFrame:
    """Equal shares of m servers; late ones are ignored and the rest scaled by 1/q."""
    return network.apportion_exact(scores.uniform_scores(spark, k), m)


def uniform_code_of(design: DataFrame, m: int) -> DataFrame:
    """The same for the blocks of a design."""
    return network.apportion_exact(scores.uniform_scores_of(design), m)


def uniform_decode(partials: DataFrame, replies: DataFrame, k: int, q: int) -> DataFrame:
    """iteration, g: the gradients of the q replies, each over q times the equal share 1/k."""
    times = replies.groupBy("iteration", "block_id").agg((F.count("*") * F.lit(k / q)).alias("w"))
    flat = partials.join(small(times), "block_id").select("iteration", F.posexplode("g").alias("i", "v"), "w")
    return flat.groupBy("iteration", "i").agg(F.sum(F.col("w") * F.col("v")).alias("v")).groupBy("iteration").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "v"))), lambda x: x["v"]).alias("g"))


def decode_cost(spark: SparkSession, q: int, k: int, d: int, m: int) -> DataFrame:
    """Operations at the master and copies stored, per scheme."""
    rows = [("uncoded", k * d, 0, 1.0), ("group code", (m // replies_needed(m, q)) * d, 0, float(replies_needed(m, q))), ("optimal decoding", q * d, q * k * min(q, k), m / k), ("leverage replicas", q * d, 0, m / k)]
    return spark.createDataFrame(rows, "scheme string, additions long, solve long, copies double")
