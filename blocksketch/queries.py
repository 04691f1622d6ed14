"""Registered queries of the engine, each beside its SQL twin where SQL can express it."""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from blocksketch import fixtures
from blocksketch.fixtures import SQL, SQL_SKETCHED, SQL_STATS, load, sql_draws, sql_path, sql_uniform
from blocksketch.functions.core import rounded
from blocksketch.operators import descent, design, distances, network, sampling, scores, sketches, stats
from blocksketch.operators.stats import Total
from blocksketch.sources.tables import stored, stored_blocks, t_entries, table

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}

Q, SEED, STEPS, M = 10, 7, 6, 60
#: Buckets of the block stores that iterations read.
BUCKETS = 20
#: Fixed values of the published experiments.
ENDINGS = [6, 12, 24, 42, 48, 54, 60]
EXAMPLE = ([3, 3, 4, 5, 5], 20, 3)


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLE_SQL[name] = sql
        return f

    return keep


def with_stats(name: str, *ctes: str, body: str, recursive: bool = False) -> str:
    return f"WITH {'RECURSIVE ' if recursive else ''}" + ",\n".join([SQL[name], SQL_STATS, *ctes]) + "\n" + body


def block_scores(spark: SparkSession, d: str, name: str, keep: bool = False) -> tuple[DataFrame, DataFrame, DataFrame, Total]:
    """design, stored block statistics (K rows), leverage distribution, total.

    ``keep`` stores the design first: for runs that read it in every iteration.
    """
    rows, width = load(spark, d, name), fixtures.WIDTH[name]
    rows = stored(rows, "design") if keep else rows
    held = stored(stats.block_stats(rows, width), "stats")
    total = stats.collect_total(held, width)
    return rows, held, scores.block_leverage(held, width, total), total


def one_row(spark: SparkSession, **values: object) -> DataFrame:
    """A row of scalars that Python computed."""
    kinds = {bool: "boolean", int: "long", float: "double", str: "string"}
    return spark.createDataFrame([tuple(values.values())], ", ".join(f"{k} {kinds[type(v)]}" for k, v in values.items()))


def vector_table(spark: SparkSession, x: np.ndarray, digits: int = 6) -> DataFrame:
    return spark.createDataFrame([(i, float(round(v, digits)) + 0.0) for i, v in enumerate(x)], "i int, v double")


def path_table(spark: SparkSession, trace: descent.Trace, digits: int = 6) -> DataFrame:
    return spark.createDataFrame([(s, *(float(round(v, digits)) + 0.0 for v in x)) for s, x in enumerate(trace.xs)], "s int, a0 double, a1 double, a2 double")


PATH_BODY = "SELECT s::INT AS s, round(a0, 6) + 0.0 AS a0, round(a1, 6) + 0.0 AS a1, round(a2, 6) + 0.0 AS a2 FROM path"
XI = "0.4 / (SELECT g00 + g11 + g22 FROM tot)"


def xi_of(total: Total, share: float = 0.4) -> float:
    return share / float(np.trace(total.gram))


# ---- designs and blocks -------------------------------------------------------------------------------------------


def _design_query(name: str) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        at = [rounded(F.get("features", F.lit(i)), 9).alias(f"x{i}") for i in range(fixtures.WIDTH[name])]
        return load(spark, d, name).select("row_id", "block_id", *at, rounded(F.col("label"), 5).alias("y"))

    return run


for _name, _id in (("lineitem", "b1_design_lineitem"), ("documents", "b2_planted_documents"), ("events", "b1_design_events"), ("star", "b1_design_star_join")):
    _cols = ", ".join(f"round(x{i}, 9) + 0.0 AS x{i}" for i in range(fixtures.WIDTH[_name]))
    query(_id, f"WITH {SQL[_name]} SELECT row_id, block_id, {_cols}, round(y, 5) + 0.0 AS y FROM design")(_design_query(_name))


@query("b3_blocks_contiguous", "SELECT event_id, CASE WHEN p < n % 7 * (n // 7 + 1) THEN p // (n // 7 + 1) ELSE n % 7 + (p - n % 7 * (n // 7 + 1)) // (n // 7) END::INT AS block_id FROM (SELECT event_id, row_number() OVER (ORDER BY event_id) - 1 AS p, count(*) OVER () AS n FROM events)")
def _(spark: SparkSession, d: str) -> DataFrame:
    return design.assign_blocks(load(spark, d, "events"), 7, "contiguous", ("row_id",)).select(F.col("row_id").alias("event_id"), "block_id")


@query("b4_blocks_hash", f"SELECT event_id, ({fixtures.sql_int(chr(39) + 'block' + chr(39), 'event_id')} % 8)::INT AS block_id FROM events")
def _(spark: SparkSession, d: str) -> DataFrame:
    return design.assign_blocks(load(spark, d, "events"), 8, "hash").select(F.col("row_id").alias("event_id"), "block_id")


@query("b4_blocks_key", "SELECT event_id, (event_id % 9)::INT AS block_id FROM events")
def _(spark: SparkSession, d: str) -> DataFrame:
    return design.assign_blocks(load(spark, d, "events"), 9, "key").select(F.col("row_id").alias("event_id"), "block_id")


@query("b4_blocks_window", "SELECT day(ts)::INT AS block_id, count(*)::BIGINT AS n FROM events GROUP BY 1")
def _(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "events").groupBy("block_id").agg(F.count("*").alias("n"))


@query("b5_padded", f"WITH {SQL['documents']}, c AS (SELECT block_id, count(*) AS n, sum(x1) AS s FROM design GROUP BY block_id) SELECT block_id, (SELECT max(n) FROM c)::BIGINT AS n, round(s, 6) + 0.0 AS s FROM c")
def _(spark: SparkSession, d: str) -> DataFrame:
    out = design.pad_blocks(load(spark, d, "documents"), 20, 3)
    return out.groupBy("block_id").agg(F.count("*").alias("n"), rounded(F.sum(F.get("features", F.lit(1))), 6).alias("s"))


@query("b6_sizes_100_7", "WITH c AS (SELECT o_orderstatus, count(o_totalprice) AS n FROM orders GROUP BY 1) SELECT o_orderstatus, range::INT AS block_id, (n // 7 + CASE WHEN range < n % 7 THEN 1 ELSE 0 END)::BIGINT AS n_rows FROM c, range(7)")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Sizes of seven blocks of the orders of each status."""
    return design.block_sizes_of(table(spark, d, "orders").groupBy("o_orderstatus").agg(F.count("o_totalprice").alias("n")), 7).select("o_orderstatus", "block_id", "n_rows")


#: Digits that leave no rounding ties for each view's decimals.
DIGITS = {"lineitem": 5, "documents": 9, "events": 9}


def _gram(n: int) -> str:
    names = [*(f"g{i}{j}" for i, j in fixtures._PAIRS), "c0", "c1", "c2", "btb"]
    return ", ".join(f"round({c}, {n}) + 0.0 AS {c}" for c in names)


def _flat(df: DataFrame, *keep: str, digits: int = 5) -> DataFrame:
    return df.select(*keep, *[rounded(F.get("gram", F.lit(k)), digits).alias(f"g{i}{j}") for k, (i, j) in enumerate(stats.packed(3))], *[rounded(F.get("atb", F.lit(i)), digits).alias(f"c{i}") for i in range(3)], rounded(F.col("btb"), digits).alias("btb"))


for _name in ("lineitem", "documents", "events"):
    query(f"b7_block_stats_{_name}", with_stats(_name, body=f"SELECT block_id, n, {_gram(DIGITS[_name])} FROM stats"))(lambda spark, d, name=_name: _flat(stats.block_stats(load(spark, d, name), 3), "block_id", "n", digits=DIGITS[name]))


@query("b7_block_stats_arrow", with_stats("lineitem", body=f"SELECT block_id, n, {_gram(5)} FROM stats"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return _flat(stats.block_stats(load(spark, d, "lineitem"), 3, engine="arrow"), "block_id", "n")


@query("b8_total_stats", with_stats("lineitem", body=f"SELECT n, {_gram(5)} FROM tot"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return _flat(stats.total_stats(stats.block_stats(load(spark, d, "lineitem"), 3), 3), "n")


@query("b9_spectrum", f"WITH {SQL['events']}, g AS (SELECT count(*) AS a, sum(x1) AS b, sum(x1 * x1) AS c FROM design) SELECT round(sqrt((a + c + sqrt((a - c) * (a - c) + 4 * b * b)) / 2), 5) AS sigma_max, round(sqrt((a + c - sqrt((a - c) * (a - c) + 4 * b * b)) / 2), 5) AS sigma_min, round(sqrt(a + c), 5) AS frobenius, 2::BIGINT AS rank FROM g")
def _(spark: SparkSession, d: str) -> DataFrame:
    two = load(spark, d, "events").withColumn("features", F.slice("features", 1, 2))
    s = stats.collect_total(stats.block_stats(two, 2), 2).spectrum()
    return one_row(spark, sigma_max=round(s["sigma_max"], 5), sigma_min=round(s["sigma_min"], 5), frobenius=round(s["frobenius"], 5), rank=int(s["rank"]))


def _t_sql(d: int) -> str:
    def entry(j: int) -> str:
        chi = f"(-2.0::DOUBLE * ln({sql_uniform(chr(39) + 'chi0' + chr(39), 'i', str(j * 64))} + 1e-12::DOUBLE))"
        return f"round({fixtures.sql_normal(chr(39) + 't0' + chr(39), 'i', str(j))} / sqrt({chi} / 2.0), 6) + 0.0"

    return "SELECT i::BIGINT AS row_id, block_id, " + ", ".join(f"{entry(j)} AS x{j}" for j in range(d)) + ", round(y, 6) + 0.0 AS y FROM (SELECT c_custkey AS i, c_nationkey::INT AS block_id, c_acctbal / 1e4 AS y FROM customer)"


@query("b10_t_matrix", _t_sql(4))
def _(spark: SparkSession, d: str) -> DataFrame:
    """A row of t-distributed entries for every customer, with the nation as block and the balance as label."""
    rows = table(spark, d, "customer").select(F.col("c_custkey").alias("row_id"), F.col("c_nationkey").cast("int").alias("block_id"), (F.col("c_acctbal") / 1e4).alias("label"))
    return t_entries(rows, 4).select("row_id", "block_id", *[rounded(F.get("features", F.lit(j)), 6).alias(f"x{j}") for j in range(4)], rounded(F.col("label"), 6).alias("y"))


# ---- scores -------------------------------------------------------------------------------------------------------

_ROW_LEVERAGE = "i00 * x0 * x0 + 2 * i01 * x0 * x1 + 2 * i02 * x0 * x2 + i11 * x1 * x1 + 2 * i12 * x1 * x2 + i22 * x2 * x2"
for _name in ("documents", "lineitem"):
    query(f"s1_row_leverage_{_name}", with_stats(_name, body=f"SELECT row_id, round({_ROW_LEVERAGE}, 8) + 0.0 AS leverage FROM design, inv"))(lambda spark, d, name=_name: scores.row_leverage(load(spark, d, name), 3).select("row_id", rounded(F.col("leverage"), 8).alias("leverage")))


_DIST = "SELECT block_id, round(p, 8) + 0.0 AS p FROM "


def _p() -> Column:
    return rounded(F.col("p"), 8).alias("p")


for _name in ("lineitem", "documents", "events"):
    query(f"s3_block_leverage_{_name}", with_stats(_name, body=_DIST + "dist"))(lambda spark, d, name=_name: block_scores(spark, d, name)[2].select("block_id", _p()))


@query("s4_block_leverage_rowsum", with_stats("documents", body=f"SELECT block_id, round(sum({_ROW_LEVERAGE}) / 3, 8) + 0.0 AS p FROM design, inv GROUP BY block_id"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return scores.block_leverage_by_rows(load(spark, d, "documents"), 3).select("block_id", _p())


@query("s7_frobenius", with_stats("documents", body="SELECT block_id, round((g00 + g11 + g22) / (SELECT g00 + g11 + g22 FROM tot), 8) + 0.0 AS p FROM stats"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return scores.frobenius_scores(block_scores(spark, d, "documents")[1], 3).select("block_id", _p())


@query("s8_uniform", "SELECT block_id, round(1.0::DOUBLE / count(*) OVER (), 8) AS p FROM (SELECT DISTINCT day(ts)::INT AS block_id FROM events)")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Equal shares of the blocks that the events have."""
    return scores.uniform_scores_of(load(spark, d, "events")).select("block_id", _p())


@query("s9_rank_blocks", with_stats("documents", body="SELECT block_id, row_number() OVER (ORDER BY p, block_id)::INT AS position FROM dist"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return scores.rank_blocks(block_scores(spark, d, "documents")[2]).select("block_id", "position")


@query("s10_degenerate", with_stats("documents", body=_DIST + "dist"))
def _(spark: SparkSession, d: str) -> DataFrame:
    """A repeated column changes no score: the span is what counts."""
    rows = load(spark, d, "documents").withColumn("features", F.concat("features", F.array(F.get("features", F.lit(1)) * 2)))
    return scores.block_leverage(stored(stats.block_stats(rows, 4), "stats"), 4).select("block_id", _p())


@query("s11_balance", with_stats("documents", body="SELECT round(count(*) * max(p), 7) AS alpha, round(max(p), 8) AS largest, round(min(p), 8) AS smallest FROM dist"))
def _(spark: SparkSession, d: str) -> DataFrame:
    r = scores.balance(block_scores(spark, d, "documents")[2])
    return r.select(F.round("alpha", 7).alias("alpha"), F.round("largest", 8).alias("largest"), F.round("smallest", 8).alias("smallest"))


# ---- distances ----------------------------------------------------------------------------------------------------

_COUNTS = f"counts AS (SELECT block_id, p, (floor(p * {M} + 1e-12) + CASE WHEN row_number() OVER (ORDER BY p * {M} - floor(p * {M} + 1e-12) DESC, block_id) <= {M} - sum(floor(p * {M} + 1e-12)) OVER () THEN 1 ELSE 0 END)::BIGINT AS r FROM dist)"
PHI = 0.7


def counted(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    dist = stored(block_scores(spark, d, "documents")[2], "dist")
    return dist, stored(network.apportion_exact(dist, M, 0), "counts")


def _measure(name: str, f: Callable[[DataFrame, DataFrame], DataFrame], body: str, digits: int = 8) -> None:
    def run(spark: SparkSession, d: str) -> DataFrame:
        out = f(*counted(spark, d))
        return out.select(*[rounded(F.col(c), digits).alias(c) for c in out.columns])

    query(name, with_stats("documents", _COUNTS, body=body))(run)


def _share(counts: DataFrame) -> DataFrame:
    return counts.select("block_id", (F.col("r") / F.lit(float(M))).alias("p"))


_measure("m1_distortion", distances.distortion, f"SELECT round(avg(abs(p - r / {M}.0)), 8) + 0.0 AS d FROM counts")
_measure("m2_channel_distortion", lambda p, c: distances.channel_distortion(p, c, PHI), f"SELECT round(avg(abs(p - (1 - pow({PHI}, r)))), 8) + 0.0 AS delta FROM counts")
_measure("m3_misestimation", lambda p, c: distances.misestimation(p, _share(c)), f"SELECT round(least(1.0, min(r / {M}.0 / p)), 8) + 0.0 AS beta, round(least(1.0, min(CASE WHEN r > 0 THEN p / (r / {M}.0) END)), 8) + 0.0 AS beta_printed FROM counts")
_measure("m4_additive_error", lambda p, c: distances.additive_error(p, _share(c)), f"SELECT round(max(abs(p - r / {M}.0)), 8) + 0.0 AS error FROM counts")
_measure("m5_rounding_loss", lambda p, c: distances.rounding_loss(network.replicas_channel(p, PHI), PHI), f"SELECT round(avg(abs(pow({PHI}, r) - pow({PHI}, rho))), 8) + 0.0 AS gap, round((1 - sqrt({PHI})) * avg(pow({PHI}, least(r, rho))), 8) + 0.0 AS per_block, round((1 - sqrt({PHI})) * max(pow({PHI}, least(r, rho))), 8) + 0.0 AS printed FROM (SELECT ln(1 - p) / ln({PHI}) AS rho, floor(ln(1 - p) / ln({PHI}) + 0.5) AS r FROM dist)")
_measure("m6_rounding_bounds", distances.rounding_bounds, f"SELECT round(min(floor(abs({M} * p - r))) / {M}.0, 8) + 0.0 AS lower, round(avg(abs({M} * p - r) / {M}.0), 8) + 0.0 AS d, round(max(ceil(abs({M} * p - r))) / {M}.0, 8) + 0.0 AS upper FROM counts")
_measure("m7_expanded_uniformity", distances.expanded_uniformity, f"SELECT round(max(abs(p / r - 1 / {M}.0)), 8) + 0.0 AS gap, round(1 / ({M} * least(1.0, min(r / {M}.0 / p))), 8) + 0.0 AS bound FROM counts WHERE r > 0")


# ---- draws and sketches -------------------------------------------------------------------------------------------


def drawn(spark: SparkSession, d: str, name: str = "documents", q: int = Q, iterations: int = STEPS, keep: bool = False) -> tuple[DataFrame, DataFrame, DataFrame, Total, DataFrame, DataFrame]:
    rows, held, dist, total = block_scores(spark, d, name, keep)
    dist = stored(dist, "dist")
    draws = stored(sampling.draw_blocks(dist, q, iterations, SEED), "draws")
    return rows, held, dist, total, draws, stored(sampling.weights(draws, q), "weights")


DRAWS = sql_draws(Q, STEPS, SEED)


@query("k1_draws_replacement", with_stats("documents", DRAWS, body="SELECT iteration, trial, block_id FROM draws"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return drawn(spark, d)[4].select("iteration", "trial", "block_id")


REPLIES = f"""law AS (SELECT value AS t, coalesce(lag(cdf) OVER (ORDER BY value), 0.0) AS lo, cdf FROM (SELECT value, sum(count(*)) OVER (ORDER BY value) / sum(count(*)) OVER () AS cdf FROM events GROUP BY value)),
servers AS (SELECT unnest(range((e - r)::BIGINT, e::BIGINT))::INT AS server_id, block_id FROM (SELECT block_id, r, sum(r) OVER (ORDER BY block_id) AS e FROM counts WHERE r > 0)),
replies AS MATERIALIZED (SELECT iteration, server_id, block_id, t FROM (SELECT range::INT AS iteration, server_id, block_id, {sql_uniform(chr(39) + 'reply' + str(SEED) + chr(39), 'range', 'server_id')} AS u FROM servers, range({STEPS})) JOIN law ON u >= lo AND u < cdf)"""
_REPLY_SQL = with_stats("documents", _COUNTS, REPLIES, body="{}")


def replied(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    counts = counted(spark, d)[1]
    law = stored(network.runtime_law(table(spark, d, "events"), "value"), "law")
    return counts, network.simulate_responses(network.allocate(counts), law, STEPS, SEED)


@query("k2_draws_fastest", _REPLY_SQL.format(f"SELECT iteration, trial::INT AS trial, server_id, block_id FROM (SELECT *, row_number() OVER (PARTITION BY iteration ORDER BY t, server_id) - 1 AS trial FROM replies) WHERE trial < {Q}"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return sampling.draw_fastest(replied(spark, d)[1], Q).select("iteration", F.col("trial").cast("int").alias("trial"), "server_id", "block_id")


@query("k3_draws_deadline", _REPLY_SQL.format("SELECT iteration, server_id, block_id, count(*) OVER (PARTITION BY iteration)::BIGINT AS q FROM replies WHERE t <= 24"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return sampling.draw_deadline(replied(spark, d)[1], 24.0).select("iteration", "server_id", "block_id", "q")


@query("k4_poisson", with_stats("documents", body=f"SELECT range::INT AS iteration, block_id, round(1 / least(1.0, p * {Q}), 6) + 0.0 AS w FROM dist, range({STEPS}) WHERE {sql_uniform(chr(39) + 'poisson' + str(SEED) + chr(39), 'range', 'block_id')} < least(1.0, p * {Q})"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return sampling.draw_poisson(block_scores(spark, d, "documents")[2], Q, STEPS, SEED).select("iteration", "block_id", rounded(F.col("w"), 6).alias("w"))


@query("k5_block_sketch", with_stats("documents", DRAWS, body=f"SELECT iteration, trial, row_id, round(x1 / sqrt({Q} * p), 6) + 0.0 AS x1, round(y / sqrt({Q} * p), 5) + 0.0 AS y FROM draws JOIN design USING (block_id) WHERE iteration = 0"))
def _(spark: SparkSession, d: str) -> DataFrame:
    rows, _, _, _, draws, _ = drawn(spark, d)
    out = sampling.block_sketch(rows, draws.where("iteration = 0"), Q)
    return out.select("iteration", "trial", "row_id", rounded(F.get("features", F.lit(1)), 6).alias("x1"), rounded(F.col("label"), 5).alias("y"))


@query("k6_row_sketch", with_stats("documents", body=f"SELECT row_id, round(1 / least(1.0, l / 3 * 100), 5) + 0.0 AS w FROM (SELECT row_id, {_ROW_LEVERAGE} AS l FROM design, inv) WHERE {sql_uniform(chr(39) + 'row' + str(SEED) + chr(39), 'row_id')} < least(1.0, l / 3 * 100)"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return sampling.row_sketch(scores.row_leverage(load(spark, d, "documents"), 3), 100, SEED).select("row_id", rounded(F.col("w"), 5).alias("w"))


_SK_BODY = f"SELECT iteration, {', '.join(f'round(g{i}{j}, 3) + 0.0 AS g{i}{j}' for i, j in fixtures._PAIRS)} FROM sk"


@query("k7_weighted_sketch", with_stats("documents", DRAWS, SQL_SKETCHED, body=_SK_BODY))
def _(spark: SparkSession, d: str) -> DataFrame:
    """Gram matrices of the weighted sketch's own rows."""
    rows, _, _, _, _, w = drawn(spark, d)
    out = stats.block_stats(sampling.weighted_sketch(rows, w), 3, by=("iteration",))
    return _flat(out, "iteration", digits=3).drop("c0", "c1", "c2", "btb")


@query("k7_sketched_stats", with_stats("documents", DRAWS, SQL_SKETCHED, body=_SK_BODY))
def _(spark: SparkSession, d: str) -> DataFrame:
    _, held, _, _, _, w = drawn(spark, d)
    return _flat(sampling.sketched_stats(held, w, 3), "iteration", digits=3).drop("c0", "c1", "c2", "btb")


@query("k8_compression", with_stats("documents", DRAWS, body="SELECT iteration, count(*)::BIGINT AS q, count(DISTINCT block_id)::BIGINT AS distinct_blocks, round(count(*) / count(DISTINCT block_id), 6) AS zeta FROM draws GROUP BY iteration"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return sampling.compression(drawn(spark, d)[4]).withColumn("zeta", F.round("zeta", 6))


@query("k9_expected_distinct", with_stats("documents", body=f"SELECT round(sum(1 - pow(1 - p, {Q})), 7) AS expected FROM dist"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return sampling.expected_distinct(block_scores(spark, d, "documents")[2], Q).select(F.round("expected", 7).alias("expected"))


@query("k9_expected_distinct_fastest", with_stats("documents", _COUNTS, body=f"SELECT round(sum(1 - {' * '.join(f'greatest(0, ({M} - r - {i}) / {M - i}.0)' for i in range(Q))}), 7) AS expected FROM counts"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return sampling.expected_distinct_fastest(counted(spark, d)[1], Q).select(F.round("expected", 7).alias("expected"))


@query("k10_embedding_error")
def _(spark: SparkSession, d: str) -> DataFrame:
    _, held, _, total, _, w = drawn(spark, d)
    rows = sorted(sampling.sketched_stats(held, w, 3).collect(), key=lambda r: r["iteration"])
    both = zip(sampling.embedding_error(total, rows, 3), sampling.embedding_error(total, rows, 3, augmented=False), strict=True)
    return spark.createDataFrame([(i, a, b) for i, (a, b) in enumerate(both)], "iteration int, eps double, eps_without_label double")


_PROBES = [[1.0, 0.0, 0.0], [0.0, 1.0, 0.0], [1.0, -2.0, 3.0]]
_SQ = ["pow(x0, 2)", "pow(x1, 2)", "pow(x0 - 2 * x1 + 3 * x2, 2)"]


@query("k11_embedding_ratio", with_stats("documents", DRAWS, "whole AS (SELECT " + ", ".join(f"sum({s}) AS f{i}" for i, s in enumerate(_SQ)) + " FROM design), part AS (SELECT iteration, " + ", ".join(f"sum(w * {s}) AS s{i}" for i, s in enumerate(_SQ)) + " FROM design JOIN weights USING (block_id) GROUP BY iteration)", body=" UNION ALL ".join(f"SELECT iteration, {i}::INT AS probe, round(s{i} / f{i}, 6) AS ratio FROM part, whole" for i in range(3))))
def _(spark: SparkSession, d: str) -> DataFrame:
    rows, _, _, _, _, w = drawn(spark, d)
    return sampling.embedding_ratio(rows, w, _PROBES).withColumn("ratio", F.round("ratio", 6))


@query("k12_trials_needed", with_stats("events", "f AS (SELECT block_id, (g00 + g11 + g22) / (SELECT g00 + g11 + g22 FROM tot) AS f FROM stats)", "beta AS (SELECT least(1.0, min(f / p)) AS beta FROM f JOIN dist USING (block_id) WHERE p > 0)", body="SELECT ceil(2 * (3 / beta - 1 + (1 + 3 / beta) * 0.5 / 3) / 0.25 * ln(60))::BIGINT AS proved, ceil(3 / 20.0 * ln(60) / (beta * 0.25))::BIGINT AS printed FROM beta"))
def _(spark: SparkSession, d: str) -> DataFrame:
    """Draws that the events need when Frobenius shares stand in for leverage: beta is the least share over leverage."""
    _, held, dist, _ = block_scores(spark, d, "events")
    both = scores.frobenius_scores(held, 3).select("block_id", F.col("p").alias("f")).join(dist.where("p > 0"), "block_id")
    beta = min(1.0, both.agg(F.min(F.col("f") / F.col("p"))).first()[0])
    return one_row(spark, proved=sampling.trials_needed(3, 0.5, 0.1, beta), printed=sampling.trials_needed(3, 0.5, 0.1, beta, tau=20, form="printed"))


@query("k13_hit_probability", with_stats("documents", body=f"SELECT block_id, round(1 - pow(1 - p, {Q}), 8) AS h, round({Q} * p, 8) AS linear, round({Q} * max(p) OVER (), 8) AS uniform_bound FROM dist"))
def _(spark: SparkSession, d: str) -> DataFrame:
    out = sampling.hit_probability(block_scores(spark, d, "documents")[2], Q)
    return out.select("block_id", *[F.round(c, 8).alias(c) for c in ("h", "linear", "uniform_bound")])


@query("k15_dims", "SELECT ((n + k - 1) // k)::BIGINT AS tau, (k // 2 * ((n + k - 1) // k))::BIGINT AS rows, (k // 2 * ((n + k - 1) // k))::DOUBLE / n AS share, (500 - k // 2)::DOUBLE / 500 AS late_share FROM (SELECT count(value) AS n, count(DISTINCT day(ts)) AS k FROM events)")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Sizes of a sketch of half of the events' blocks."""
    n, k = table(spark, d, "events").agg(F.count("value"), F.count_distinct(F.dayofmonth("ts"))).first()
    return one_row(spark, **sampling.sketch_dims(n, k, k // 2, 500))


# ---- other sketches -----------------------------------------------------------------------------------------------


def _quality_of(spark: SparkSession, total: Total, sketch: DataFrame, width: int, expected_rows: int) -> DataFrame:
    """Rows of a sketch, its embedding error and what its solution costs."""
    s = sketches.sketch_total(stored(sketch, "sketch"), width)
    best = total.solution()
    error = sampling.embedding_error(total, [{"gram": s.gram[np.triu_indices(width)].tolist(), "atb": s.atb.tolist(), "btb": s.btb}], width)[0]
    ratio = math.sqrt(total.objective(s.solution()) / total.objective(best))
    return one_row(spark, rows=int(s.n), as_planned=bool(s.n == expected_rows), eps=float(error), ratio=float(ratio))


@query("x1_gaussian")
def _(spark: SparkSession, d: str) -> DataFrame:
    rows = load(spark, d, "documents")
    return _quality_of(spark, stats.collect_total(stats.block_stats(rows, 3), 3), sketches.dense_sketch(rows, 3, 60), 3, 60)


@query("x2_rademacher")
def _(spark: SparkSession, d: str) -> DataFrame:
    rows = load(spark, d, "documents")
    return _quality_of(spark, stats.collect_total(stats.block_stats(rows, 3), 3), sketches.dense_sketch(rows, 3, 60, "rademacher"), 3, 60)


_SIGN = lambda i: f"(CASE WHEN {fixtures.sql_int(chr(39) + 'sign' + str(i) + chr(39), 'row_id')} % 2 = 0 THEN 1.0 ELSE -1.0 END)"


@query("x2_rademacher_exact", f"WITH {SQL['events']} " + " UNION ALL ".join(f"SELECT {i}::INT AS sketch_row, " + ", ".join(f"round(sum({_SIGN(i)} * {c}) / 2.0, 5) + 0.0 AS {n}" for c, n in (("x0", "x0"), ("x1", "x1"), ("x2", "x2"), ("y", "y"))) + " FROM design" for i in range(4)))
def _(spark: SparkSession, d: str) -> DataFrame:
    return sketches.rademacher_rows(load(spark, d, "events"), 3, 4).select("sketch_row", *[rounded(F.get("features", F.lit(i)), 5).alias(f"x{i}") for i in range(3)], rounded(F.col("label"), 5).alias("y"))


@query("x3_block_srht")
def _(spark: SparkSession, d: str) -> DataFrame:
    rows = stored(load(spark, d, "embeddings"), "design")
    n = rows.count()
    tau = 1 << max(0, (-(-n // 32) - 1).bit_length())
    return _quality_of(spark, stats.collect_total(stats.block_stats(rows, 40), 40), sketches.block_srht(rows, 40, 32, 24), 40, 24 * tau)


@query("x4_srht_rows")
def _(spark: SparkSession, d: str) -> DataFrame:
    rows = stored(load(spark, d, "embeddings"), "design")
    return _quality_of(spark, stats.collect_total(stats.block_stats(rows, 40), 40), sketches.srht_rows(rows, 40, 200), 40, 200)


@query("x5_uniform_blocks", "WITH u AS (SELECT range::INT AS block_id, 0.05::DOUBLE AS p FROM range(20)), " + sql_draws(Q, STEPS, SEED, "u") + " SELECT iteration, trial, block_id FROM draws")
def _(spark: SparkSession, d: str) -> DataFrame:
    return sketches.uniform_block_draws(load(spark, d, "documents"), 20, Q, STEPS, SEED).select("iteration", "trial", "block_id")


@query("x6_sketch_and_solve", with_stats("documents", DRAWS, SQL_SKETCHED, "sdet AS (SELECT *, g00 * (g11 * g22 - g12 * g12) - g01 * (g01 * g22 - g12 * g02) + g02 * (g01 * g12 - g11 * g02) AS det FROM sk WHERE iteration = 0)", body="SELECT 0::INT AS i, round(((g11 * g22 - g12 * g12) * c0 + (g02 * g12 - g01 * g22) * c1 + (g01 * g12 - g02 * g11) * c2) / det, 5) + 0.0 AS v FROM sdet UNION ALL SELECT 1, round(((g02 * g12 - g01 * g22) * c0 + (g00 * g22 - g02 * g02) * c1 + (g01 * g02 - g00 * g12) * c2) / det, 5) + 0.0 FROM sdet UNION ALL SELECT 2, round(((g01 * g12 - g02 * g11) * c0 + (g01 * g02 - g00 * g12) * c1 + (g00 * g11 - g01 * g01) * c2) / det, 5) + 0.0 FROM sdet"))
def _(spark: SparkSession, d: str) -> DataFrame:
    rows, _, _, _, draws, _ = drawn(spark, d)
    sketch = sampling.block_sketch(rows, draws.where("iteration = 0"), Q).select(F.lit(0).alias("block_id"), "features", "label")
    return vector_table(spark, sketches.sketch_and_solve(sketch, 3), 5)


@query("x7_fixed_sketch_descent", with_stats("documents", DRAWS, SQL_SKETCHED, "one AS (SELECT * FROM sk WHERE iteration = 0)", sql_path(STEPS, XI, "one").replace(" AND iteration = s", ""), body=PATH_BODY, recursive=True))
def _(spark: SparkSession, d: str) -> DataFrame:
    rows, _, _, total, _, w = drawn(spark, d, keep=True)
    return path_table(spark, descent.sketched_descent(stored_blocks(rows, BUCKETS), [0.0] * 3, descent.fixed_step(xi_of(total)), descent.Stop(STEPS), w, fixed=True))


@query("x8_countsketch", f"WITH {SQL['events']} SELECT ({fixtures.sql_int(chr(39) + 'cs0' + chr(39), 'row_id')} % 16)::INT AS sketch_row, " + ", ".join(f"round(sum(CASE WHEN {fixtures.sql_int(chr(39) + 'sg0' + chr(39), 'row_id')} % 2 = 0 THEN 1.0 ELSE -1.0 END * {c}), 5) + 0.0 AS {c}" for c in ("x0", "x1", "x2", "y")) + " FROM design GROUP BY 1")
def _(spark: SparkSession, d: str) -> DataFrame:
    return sketches.countsketch(load(spark, d, "events"), 3, 16).select("sketch_row", *[rounded(F.get("features", F.lit(i)), 5).alias(f"x{i}") for i in range(3)], rounded(F.col("label"), 5).alias("y"))


@query("x9_srht_trials", "SELECT ceil(40 * ln(2000 * 40 / 0.1) * ln(800) / 0.25 / 20)::BIGINT AS printed, ceil(40 * ln(2000 * 40 / 0.1) * ln(800) / 0.25)::BIGINT AS whole")
def _(spark: SparkSession, d: str) -> DataFrame:
    return one_row(spark, printed=sketches.srht_trials(40, 20, 2000, 0.5, 0.1), whole=sketches.srht_trials(40, 20, 2000, 0.5, 0.1, "whole"))
