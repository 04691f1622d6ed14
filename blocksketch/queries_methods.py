"""Registered queries, second part: networks, descent, coding, products and measures."""

from __future__ import annotations

from itertools import combinations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blocksketch.fixtures import SQL, SQL_SKETCHED, WIDTH, load, sql_path, sql_uniform
from blocksketch.functions.core import rounded
from blocksketch.operators import coding, descent, distances, gradients, metrics, network, products, sampling, scores, sketches, stats
from blocksketch.operators.descent import Stop, fixed_step
from blocksketch.queries import (
    _COUNTS,
    _REPLY_SQL,
    BUCKETS,
    DRAWS,
    ENDINGS,
    EXAMPLE,
    M,
    PATH_BODY,
    PHI,
    Q,
    SEED,
    STEPS,
    XI,
    block_scores,
    counted,
    drawn,
    one_row,
    path_table,
    query,
    replied,
    vector_table,
    with_stats,
    xi_of,
)
from blocksketch.sources.tables import stored, stored_blocks, table

X = [0.2, -0.4, 0.7]
RESID = "(0.2 * x0 - 0.4 * x1 + 0.7 * x2 - y)"

# ---- network ------------------------------------------------------------------------------------------------------


@query("n1_runtime_cdf", "SELECT value AS t, round(sum(count(*)) OVER (ORDER BY value) / sum(count(*)) OVER (), 8) AS cdf FROM events GROUP BY value")
def _(spark: SparkSession, d: str) -> DataFrame:
    return network.runtime_law(table(spark, d, "events"), "value").withColumn("cdf", F.round("cdf", 8))


_F = lambda t: f"(SELECT avg(CASE WHEN value <= {t} THEN 1.0 ELSE 0.0 END) FROM events)"


@query("n2_replies_by_T", " UNION ALL ".join(f"SELECT {t}.0::DOUBLE AS ending, round(1 - {_F(t)}, 8) AS phi, floor({_F(t)} * 500 + 1e-9)::BIGINT AS q" for t in ENDINGS))
def _(spark: SparkSession, d: str) -> DataFrame:
    return network.replies_by(table(spark, d, "events"), "value", ENDINGS, 500).withColumn("phi", F.round("phi", 8))


@query("n3_ending_time", "SELECT min(value) AS ending FROM (SELECT value, sum(count(*)) OVER (ORDER BY value) / sum(count(*)) OVER () AS cdf FROM events GROUP BY value) WHERE floor(cdf * 500 + 1e-9) >= 250")
def _(spark: SparkSession, d: str) -> DataFrame:
    return network.ending_time(table(spark, d, "events"), "value", 500, 250)


def _dist(spark: SparkSession, d: str) -> DataFrame:
    return stored(block_scores(spark, d, "documents")[2], "dist")


_RHO = f"(ln(1 - p) / ln({PHI}))"


@query("n4_replicas_channel", with_stats("documents", body=f"SELECT block_id, round({_RHO}, 7) + 0.0 AS rho, floor({_RHO} + 0.5)::BIGINT AS r FROM dist"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return network.replicas_channel(_dist(spark, d), PHI).select("block_id", rounded(F.col("rho"), 7).alias("rho"), "r")


@query("n5_replicas_scaled", with_stats("documents", body=f"SELECT block_id, greatest(1, floor({_RHO} * {M} / (SELECT sum({_RHO}) FROM dist) + 0.5))::BIGINT AS r FROM dist"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return network.replicas_channel_scaled(_dist(spark, d), PHI, M).select("block_id", "r")


@query("n6_replicas_ratio", with_stats("documents", body="SELECT block_id, floor(2 * p / (SELECT min(p) FROM dist WHERE p > 0) + 0.5)::BIGINT AS r FROM dist"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return network.replicas_ratio(_dist(spark, d), 2).select("block_id", "r")


_PRIORITIES = "WITH c AS (SELECT (row_number() OVER (ORDER BY o_orderpriority) - 1)::INT AS block_id, count(o_totalprice) AS n FROM orders GROUP BY o_orderpriority)"


def _priorities(spark: SparkSession, d: str) -> list[int]:
    """Orders of each priority: exact shares, a handful of numbers."""
    counts = table(spark, d, "orders").groupBy("o_orderpriority").agg(F.count("o_totalprice").alias("n"))
    return [r["n"] for r in counts.orderBy("o_orderpriority").collect()]


@query("n7_replicas_lcm", _PRIORITIES + ", g AS (SELECT " + "gcd(" * 4 + "max(n) FILTER (block_id = 0), " + "), ".join(f"max(n) FILTER (block_id = {i})" for i in range(1, 5)) + ") AS g FROM c) SELECT block_id, (n // g)::BIGINT AS r FROM c, g")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Counts that emulate the priorities' shares of the orders exactly."""
    counts = _priorities(spark, d)
    return network.replicas_lcm(spark, counts, [sum(counts)] * len(counts))


@query("n8_is_perfect", _PRIORITIES + f", a AS (SELECT sum(n)::BIGINT AS a FROM c) SELECT bool_and(a * n % a = 0) AS at_all, bool_and(2 * a * n % a = 0) AS at_twice, bool_and({M} * n % a = 0) AS at_{M} FROM c, a")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Whether the priorities' shares of the orders can be met exactly by as many servers as orders, by twice as many, and by M."""
    counts = _priorities(spark, d)
    n = sum(counts)
    return one_row(spark, **{f"at_{name}": network.is_perfect(counts, [n] * len(counts), r) for name, r in (("all", n), ("twice", 2 * n), (M, M))})


@query("n10_apportion_remainders", with_stats("documents", _COUNTS, body="SELECT block_id, r FROM counts"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return counted(spark, d)[1].select("block_id", "r")


@query("n10_apportion_floor_one", with_stats("documents", f"units AS (SELECT block_id, k, abs(p - (k - 1) / {M}.0) - abs(p - k / {M}.0) AS gain FROM dist, (SELECT range AS k FROM range(2, {M + 1}))), given AS (SELECT block_id, count(*) AS more FROM (SELECT block_id, row_number() OVER (ORDER BY round(gain, 12) DESC, block_id, k) AS place FROM units) WHERE place <= {M} - (SELECT count(*) FROM dist) GROUP BY block_id)", body="SELECT dist.block_id, (1 + coalesce(more, 0))::BIGINT AS r FROM dist LEFT JOIN given USING (block_id)"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return network.apportion_exact(_dist(spark, d), M, 1).select("block_id", "r")


@query("n11_allocate", _REPLY_SQL.format("SELECT server_id, block_id FROM servers"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return network.allocate(counted(spark, d)[1])


@query("n12_encoding", with_stats("documents", _COUNTS, body=f"SELECT block_id, round(1 / sqrt({Q} * r / {M}.0), 8) AS scale FROM counts WHERE r > 0"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return network.encoding(counted(spark, d)[1], Q).select("block_id", F.round("scale", 8).alias("scale"))


@query("n13_expanded", with_stats("documents", _COUNTS, body=f"SELECT block_id, (r * n)::BIGINT AS n, round(r * btb / ({Q} * r / {M}.0), 4) + 0.0 AS btb FROM counts JOIN stats USING (block_id) WHERE r > 0"))
def _(spark: SparkSession, d: str) -> DataFrame:
    out = network.expand(load(spark, d, "documents"), counted(spark, d)[1], Q)
    return out.groupBy("block_id").agg(F.count("*").alias("n"), rounded(F.sum(F.col("label") * F.col("label")), 4).alias("btb"))


@query("n14_responses", _REPLY_SQL.format("SELECT iteration, server_id, block_id, t FROM replies"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return replied(spark, d)[1]


# ---- gradients ----------------------------------------------------------------------------------------------------

for _name in ("lineitem", "documents"):
    query(f"g1_objective_{_name}", f"WITH {SQL[_name]} SELECT round(sum(pow({RESID}, 2)), 3) AS objective FROM design")(lambda spark, d, name=_name: gradients.objective(load(spark, d, name), X).select(F.round("objective", 3).alias("objective")))

_G = ", ".join(f"round(sum(2 * {RESID} * x{i}), 3) + 0.0 AS g{i}" for i in range(3))


def _spread(df: DataFrame, *keep: str, digits: int = 3) -> DataFrame:
    return df.select(*keep, *[rounded(F.get("g", F.lit(i)), digits).alias(f"g{i}") for i in range(3)])


@query("g2_gradient", f"WITH {SQL['lineitem']} SELECT {_G} FROM design")
def _(spark: SparkSession, d: str) -> DataFrame:
    return _spread(gradients.gradient(load(spark, d, "lineitem"), X))


@query("g2_partial_gradients", f"WITH {SQL['lineitem']} SELECT block_id, {_G} FROM design GROUP BY block_id")
def _(spark: SparkSession, d: str) -> DataFrame:
    return _spread(gradients.partial_gradients(load(spark, d, "lineitem"), X), "block_id")


@query("g2_partial_gradients_star", f"WITH {SQL['star']} SELECT block_id, " + ", ".join(f"round(sum(2 * (0.1 * (x0 + x1 + x2 + x3 + x4 + x5 + x6) - y) * x{i}), 3) + 0.0 AS g{i}" for i in range(7)) + " FROM design GROUP BY block_id")
def _(spark: SparkSession, d: str) -> DataFrame:
    out = gradients.partial_gradients(load(spark, d, "star"), [0.1] * 7)
    return out.select("block_id", *[rounded(F.get("g", F.lit(i)), 3).alias(f"g{i}") for i in range(7)])


@query("g3_encoded_partials", with_stats("documents", _COUNTS, "g AS (SELECT block_id, " + ", ".join(f"sum(2 * {RESID} * x{i}) AS g{i}" for i in range(3)) + " FROM design GROUP BY block_id)", body="SELECT block_id, " + ", ".join(f"round(g{i} / ({Q} * r / {M}.0), 4) + 0.0 AS g{i}" for i in range(3)) + " FROM g JOIN counts USING (block_id) WHERE r > 0"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return _spread(gradients.encoded_partials(load(spark, d, "documents"), X, network.encoding(counted(spark, d)[1], Q)), "block_id", digits=4)


@query("g4_sketched_gradient", with_stats("documents", DRAWS, body="SELECT iteration, " + ", ".join(f"round(sum(2 * w * {RESID} * x{i}), 3) + 0.0 AS g{i}" for i in range(3)) + " FROM design JOIN weights USING (block_id) GROUP BY iteration"))
def _(spark: SparkSession, d: str) -> DataFrame:
    rows, _, _, _, _, w = drawn(spark, d)
    return _spread(gradients.sketched_gradient(rows, X, w), "iteration")


@query("g5_sketched_hessian", with_stats("documents", DRAWS, SQL_SKETCHED, body="SELECT iteration, round(2 * g00, 3) AS h00, round(2 * g12, 3) + 0.0 AS h12, round(2 * g22, 3) AS h22 FROM sk"))
def _(spark: SparkSession, d: str) -> DataFrame:
    _, held, _, _, _, w = drawn(spark, d)
    return gradients.sketched_hessian(held, w, 3).select("iteration", *[rounded(F.get("h", F.lit(k)), 3).alias(n) for k, n in ((0, "h00"), (4, "h12"), (5, "h22"))])


_SOLVE = " UNION ALL ".join(f"SELECT {i}::INT AS i, round({' + '.join(f'i{min(i, j)}{max(i, j)} * c{j}' for j in range(3))}, 5) + 0.0 AS v FROM inv, tot" for i in range(3))
for _name in ("lineitem", "documents", "events"):
    query(f"g6_solve_exact_{_name}", with_stats(_name, body=_SOLVE))(lambda spark, d, name=_name: vector_table(spark, block_scores(spark, d, name)[3].solution(), 5))


# ---- descent ------------------------------------------------------------------------------------------------------


@query("g7_line_search", with_stats("events", "path(s, a0, a1, a2) AS (SELECT 0, 0.0::DOUBLE, 0.0::DOUBLE, 0.0::DOUBLE UNION ALL SELECT s + 1, a0 - t * r0, a1 - t * r1, a2 - t * r2 FROM (SELECT *, (r0 * r0 + r1 * r1 + r2 * r2) / (g00 * r0 * r0 + g11 * r1 * r1 + g22 * r2 * r2 + 2 * (g01 * r0 * r1 + g02 * r0 * r2 + g12 * r1 * r2)) AS t FROM (SELECT *, g00 * a0 + g01 * a1 + g02 * a2 - c0 AS r0, g01 * a0 + g11 * a1 + g12 * a2 - c1 AS r1, g02 * a0 + g12 * a1 + g22 * a2 - c2 AS r2 FROM path, tot WHERE s < 5)))", body=PATH_BODY, recursive=True))
def _(spark: SparkSession, d: str) -> DataFrame:
    return path_table(spark, descent.steepest_descent(stored(load(spark, d, "events"), "design"), [0.0] * 3, descent.line_search(), Stop(5)))


@query("g8_descent", with_stats("lineitem", sql_path(STEPS, XI, "tot"), body=PATH_BODY, recursive=True))
def _(spark: SparkSession, d: str) -> DataFrame:
    rows, _, _, total = block_scores(spark, d, "lineitem", keep=True)
    return path_table(spark, descent.steepest_descent(rows, [0.0] * 3, fixed_step(xi_of(total)), Stop(STEPS)))


def _batch_sql(name: str, key: str, share: float) -> str:
    u = sql_uniform(f"'sgd{SEED}'", "range", key)
    g = ", ".join(f"coalesce(sum(x{i} * x{j}), 0) / {share} AS g{i}{j}" for i in range(3) for j in range(i, 3))
    c = ", ".join(f"coalesce(sum(x{i} * y), 0) / {share} AS c{i}" for i in range(3))
    return with_stats(name, f"sk AS MATERIALIZED (SELECT range AS iteration, {g}, {c} FROM design, range({STEPS}) WHERE {u} < {share} GROUP BY range)", sql_path(STEPS, XI), body=PATH_BODY, recursive=True)


@query("g9_ssd_rows", _batch_sql("events", "row_id", 0.2))
def _(spark: SparkSession, d: str) -> DataFrame:
    rows, _, _, total = block_scores(spark, d, "events", keep=True)
    return path_table(spark, descent.stochastic_descent(rows, [0.0] * 3, fixed_step(xi_of(total)), Stop(STEPS), 0.2, SEED))


@query("g9_ssd_blocks", _batch_sql("documents", "block_id", 0.5))
def _(spark: SparkSession, d: str) -> DataFrame:
    rows, _, _, total = block_scores(spark, d, "documents", keep=True)
    return path_table(spark, descent.stochastic_descent(rows, [0.0] * 3, fixed_step(xi_of(total)), Stop(STEPS), 0.5, SEED, "block"))


_ITER = with_stats("documents", DRAWS, SQL_SKETCHED, sql_path(STEPS, XI), body=PATH_BODY, recursive=True)


@query("g10_sketched_descent", _ITER)
def _(spark: SparkSession, d: str) -> DataFrame:
    rows, _, _, total, _, w = drawn(spark, d, keep=True)
    return path_table(spark, descent.sketched_descent(stored_blocks(rows, BUCKETS), [0.0] * 3, fixed_step(xi_of(total)), Stop(STEPS), w))


@query("g12_weighted_descent", _ITER)
def _(spark: SparkSession, d: str) -> DataFrame:
    """The same iterates from weighted Gram matrices."""
    _, held, _, total, _, w = drawn(spark, d)
    return path_table(spark, descent.descend_on_stats(total, descent.sketch_totals(held, w, 3), [0.0] * 3, fixed_step(xi_of(total)), Stop(STEPS)))


_ONE = f"units AS (SELECT block_id, k, abs(p - (k - 1) / {M}.0) - abs(p - k / {M}.0) AS gain FROM dist, (SELECT range AS k FROM range(2, {M + 1}))), given AS (SELECT block_id, count(*) AS more FROM (SELECT block_id, row_number() OVER (ORDER BY round(gain, 12) DESC, block_id, k) AS place FROM units) WHERE place <= {M} - (SELECT count(*) FROM dist) GROUP BY block_id), counts AS (SELECT dist.block_id, 1 + coalesce(more, 0) AS r FROM dist LEFT JOIN given USING (block_id))"
_REPLIES = _REPLY_SQL[_REPLY_SQL.index("law AS") : _REPLY_SQL.rindex("\n")]
_CODED = f"weights AS MATERIALIZED (SELECT iteration, block_id, count(*) / ({Q} * any_value(r) / {M}.0) AS w FROM (SELECT iteration, block_id FROM (SELECT *, row_number() OVER (PARTITION BY iteration ORDER BY t, server_id) AS place FROM replies) WHERE place <= {Q}) JOIN counts USING (block_id) GROUP BY iteration, block_id)"


def coded_path(spark: SparkSession, d: str, name: str, ending: float | None = None) -> descent.Trace:
    rows, _, dist, total = block_scores(spark, d, name, keep=True)
    law = stored(network.runtime_law(table(spark, d, "events"), "value"), "law")
    q = None if ending else Q
    return descent.coded_descent(stored_blocks(rows, BUCKETS), stored(dist, "dist"), law, M, [0.0] * 3, fixed_step(xi_of(total)), Stop(STEPS), SEED, q, ending)[0]


for _name in ("lineitem", "documents"):
    query(f"g11_coded_descent_{_name}", with_stats(_name, _ONE, _REPLIES, _CODED, SQL_SKETCHED, sql_path(STEPS, XI), body=PATH_BODY, recursive=True))(lambda spark, d, name=_name: path_table(spark, coded_path(spark, d, name)))

_LATE = f"came AS (SELECT iteration, block_id, count(*) OVER (PARTITION BY iteration) AS q FROM replies WHERE t <= 24), weights AS MATERIALIZED (SELECT iteration, block_id, count(*) / (any_value(q) * any_value(r) / {M}.0) AS w FROM came JOIN counts USING (block_id) GROUP BY iteration, block_id)"


@query("g11_coded_descent_deadline", with_stats("documents", _ONE, _REPLIES, _LATE, SQL_SKETCHED, sql_path(STEPS, XI), body=PATH_BODY, recursive=True))
def _(spark: SparkSession, d: str) -> DataFrame:
    return path_table(spark, coded_path(spark, d, "documents", 24.0))


@query("g14_ridge", with_stats("events", sql_path(STEPS, XI, "tot", ridge=5.0), body=PATH_BODY, recursive=True))
def _(spark: SparkSession, d: str) -> DataFrame:
    rows, _, _, total = block_scores(spark, d, "events", keep=True)
    return path_table(spark, descent.steepest_descent(rows, [0.0] * 3, fixed_step(xi_of(total)), Stop(STEPS), ridge=5.0))


@query("g16_projected", with_stats("events", sql_path(STEPS, XI, "tot", project=0.5), body=PATH_BODY, recursive=True))
def _(spark: SparkSession, d: str) -> DataFrame:
    rows, _, _, total = block_scores(spark, d, "events", keep=True)
    return path_table(spark, descent.steepest_descent(rows, [0.0] * 3, fixed_step(xi_of(total)), Stop(STEPS), project=0.5))


@query("g17_encoded_objective", with_stats("documents", _COUNTS, "e AS (SELECT block_id, sum(pow(" + RESID + ", 2)) AS v FROM design GROUP BY block_id)", body=f"SELECT round(sum(v / ({Q} * r / {M}.0)), 4) AS encoded, round(sum(r * v / ({Q} * r / {M}.0)), 4) AS expanded FROM e JOIN counts USING (block_id) WHERE r > 0"))
def _(spark: SparkSession, d: str) -> DataFrame:
    rows, code = load(spark, d, "documents"), network.encoding(counted(spark, d)[1], Q)
    a = gradients.encoded_objective(rows, X, code).first()["objective"]
    b = gradients.encoded_objective(rows, X, code, expanded=True).first()["objective"]
    return one_row(spark, encoded=round(a, 4), expanded=round(b, 4))


# ---- coding -------------------------------------------------------------------------------------------------------


@query("c1_uncoded", f"WITH {SQL['documents']} SELECT 0::INT AS iteration, {_G} FROM design")
def _(spark: SparkSession, d: str) -> DataFrame:
    return _spread(coding.uncoded(gradients.partial_gradients(load(spark, d, "documents"), X)), "iteration")


@query("c1_uncoded_late_dropped", _REPLY_SQL.format(f"SELECT iteration, {_G} FROM design JOIN (SELECT DISTINCT iteration, block_id FROM replies WHERE t <= 24) USING (block_id) GROUP BY iteration"))
def _(spark: SparkSession, d: str) -> DataFrame:
    came = replied(spark, d)[1].where("t <= 24")
    return _spread(coding.uncoded(stored(gradients.partial_gradients(load(spark, d, "documents"), X), "parts"), came), "iteration")


@query("c2_group_coding", f"WITH {SQL['documents']} SELECT range::INT AS iteration, {_G} FROM design, range({STEPS}) GROUP BY range")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Any 7 of 8 servers in groups of 2 give the exact gradient in every iteration."""
    m, q = 8, 7
    law = stored(network.runtime_law(table(spark, d, "events"), "value"), "law")
    code = coding.group_code(spark, m, q)
    replies = sampling.draw_fastest(network.simulate_responses(code.withColumn("block_id", F.col("group_id")), law, STEPS, SEED), q)
    parts = stored(gradients.partial_gradients(load(spark, d, "documents"), X), "parts")
    return _spread(coding.group_decode(parts, code, replies.select("iteration", "server_id"), 5), "iteration")


@query("c4_uniform_replicas", f"WITH b AS (SELECT DISTINCT day(ts)::INT AS block_id FROM events), c AS (SELECT block_id, count(*) OVER () AS k, row_number() OVER (ORDER BY block_id) AS place FROM b) SELECT block_id, ({M} // k + CASE WHEN place <= {M} % k THEN 1 ELSE 0 END)::BIGINT AS r FROM c")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Equal shares of the servers for the blocks that the events have."""
    return coding.uniform_code_of(load(spark, d, "events"), M).select("block_id", "r")


@query("c6_decode_cost", f"WITH b AS (SELECT count(DISTINCT day(ts)) AS k FROM events) SELECT 'uncoded' AS scheme, (3 * k)::BIGINT AS additions, 0::BIGINT AS solve, 1.0::DOUBLE AS copies FROM b UNION ALL SELECT 'group code', 3, 0, 51.0 UNION ALL SELECT 'optimal decoding', 30, {Q} * k * least({Q}, k), {M} / k::DOUBLE FROM b UNION ALL SELECT 'leverage replicas', 30, 0, {M} / k::DOUBLE FROM b")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Costs for the blocks and columns of the events."""
    k = load(spark, d, "events").agg(F.count_distinct("block_id")).first()[0]
    return coding.decode_cost(spark, Q, k, WIDTH["events"], M)


# ---- products -----------------------------------------------------------------------------------------------------


def _two(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    a = load(spark, d, "documents")
    b = a.select("row_id", "block_id", F.array(F.col("label"), F.get("features", F.lit(1)) - F.get("features", F.lit(2))).alias("features"))
    return a, b


_Z = ["y", "(x1 - x2)"]
_CELLS = [(i, j) for i in range(3) for j in range(2)]
_PRODUCT = "prod AS (SELECT block_id, " + ", ".join(f"sum(x{i} * {_Z[j]}) AS p{i}{j}" for i, j in _CELLS) + ", sqrt(sum(x0 * x0 + x1 * x1 + x2 * x2)) * sqrt(sum(y * y + pow(x1 - x2, 2))) AS score FROM design GROUP BY block_id), pdist AS (SELECT block_id, score / sum(score) OVER () AS p FROM prod)"


@query("p1_cr_exact", f"WITH {SQL['documents']}, {_PRODUCT} " + " UNION ALL ".join(f"SELECT {i}::INT AS i, {j}::INT AS j, round(sum(p{i}{j}), 4) + 0.0 AS v FROM prod" for i, j in _CELLS))
def _(spark: SparkSession, d: str) -> DataFrame:
    return products.exact_product(*_two(spark, d), 3, 2).withColumn("v", rounded(F.col("v"), 4))


def _cr_sql() -> str:
    from blocksketch.fixtures import sql_draws

    return f"WITH {SQL['documents']}, {_PRODUCT}, {sql_draws(Q, STEPS, SEED, 'pdist')} " + " UNION ALL ".join(f"SELECT iteration, {i}::INT AS i, {j}::INT AS j, round(sum(w * p{i}{j}), 4) + 0.0 AS v FROM prod JOIN weights USING (block_id) GROUP BY iteration" for i, j in _CELLS)


@query("p1_cr_product", _cr_sql())
def _(spark: SparkSession, d: str) -> DataFrame:
    return products.cr_product(*_two(spark, d), 3, 2, Q, SEED, STEPS).withColumn("v", rounded(F.col("v"), 4))


@query("p4_sketched_product")
def _(spark: SparkSession, d: str) -> DataFrame:
    a, b = _two(spark, d)
    made = products.sketched_product(a.withColumn("label", F.lit(0.0)), b.withColumn("label", F.lit(0.0)), lambda df: sketches.countsketch(df, len(df.first()["features"]), 64))
    return spark.createDataFrame([(i, j, float(made[i, j])) for i, j in _CELLS], "i int, j int, v double")


# ---- measures -----------------------------------------------------------------------------------------------------


def run_documents(spark: SparkSession, d: str) -> tuple:
    rows, held, dist, total, draws, w = drawn(spark, d)
    trace = descent.descend_on_stats(total, descent.sketch_totals(held, w, 3), [0.0] * 3, fixed_step(xi_of(total)), Stop(STEPS))
    return rows, held, dist, total, w, trace


_BEST = "best AS (SELECT " + ", ".join(f"{' + '.join(f'i{min(i, j)}{max(i, j)} * c{j}' for j in range(3))} AS b{i}" for i in range(3)) + " FROM inv, tot)"
_CURVE = "log10(sqrt(pow(a0 - b0, 2) + pow(a1 - b1, 2) + pow(a2 - b2, 2)) / sqrt((SELECT n FROM tot)))"


@query("a1_log_residual", with_stats("documents", DRAWS, SQL_SKETCHED, _BEST, sql_path(STEPS, XI), body=f"SELECT round({_CURVE}, 5) + 0.0 AS log_residual FROM path, best WHERE s = {STEPS}", recursive=True))
def _(spark: SparkSession, d: str) -> DataFrame:
    *_, total, _, trace = run_documents(spark, d)
    return metrics.log_residual(trace.table(spark), total.solution().tolist(), total.n).select(rounded(F.col("log_residual"), 5).alias("log_residual"))


@query("a2_convergence", with_stats("documents", DRAWS, SQL_SKETCHED, _BEST, sql_path(STEPS, XI), body=f"SELECT s::INT AS s, round({_CURVE}, 5) + 0.0 AS log_residual FROM path, best", recursive=True))
def _(spark: SparkSession, d: str) -> DataFrame:
    *_, total, _, trace = run_documents(spark, d)
    return metrics.convergence(trace.table(spark), total.solution().tolist(), total.n).select("s", rounded(F.col("log_residual"), 5).alias("log_residual"))


_ERR = lambda v: f"sqrt(sum(pow({v} - y, 2)))"


@query("a3_objective_ratio", with_stats("documents", _BEST, body=f"SELECT round({_ERR('0.2 * x0 - 0.4 * x1 + 0.7 * x2')} / {_ERR('b0 * x0 + b1 * x1 + b2 * x2')}, 4) AS ratio FROM design, best"))
def _(spark: SparkSession, d: str) -> DataFrame:
    rows, _, _, total = block_scores(spark, d, "documents")
    return metrics.objective_ratio(rows, X, total.solution().tolist()).select(F.round("ratio", 4).alias("ratio"))


@query("a4_in_span_error", with_stats("documents", _BEST, body=f"SELECT round(sqrt(sum(pow((b0 - 0.2) * x0 + (b1 + 0.4) * x1 + (b2 - 0.7) * x2, 2))), 4) AS in_span, round({_ERR('b0 * x0 + b1 * x1 + b2 * x2')}, 4) AS b_perp FROM design, best"))
def _(spark: SparkSession, d: str) -> DataFrame:
    rows, _, _, total = block_scores(spark, d, "documents")
    return metrics.in_span_error(rows, X, total.solution().tolist()).select(F.round("in_span", 4).alias("in_span"), F.round("b_perp", 4).alias("b_perp"))


@query("a9_bias_example", "WITH b AS (SELECT (o_custkey % 5)::INT AS b, sum(o_totalprice) / 1e9 AS g FROM orders GROUP BY 1), servers AS (SELECT row_number() OVER (ORDER BY b, k) AS s, g * 20 / (3 * r) AS v FROM b JOIN (VALUES (0, 3), (1, 3), (2, 4), (3, 5), (4, 5)) t(b, r) USING (b), range(5) u(k) WHERE k < r), sums AS (SELECT x.v + y.v + z.v AS v FROM servers x, servers y, servers z WHERE x.s < y.s AND y.s < z.s) SELECT count(*)::BIGINT AS sets, round(avg(v), 6) AS mean, (SELECT round(sum(g), 6) FROM b) AS whole, var_pop(v) < 3 * (SELECT var_pop(v) FROM servers) AS less_spread_than_with_replacement FROM sums")
def _(spark: SparkSession, d: str) -> DataFrame:
    """The worked example on orders: all 3-subsets of 20 servers, five blocks of customers with sums of prices as partial gradients; the mean is the whole sum."""
    counts, m, q = EXAMPLE
    sums = table(spark, d, "orders").groupBy(F.pmod("o_custkey", F.lit(len(counts))).cast("int").alias("b")).agg((F.sum("o_totalprice") / 1e9).alias("g"))
    part = {r["b"]: r["g"] for r in sums.collect()}  # five numbers
    block = [b for b, r in enumerate(counts) for _ in range(r)]
    value = [part[b] * m / (q * counts[b]) for b in block]
    sums = np.array([value[i] + value[j] + value[k] for i, j, k in combinations(range(m), q)])
    single = np.array(value)
    return one_row(spark, sets=len(sums), mean=round(float(sums.mean()), 6), whole=round(sum(part.values()), 6), less_spread_than_with_replacement=bool(sums.var() < q * single.var()))


@query("a10_prediction_error", with_stats("documents", _BEST, body="SELECT round(avg(pow((b0 - 0.5) * x0 + (b1 - 1) * x1 + (b2 + 2) * x2, 2)), 8) + 0.0 AS prediction_error FROM design, best"))
def _(spark: SparkSession, d: str) -> DataFrame:
    rows, _, _, total = block_scores(spark, d, "documents")
    return metrics.prediction_error(rows, total.solution().tolist(), [0.5, 1.0, -2.0]).select(rounded(F.col("prediction_error"), 8).alias("prediction_error"))


@query("a12_costs")
def _(spark: SparkSession, d: str) -> DataFrame:
    """What a run from a block store costs for several numbers of draws: files and rows read, jobs, additions, simulated waiting, seconds."""
    rows, _, dist, total = block_scores(spark, d, "documents", keep=True)
    store, dist, out = stored_blocks(rows, BUCKETS), stored(dist, "dist"), []
    law = stored(network.runtime_law(table(spark, d, "events"), "value"), "law")
    replies = stored(network.simulate_responses(network.allocate(network.apportion_exact(dist, M, 0)), law, STEPS, SEED), "replies")
    for q in (2, 5, 10, 20):
        w = stored(sampling.weights(sampling.draw_blocks(dist, q, STEPS, SEED), q), "weights")
        with metrics.measured_jobs(spark) as seen:
            trace = descent.sketched_descent(store, [0.0] * 3, fixed_step(xi_of(total)), Stop(STEPS), w)
        waits = [r["waited"] for r in metrics.waiting_times(replies, q).collect()]
        c = metrics.costs(trace, q, 3, waits)
        out.append((q, c["iterations"], c["files_read"], c["rows_read"], c["blocks_read"], seen["jobs"], c["master_additions"], c["waited"], seen["seconds"]))
    return spark.createDataFrame(out, "q int, iterations int, files_read long, rows_read long, blocks_read long, jobs long, master_additions long, waited double, seconds double")


@query("a12_waiting_times", _REPLY_SQL.format(f"SELECT iteration, t AS waited FROM (SELECT *, row_number() OVER (PARTITION BY iteration ORDER BY t, server_id) AS place FROM replies) WHERE place = {Q}"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return metrics.waiting_times(replied(spark, d)[1], Q)


#: Fixed values of the worked example: its four draws (blocks from 1).
EXAMPLE_DRAWS = [[1, 4, 5], [3, 5, 5], [2, 4, 5], [4, 1, 4]]


@query("w6_worked_example", "SELECT t.iteration::INT AS iteration, t.block_id::INT AS block_id, round(n / (3 * share), 6) AS w FROM (VALUES (0, 0, 1, 0.15), (0, 3, 1, 0.25), (0, 4, 1, 0.25), (1, 2, 1, 0.2), (1, 4, 2, 0.25), (2, 1, 1, 0.15), (2, 3, 1, 0.25), (2, 4, 1, 0.25), (3, 3, 2, 0.25), (3, 0, 1, 0.15)) t(iteration, block_id, n, share)")
def _(spark: SparkSession, d: str) -> DataFrame:
    counts, m, q = EXAMPLE
    rows = [(i, b - 1, counts[b - 1] / m) for i, draw in enumerate(EXAMPLE_DRAWS) for b in draw]
    return sampling.weights(spark.createDataFrame(rows, "iteration int, block_id int, p double"), q).select("iteration", "block_id", F.round("w", 6).alias("w"))
