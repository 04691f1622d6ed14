"""Registered queries, third part: measures over many draws, decoding on replies, and numbers that SQL recomputes."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blocksketch.fixtures import NOISE, PLANTED, SQL, SQL_SKETCHED, load, sql_draws, sql_int, sql_path, sql_uniform
from blocksketch.functions import udfs
from blocksketch.functions.core import rounded
from blocksketch.operators import coding, descent, distances, gradients, metrics, network, products, sampling, scores, sketches, stats
from blocksketch.operators.descent import Stop, fixed_step
from blocksketch.plans.rewrites import small
from blocksketch.queries import _COUNTS, BUCKETS, DRAWS, M, Q, REPLIES, SEED, STEPS, XI, _ROW_LEVERAGE, block_scores, counted, drawn, one_row, query, vector_table, with_stats, xi_of
from blocksketch.queries_methods import _BEST, _CELLS, _ONE, _PRODUCT, RESID, X, _spread, _two
from blocksketch.sources.tables import stored, stored_blocks, table

RUNS = 40
_D3 = [(i, j) for i in range(3) for j in range(i, 3)]


def _inverse(source: str, name: str, keep: str = "") -> str:
    """CTEs ``name``d and ``name``: closed inverses (i00 ..) of the Gram matrices g00 .. of every row of ``source``."""
    det = "g00 * (g11 * g22 - g12 * g12) - g01 * (g01 * g22 - g12 * g02) + g02 * (g01 * g12 - g11 * g02)"
    return f"""{name}d AS (SELECT *, {det} AS det FROM {source}),
{name} AS MATERIALIZED (SELECT {keep} (g11 * g22 - g12 * g12) / det AS i00, (g02 * g12 - g01 * g22) / det AS i01, (g01 * g12 - g02 * g11) / det AS i02,
  (g00 * g22 - g02 * g02) / det AS i11, (g01 * g02 - g00 * g12) / det AS i12, (g00 * g11 - g01 * g01) / det AS i22 FROM {name}d)"""


_SCORE = "i00 * g00 + 2 * i01 * g01 + 2 * i02 * g02 + i11 * g11 + 2 * i12 * g12 + i22 * g22"


def law_of(spark: SparkSession, d: str) -> DataFrame:
    return stored(network.runtime_law(table(spark, d, "events"), "value"), "law")


# ---- factors and approximate scores -------------------------------------------------------------------------------

_CHOLESKY = ("l AS (SELECT *, sqrt(g00) AS r00, g01 / sqrt(g00) AS r01, g02 / sqrt(g00) AS r02 FROM tot)", "m AS (SELECT *, sqrt(g11 - r01 * r01) AS r11, (g12 - r01 * r02) / sqrt(g11 - r01 * r01) AS r12 FROM l)")


@query("s2_tsqr", with_stats("lineitem", *_CHOLESKY, body="SELECT " + ", ".join(f"round({v}, 5) + 0.0 AS {n}" for n, v in (("r00", "r00"), ("r01", "r01"), ("r02", "r02"), ("r11", "r11"), ("r12", "r12"), ("r22", "sqrt(g22 - r02 * r02 - r12 * r12)"))) + " FROM m"))
def _(spark: SparkSession, d: str) -> DataFrame:
    """The triangular factor by the tree of small factorisations; SQL has it from the Gram matrix."""
    r = stats.tsqr(load(spark, d, "lineitem"), 3)
    return one_row(spark, **{f"r{i}{j}": round(float(r[i, j]), 5) + 0.0 for i, j in _D3})


def _signed(salt: int, rows: int) -> str:
    sign = f"CASE WHEN {sql_int(chr(39) + 'sg' + str(salt) + chr(39), 'row_id')} % 2 = 0 THEN 1.0 ELSE -1.0 END"
    return f"hashed AS (SELECT {sql_int(chr(39) + 'cs' + str(salt) + chr(39), 'row_id')} % {rows} AS bucket, " + ", ".join(f"sum(({sign}) * x{i}) AS s{i}" for i in range(3)) + " FROM design GROUP BY 1), hgram AS (SELECT " + ", ".join(f"sum(s{i} * s{j}) AS g{i}{j}" for i, j in _D3) + " FROM hashed)"


@query("s5_approx", with_stats("documents", _signed(3, 128), _inverse("hgram", "hinv"), f"scored AS (SELECT block_id, {_SCORE} AS score FROM stats, hinv)", body="SELECT block_id, round(score / sum(score) OVER (), 8) + 0.0 AS p FROM scored"))
def _(spark: SparkSession, d: str) -> DataFrame:
    """Block scores from the factor of a hashed sketch of 128 rows."""
    return scores.approx_leverage(load(spark, d, "documents"), 3, 128, 0, seed=3).select("block_id", rounded(F.col("p"), 8).alias("p"))


@query("s5_approx_kinds")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Misestimation of approximate scores from each sketch, with exact and with projected row norms."""
    rows = stored(load(spark, d, "embeddings"), "design")
    exact = stored(scores.block_leverage(stored(stats.block_stats(rows, 40), "stats"), 40), "dist")
    out = []
    for kind in ("countsketch", "gaussian", "srht"):
        for dims in (0, 16):
            approx = stored(scores.approx_leverage(rows, 40, 512, dims, 3, kind), "approx")
            out.append((kind, dims, distances.misestimation(exact, approx).first()["beta"]))
    return spark.createDataFrame(out, "sketch string, projected_to int, beta double")


_SAMPLED = "u AS (SELECT block_id, " + ", ".join([f"count(*) FILTER (WHERE u < 0.3) AS m, count(*) AS n"] + [f"coalesce(sum(x{i} * x{j}) FILTER (WHERE u < 0.3), 0) AS s{i}{j}" for i, j in _D3]) + f" FROM (SELECT *, {sql_uniform(chr(39) + 'sample3' + chr(39), 'row_id')} AS u FROM design) GROUP BY block_id), up AS MATERIALIZED (SELECT block_id, " + ", ".join(f"s{i}{j} * n / greatest(m, 1) AS g{i}{j}" for i, j in _D3) + " FROM u), upt AS (SELECT " + ", ".join(f"sum(g{i}{j}) AS g{i}{j}" for i, j in _D3) + " FROM up)"


@query("s6_sampled", with_stats("lineitem", _SAMPLED, _inverse("upt", "uinv"), f"scored AS (SELECT block_id, greatest({_SCORE}, 1e-12) AS score FROM up, uinv)", body="SELECT block_id, round(score / sum(score) OVER (), 8) + 0.0 AS p FROM scored"))
def _(spark: SparkSession, d: str) -> DataFrame:
    """Block scores from three tenths of the rows."""
    return scores.sampled_scores(load(spark, d, "lineitem"), 3, 0.3, seed=3).select("block_id", rounded(F.col("p"), 8).alias("p"))


# ---- draws --------------------------------------------------------------------------------------------------------

_MANY = sql_draws(Q, RUNS * STEPS, SEED)


def many(spark: SparkSession, d: str) -> tuple:
    """held, total, weights of RUNS x STEPS independent sketches of the documents."""
    _, held, dist, total = block_scores(spark, d, "documents")
    return held, total, stored(sampling.weights(sampling.draw_blocks(stored(dist, "dist"), Q, RUNS * STEPS, SEED), Q), "weights")


@query("k14_identity", with_stats("documents", _MANY, body=f"SELECT block_id, round(sum(w) / {RUNS * STEPS}.0, 7) AS mean_weight FROM weights GROUP BY block_id"))
def _(spark: SparkSession, d: str) -> DataFrame:
    """The mean weight of every block over 240 sketches, which E[S'S] = I says is 1."""
    return sampling.mean_weights(many(spark, d)[2], RUNS * STEPS).select("block_id", F.round("mean_weight", 7).alias("mean_weight"))


_PI = f"lev AS (SELECT block_id, row_id, ({_ROW_LEVERAGE}) / 3 AS pi FROM design, inv), shares AS (SELECT block_id, sum(pi) AS p FROM lev GROUP BY block_id)"


@query("k6_row_draws", with_stats("documents", _PI, sql_draws(Q, STEPS, SEED, "shares"), f"spans AS (SELECT block_id, row_id, pi, sum(pi) OVER o - pi AS lo, CASE WHEN lead(row_id) OVER o IS NULL THEN 2.0 ELSE sum(pi) OVER o END AS hi FROM lev WINDOW o AS (PARTITION BY block_id ORDER BY row_id)), tries AS (SELECT *, {sql_uniform(chr(39) + 'row' + str(SEED) + chr(39), 'iteration', 'trial')} * p AS v FROM draws)", body=f"SELECT iteration, trial, row_id, round(1 / ({Q} * pi), 4) + 0.0 AS w FROM tries JOIN spans ON tries.block_id = spans.block_id AND v >= lo AND v < hi"))
def _(spark: SparkSession, d: str) -> DataFrame:
    """Single rows drawn with replacement by leverage: blocks of one row."""
    rows = scores.row_leverage(load(spark, d, "documents"), 3)
    return sampling.draw_rows(rows, Q, STEPS, SEED).select("iteration", "trial", "row_id", rounded(F.col("w"), 4).alias("w"))


# One column (and the label): closed forms of the 2 x 2 problem.
_ONE_COLUMN = ("dist1 AS MATERIALIZED (SELECT block_id, g11 / (SELECT g11 FROM tot) AS p FROM stats)", sql_draws(Q, STEPS, SEED, "dist1"), "sk1 AS (SELECT iteration, sum(w * s.g11) AS a, sum(w * s.c1) AS b, sum(w * s.btb) AS c FROM weights JOIN stats s USING (block_id) GROUP BY iteration)", "tr AS (SELECT iteration, a, b, c, (t.btb * a - 2 * t.c1 * b + t.g11 * c) / (t.g11 * t.btb - t.c1 * t.c1) AS trace, (a * c - b * b) / (t.g11 * t.btb - t.c1 * t.c1) AS det, t.g11, t.c1, t.btb FROM sk1, tot t)", "eps AS (SELECT *, greatest(abs(1 - (trace + sqrt(greatest(0, trace * trace - 4 * det))) / 2), abs(1 - (trace - sqrt(greatest(0, trace * trace - 4 * det))) / 2)) AS eps FROM tr)")


def one_column(spark: SparkSession, d: str) -> tuple:
    """total, list of sketched statistics and embedding errors of the second feature alone."""
    rows = load(spark, d, "documents").withColumn("features", F.array(F.get("features", F.lit(1))))
    held = stored(stats.block_stats(rows, 1), "stats")
    total = stats.collect_total(held, 1)
    dist = stored(scores.block_leverage(held, 1, total), "dist")
    made = sorted(sampling.sketched_stats(held, sampling.weights(sampling.draw_blocks(dist, Q, STEPS, SEED), Q), 1).collect(), key=lambda r: r["iteration"])
    return total, made, sampling.embedding_error(total, made, 1), sampling.embedding_error(total, made, 1, augmented=False)


@query("k10_embedding_error_closed", with_stats("documents", *_ONE_COLUMN, body="SELECT iteration, round(eps, 6) AS eps, round(abs(1 - a / g11), 6) AS eps_without_label FROM eps"))
def _(spark: SparkSession, d: str) -> DataFrame:
    """Embedding errors on [A | b] and on A for a design of one column."""
    _, made, both, alone = one_column(spark, d)
    return spark.createDataFrame([(r["iteration"], round(a, 6), round(b, 6)) for r, a, b in zip(made, both, alone, strict=True)], "iteration int, eps double, eps_without_label double")


@query("a5_gradient_error", with_stats("documents", *_ONE_COLUMN, body="SELECT iteration, round(2 * abs((a - g11) * 0.4 - (b - c1)), 5) AS error, round(2 * eps * sqrt(g11) * sqrt(g11 * 0.16 - 0.8 * c1 + btb), 4) AS bound FROM eps"))
def _(spark: SparkSession, d: str) -> DataFrame:
    """The sketched gradient's error at x = 0.4 and what the embedding error allows."""
    total, made, both, _ = one_column(spark, d)
    x, out = np.array([0.4]), []
    for r, eps in zip(made, both, strict=True):
        gap = 2 * ((r["gram"][0] - total.gram[0, 0]) * 0.4 - (r["atb"][0] - total.atb[0]))
        out.append((r["iteration"], round(float(abs(gap)), 5), round(metrics.gradient_error_bound(total, x, eps), 4)))
    return spark.createDataFrame(out, "iteration int, error double, bound double")


_SKEWS = "three AS MATERIALIZED (SELECT 'uniform' AS scores, block_id, 0.05::DOUBLE AS p FROM dist UNION ALL SELECT 'documents', block_id, p FROM dist UNION ALL SELECT 'degenerate', block_id, CASE WHEN block_id = 0 THEN 0.999 ELSE 0.001 / 19 END FROM dist), cdf AS (SELECT scores, block_id, sum(p) OVER o - p AS lo, CASE WHEN lead(block_id) OVER o IS NULL THEN 1.0 ELSE sum(p) OVER o END AS hi FROM three WINDOW o AS (PARTITION BY scores ORDER BY block_id)), trials AS (SELECT it.range AS iteration, tr.range AS trial, " + sql_uniform(f"'{SEED}'", "it.range", "tr.range") + " AS u FROM range(30) it, range(20) tr), zs AS (SELECT scores, iteration, count(*) / count(DISTINCT block_id) AS zeta FROM trials JOIN cdf ON u >= lo AND u < hi GROUP BY scores, iteration)"


@query("w7_compression_by_skew", with_stats("documents", _SKEWS, body="SELECT scores, round(avg(zeta), 6) AS zeta, round(any_value(expected), 6) AS expected FROM zs JOIN (SELECT scores, 20 / sum(1 - pow(1 - p, 20)) AS expected FROM three GROUP BY scores) USING (scores) GROUP BY scores"))
def _(spark: SparkSession, d: str) -> DataFrame:
    """zeta for uniform, measured and degenerate scores."""
    dist = stored(block_scores(spark, d, "documents")[2], "dist")
    point = dist.select("block_id", F.when(F.col("block_id") == 0, 0.999).otherwise(0.001 / 19).alias("p"))
    out = []
    for name, p in (("uniform", scores.uniform_scores(spark, 20)), ("documents", dist), ("degenerate", point)):
        r = sampling.compression(sampling.draw_blocks(p, 20, 30, SEED)).agg(F.avg("zeta").alias("z")).first()
        out.append((name, round(r["z"], 6), round(20 / sampling.expected_distinct(p, 20).first()["expected"], 6)))
    return spark.createDataFrame(out, "scores string, zeta double, expected double")


# ---- sketches -----------------------------------------------------------------------------------------------------


@query("x6_half_sketch", with_stats("documents", DRAWS, SQL_SKETCHED, "first AS (SELECT * FROM sk WHERE iteration = 0)", _inverse("first", "sinv"), body=" UNION ALL ".join(f"SELECT {i}::INT AS i, round({' + '.join(f'i{min(i, j)}{max(i, j)} * c{j}' for j in range(3))}, 5) + 0.0 AS v FROM sinv, tot" for i in range(3))))
def _(spark: SparkSession, d: str) -> DataFrame:
    """The second classical estimate: sketched Gram matrix, full right side."""
    _, held, _, total, _, w = drawn(spark, d)
    return vector_table(spark, sketches.half_sketch_solution(total, descent.sketch_totals(held, w, 3)[0]), 5)


# ---- networks -----------------------------------------------------------------------------------------------------


def _replies(iterations: int, servers: str = "") -> str:
    """law, servers, replies with another number of iterations, or other servers."""
    out = REPLIES.replace(f"range({STEPS}))", f"range({iterations}))")
    return out if not servers else out[: out.index("servers AS")] + servers + ",\n" + out[out.index("replies AS") :]


_FULL = ", ".join(f"2 * ({' + '.join(f'g{min(i, j)}{max(i, j)} * {X[j]}' for j in range(3))} - c{i}) AS f{i}" for i in range(3))
_AT = lambda t: ", ".join(f"2 * ({' + '.join(f'{t}.g{min(i, j)}{max(i, j)} * {X[j]}' for j in range(3))} - {t}.c{i}) AS f{i}" for i in range(3))
_SUMS = ", ".join([*(f"sum(w * s.g{i}{j}) AS g{i}{j}" for i, j in _D3), *(f"sum(w * s.c{i}) AS c{i}" for i in range(3))])
_BIAS = f"kinds AS (SELECT * FROM (VALUES ('none', 0), ('ten', 10)) t(late, least)), placed AS (SELECT late, iteration, block_id, row_number() OVER (PARTITION BY late, iteration ORDER BY t, server_id) AS place FROM replies, kinds WHERE server_id >= least), w AS (SELECT late, iteration, block_id, count(*) / ({Q} * any_value(r) / {M}.0) AS w FROM placed JOIN counts USING (block_id) WHERE place <= {Q} GROUP BY late, iteration, block_id), sks AS (SELECT late, iteration, {_SUMS} FROM w JOIN stats s USING (block_id) GROUP BY late, iteration), gs AS (SELECT late, iteration, {_FULL} FROM sks), whole AS (SELECT {_FULL} FROM tot)"


def _fastest(spark: SparkSession, counts: DataFrame, law: DataFrame, iterations: int, late: list[int]) -> DataFrame:
    """Weights of the Q fastest replies of every iteration."""
    share = small(counts.select("block_id", (F.col("r") / F.lit(float(M))).alias("p")))
    return sampling.weights(sampling.draw_fastest(network.simulate_responses(network.allocate(counts), law, iterations, SEED, late), Q).join(share, "block_id"), Q)


@query("n15_persistent_stragglers", with_stats("documents", _COUNTS, _replies(40), _BIAS, body="SELECT late, round(sqrt(" + " + ".join(f"pow(avg(g.f{i}) - any_value(whole.f{i}), 2)" for i in range(3)) + ") / sqrt(" + " + ".join(f"pow(any_value(whole.f{i}), 2)" for i in range(3)) + "), 6) AS relative_bias FROM gs g, whole GROUP BY late"))
def _(spark: SparkSession, d: str) -> DataFrame:
    """Servers 0..9 never answer: how far the mean of many sketched gradients is from the full one."""
    _, held, _, total = block_scores(spark, d, "documents")
    counts, law, x = counted(spark, d)[1], law_of(spark, d), np.array(X)
    full = 2 * (total.gram @ x - total.atb)
    out = []
    for name, late in (("none", []), ("ten", list(range(10)))):
        g = np.array([2 * (t.gram @ x - t.atb) for t in descent.sketch_totals(held, _fastest(spark, counts, law, 40, late), 3)])
        out.append((name, round(metrics.bias_and_variance(g, full)[0] / float(np.linalg.norm(full)), 6)))
    return spark.createDataFrame(out, "late string, relative_bias double")


_TWO_MODES = f"sks AS (SELECT 'with replacement' AS mode, iteration, {_SUMS} FROM weights w JOIN stats s USING (block_id) GROUP BY iteration UNION ALL SELECT 'fastest replies', iteration, {_SUMS} FROM (SELECT iteration, block_id, count(*) / ({Q} * any_value(r) / {M}.0) AS w FROM (SELECT *, row_number() OVER (PARTITION BY iteration ORDER BY t, server_id) AS place FROM replies) JOIN counts USING (block_id) WHERE place <= {Q} GROUP BY iteration, block_id) w JOIN stats s USING (block_id) GROUP BY iteration), gs AS (SELECT mode, iteration, {_FULL} FROM sks), whole AS (SELECT {_FULL} FROM tot)"


@query("a9_bias_and_variance", with_stats("documents", _COUNTS, _MANY, _replies(RUNS * STEPS), _TWO_MODES, body="SELECT mode, round(sqrt(" + " + ".join(f"pow(avg(g.f{i}) - any_value(whole.f{i}), 2)" for i in range(3)) + "), 4) AS bias, round(" + " + ".join(f"var_pop(g.f{i})" for i in range(3)) + ", 3) AS variance FROM gs g, whole GROUP BY mode"))
def _(spark: SparkSession, d: str) -> DataFrame:
    """Sketched gradients of 240 draws with replacement and of the 10 fastest of 60 replicas: distance of the mean, and spread."""
    held, total, w = many(spark, d)
    x = np.array(X)
    full = 2 * (total.gram @ x - total.atb)
    fastest = _fastest(spark, counted(spark, d)[1], law_of(spark, d), RUNS * STEPS, [])
    out = []
    for name, used in (("with replacement", w), ("fastest replies", fastest)):
        g = np.array([2 * (t.gram @ x - t.atb) for t in descent.sketch_totals(held, used, 3)])
        bias, variance = metrics.bias_and_variance(g, full)
        out.append((name, round(bias, 4), round(variance, 3)))
    return spark.createDataFrame(out, "mode string, bias double, variance double")


_EIGHT = "servers AS (SELECT range::INT AS server_id, (range // 2)::INT AS block_id FROM range(8))"
_PARTS = "parts AS (SELECT block_id // 5 AS grp, block_id, " + ", ".join(f"sum(2 * {RESID} * x{i}) AS g{i}" for i in range(3)) + " FROM design GROUP BY block_id)"
_COVER = "came AS (SELECT DISTINCT iteration, block_id AS grp FROM replies WHERE t <= 24)"


def _ring_code(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Partial gradients of 20 blocks, a code of 8 servers in groups of 2 with 5 blocks each, and the replies by 24."""
    parts = stored(gradients.partial_gradients(load(spark, d, "documents"), X), "parts")
    group = F.floor(F.col("server_id") / 2).cast("int")
    servers = spark.range(8).select(F.col("id").cast("int").alias("server_id")).withColumn("block_id", group)
    code = servers.select("server_id", F.explode(F.sequence(F.col("block_id") * 5, F.col("block_id") * 5 + 4)).alias("block_id"), F.lit(1.0).alias("c"))
    replies = network.simulate_responses(servers, law_of(spark, d), STEPS, SEED).where("t <= 24")
    return parts, code, stored(replies.select("iteration", "server_id"), "replies")


@query("c3_optimal_decoding", with_stats("documents", _replies(STEPS, _EIGHT), _PARTS, _COVER, body="SELECT iteration, " + ", ".join(f"round(sum(g{i}), 4) + 0.0 AS g{i}" for i in range(3)) + " FROM came JOIN parts USING (grp) GROUP BY iteration"))
def _(spark: SparkSession, d: str) -> DataFrame:
    """Replies that came by the deadline, decoded by the weights that come closest to a sum of all blocks."""
    return _spread(coding.decode_replies(*_ring_code(spark, d)), "iteration", digits=4)


_GROUPS = "groups AS (SELECT grp, " + ", ".join(f"sum(g{i}) AS g{i}" for i in range(3)) + " FROM parts GROUP BY grp), its AS (SELECT DISTINCT iteration FROM replies WHERE t <= 24), miss AS (SELECT iteration, " + ", ".join(f"coalesce(sum(g{i}) FILTER (WHERE came.grp IS NULL), 0) AS m{i}" for i in range(3)) + ", bool_or(came.grp IS NULL) AS lacks, sqrt(sum(g0 * g0 + g1 * g1 + g2 * g2)) AS norm FROM (SELECT * FROM its, groups) a LEFT JOIN came USING (iteration, grp) GROUP BY iteration)"


@query("c5_decoding_error", with_stats("documents", _replies(STEPS, _EIGHT), _PARTS, _COVER, _GROUPS, body="SELECT iteration, CASE WHEN lacks THEN 1.0 ELSE 0.0 END::DOUBLE AS err, round(sqrt(m0 * m0 + m1 * m1 + m2 * m2), 3) + 0.0 AS error, round(CASE WHEN lacks THEN 2 * norm ELSE 0.0 END, 3) AS bound FROM miss"))
def _(spark: SparkSession, d: str) -> DataFrame:
    """err = ||I - pinv(G) G||, the decoded gradient's error, and its bound; the code's four groups are its blocks."""
    parts, code, replies = _ring_code(spark, d)
    each = np.array([r["g"] for r in sorted(parts.collect(), key=lambda r: r["block_id"])])
    g = each.reshape(4, 5, -1).sum(1)
    matrix = coding.code_matrix(code, 8, 20)[:, ::5]
    out = []
    for iteration, came in sorted(coding.replies_by_iteration(replies).items()):
        error, bound = coding.decoded_gradient_bound(matrix, came, g)
        out.append((iteration, round(coding.decoding_error(matrix, came), 6) + 0.0, round(error, 3) + 0.0, round(bound, 3) if bound > 1e-6 else 0.0))
    return spark.createDataFrame(out, "iteration int, err double, error double, bound double")


_THREE_EACH = "servers AS (SELECT range::INT AS server_id, (range // 3)::INT AS block_id FROM range(60))"


@query("c4_uniform_gradient", with_stats("documents", _replies(STEPS, _THREE_EACH), _PARTS, body="SELECT iteration, " + ", ".join(f"round(20 / {Q}.0 * sum(g{i}), 3) + 0.0 AS g{i}" for i in range(3)) + f" FROM (SELECT *, row_number() OVER (PARTITION BY iteration ORDER BY t, server_id) AS place FROM replies) JOIN parts USING (block_id) WHERE place <= {Q} GROUP BY iteration"))
def _(spark: SparkSession, d: str) -> DataFrame:
    """Equal replicas, late ones ignored: the q replies' gradients over q times their share 1/K."""
    replies = network.simulate_responses(network.allocate(coding.uniform_code(spark, 20, M)), law_of(spark, d), STEPS, SEED)
    parts = stored(gradients.partial_gradients(load(spark, d, "documents"), X), "parts")
    return _spread(coding.uniform_decode(parts, sampling.draw_fastest(replies, Q), 20, Q), "iteration")


def _adjust_sql(start: str, keys: str, m: int, most: int) -> str:
    """``adjusted(keys, r)``: counts of ``start`` (keys, block_id, p, r) moved one by one until they sum to m.

    A row per key holds all counts as lists; every recursion moves one of them.
    """
    gap = "sign * (ps[i] - rs[i] / {m}.0)".replace("{m}", str(m))
    after = "sign * (ps[j] - (rs[j] - sign) / {m}.0)".replace("{m}", str(m))
    park = f"j = last AND gaps[j] < 0 AND {after} > 0"
    return f"""lists AS (SELECT {keys}, list(p ORDER BY block_id) AS ps, list(greatest(1, r)::BIGINT ORDER BY block_id) AS rs, list(block_id ORDER BY block_id) AS ids FROM {start} GROUP BY {keys}),
signed AS (SELECT *, CASE WHEN list_sum(rs) < {m} THEN -1 ELSE 1 END AS sign FROM lists),
moves({keys}, ps, rs, ids, sign, gaps, last, step) AS (
  SELECT {keys}, ps, rs, ids, sign, list_transform(range(1, len(ps) + 1), lambda i: CASE WHEN sign = 1 AND rs[i] <= 1 THEN 9.0 ELSE {gap} END), -1::BIGINT, 0 FROM signed
  UNION ALL
  SELECT {keys}, ps, CASE WHEN {park} THEN rs ELSE list_transform(range(1, len(ps) + 1), lambda i: CASE WHEN i = j THEN rs[i] - sign ELSE rs[i] END) END, ids, sign,
    list_transform(range(1, len(ps) + 1), lambda i: CASE WHEN i <> j THEN gaps[i] WHEN {park} THEN 1 + {after} WHEN sign = 1 AND rs[j] - sign <= 1 THEN 9.0 ELSE {after} END),
    CASE WHEN {park} THEN -1 ELSE j END, step + 1
  FROM (SELECT *, list_position(gaps, list_min(gaps))::BIGINT AS j FROM moves WHERE list_sum(rs) <> {m} AND step < {most})),
adjusted AS (SELECT {keys}, unnest(ids) AS block_id, unnest(ps) AS p, unnest(rs) AS r FROM moves WHERE list_sum(rs) = {m})"""


_STARTS = f"rounded AS (SELECT block_id, round(p, 12) AS p FROM dist), starts AS (SELECT 'scaled' AS start, block_id, p, greatest(1, floor(ln(1 - p) / ln(0.7) * 120 / (SELECT sum(ln(1 - p) / ln(0.7)) FROM rounded) + 0.5)) AS r FROM rounded UNION ALL SELECT 'ratio', block_id, p, floor(p / (SELECT min(p) FROM rounded WHERE p > 0) + 0.5) FROM rounded)"


@query("n9_adjust_replicas", with_stats("documents", _STARTS, _adjust_sql("starts", "start", M, 2000), body=f"SELECT start, block_id, r::BIGINT AS r, round(abs(p - r / {M}.0), 9) + 0.0 AS gap FROM adjusted", recursive=True))
def _(spark: SparkSession, d: str) -> DataFrame:
    """Counts adjusted one by one to 60 servers, from twice too many and from the ratio rule."""
    dist = stored(block_scores(spark, d, "documents")[2].select("block_id", F.round("p", 12).alias("p")), "dist")
    out = []
    for name, made in (("scaled", network.replicas_channel_scaled(dist, 0.7, 2 * M)), ("ratio", network.replicas_ratio(dist, 1))):
        rows = sorted((r["block_id"], r["p"], r["r"]) for r in made.select("block_id", "p", "r").collect())
        r = network.adjust_replicas([p for _, p, _ in rows], [c for *_, c in rows], M)
        out += [(name, b, int(v), round(abs(p - v / M), 9)) for (b, p, _), v in zip(rows, r, strict=True)]
    return spark.createDataFrame(out, "start string, block_id int, r long, gap double")


#: Fixed values of the published design: blocks and servers.
NETWORK_BLOCKS, NETWORK_SERVERS = 100, 500
ENDINGS = [6, 12, 24, 42, 48, 54, 60]
_HUNDRED = SQL["documents"].replace("doc_id % 20", f"doc_id % {NETWORK_BLOCKS}")


def _network_sql() -> str:
    base = with_stats("documents", body="").replace(SQL["documents"], _HUNDRED).strip()
    phis = "phis AS (SELECT ending, round(1 - f, 8) AS phi, floor(f * 500 + 1e-9)::BIGINT AS q FROM (" + " UNION ALL ".join(f"SELECT {t}.0::DOUBLE AS ending, avg(CASE WHEN value <= {t} THEN 1.0 ELSE 0.0 END) AS f FROM events" for t in ENDINGS) + "))"
    first = "rounded AS MATERIALIZED (SELECT block_id, round(p, 12) AS p FROM dist), rule AS MATERIALIZED (SELECT ending, phi, block_id, p, floor(ln(1 - p) / ln(phi) + 0.5) AS r0 FROM rounded, phis), totals AS (SELECT ending, sum(r0) AS total FROM rule GROUP BY ending), starts AS (SELECT ending, block_id, p, CASE WHEN total > 0 THEN floor(500 / total + 0.5) ELSE 0 END * r0 AS r FROM rule JOIN totals USING (ending))"
    body = "SELECT ending, any_value(q) AS q, round(avg(abs(p - (1 - pow(phi, r)))), 7) AS delta, round(least(1.0, min(r / 500.0 / p)), 7) AS beta, round(least(1.0, min(p / (r / 500.0))), 7) AS beta_printed, round(avg(abs(p - r / 500.0)), 9) AS d, any_value(zero)::BIGINT AS zero_counts FROM adjusted JOIN phis USING (ending) JOIN (SELECT ending, sum(CASE WHEN r0 = 0 THEN 1 ELSE 0 END) AS zero FROM rule GROUP BY ending) USING (ending) GROUP BY ending"
    return base.replace("WITH ", "WITH RECURSIVE ", 1) + ",\n" + phis + ",\n" + first + ",\n" + _adjust_sql("starts", "ending", NETWORK_SERVERS, 4000) + "\n" + body


@query("a11_network_table", _network_sql())
def _(spark: SparkSession, d: str) -> DataFrame:
    """The replica design at each ending time: channel counts for phi(T), taken as often as fits, adjusted to 500 servers; then q, Delta, beta, d."""
    rows = load(spark, d, "documents").withColumn("block_id", F.pmod("row_id", F.lit(NETWORK_BLOCKS)).cast("int"))
    dist = stored(scores.block_leverage(stored(stats.block_stats(rows, 3), "stats"), 3).select("block_id", F.round("p", 12).alias("p")), "dist")
    out = []
    for r in network.replies_by(table(spark, d, "events"), "value", ENDINGS, NETWORK_SERVERS).collect():
        phi = round(r["phi"], 8)
        counts = network.channel_counts(dist, phi, NETWORK_SERVERS, "multiple")
        share = counts.select("block_id", (F.col("r") / F.lit(float(NETWORK_SERVERS))).alias("p"))
        beta = distances.misestimation(dist, share).first()
        delta, gap = distances.channel_distortion(dist, counts, phi).first()["delta"], distances.distortion(dist, counts).first()["d"]
        zero = network.replicas_channel(dist, phi).where("r = 0").count()
        out.append((r["ending"], r["q"], round(delta, 7), round(beta["beta"], 7), round(beta["beta_printed"], 7), round(gap, 9), zero))
    return spark.createDataFrame(out, "ending double, q long, delta double, beta double, beta_printed double, d double, zero_counts long")


@query("n16_design_network")
def _(spark: SparkSession, d: str) -> DataFrame:
    """The channel rule's own total for several numbers of blocks, and which comes closest to the servers there are."""
    rows = stored(load(spark, d, "documents"), "design")

    def scores_for(k: int) -> DataFrame:
        cut = rows.withColumn("block_id", F.pmod("row_id", F.lit(k)).cast("int"))
        return stored(scores.block_leverage(stored(stats.block_stats(cut, 3), "stats"), 3), "dist")

    out = network.design_network(scores_for, table(spark, d, "events"), "value", 60.0, M, [2, 4, 6, 8, 10, 20])
    return spark.createDataFrame([(r["k"], int(r["rule_total"]), r["q"], r["beta"], r["d"], r["delta"], bool(r["chosen"])) for r in out], "k int, rule_total long, q long, beta double, d double, delta double, chosen boolean")


@query("g11_coded_descent_channel")
def _(spark: SparkSession, d: str) -> DataFrame:
    """The whole procedure with counts from the channel rule and the step-by-step adjustment, waiting until 24."""
    rows, _, dist, total = block_scores(spark, d, "documents", keep=True)
    dist = stored(dist, "dist")
    phi = network.replies_by(table(spark, d, "events"), "value", [24.0], M).first()["phi"]
    counts = network.channel_counts(dist, phi, M, "scaled")
    trace, _ = descent.coded_descent(stored_blocks(rows, BUCKETS), dist, law_of(spark, d), M, [0.0] * 3, fixed_step(xi_of(total)), Stop(STEPS), SEED, ending=24.0, counts=counts)
    return trace.table(spark).select("s", *[F.round(F.get("x", F.lit(i)), 6).alias(f"a{i}") for i in range(3)])


@query("p2_coded_cr", f"WITH {SQL['documents']}, {_PRODUCT}, {_ONE.replace('FROM dist', 'FROM pdist').replace('dist.block_id', 'pdist.block_id').replace('ppdist', 'pdist')}, {_replies(1)}, w AS (SELECT block_id, count(*) / (30 * any_value(r) / {M}.0) AS w FROM (SELECT *, row_number() OVER (ORDER BY t, server_id) AS place FROM replies) JOIN counts USING (block_id) WHERE place <= 30 GROUP BY block_id) " + " UNION ALL ".join(f"SELECT {i}::INT AS i, {j}::INT AS j, round(sum(w * p{i}{j}), 4) + 0.0 AS v FROM prod JOIN w USING (block_id)" for i, j in _CELLS))
def _(spark: SparkSession, d: str) -> DataFrame:
    return products.coded_cr(*_two(spark, d), 3, 2, M, law_of(spark, d), 30, SEED).select("i", "j", rounded(F.col("v"), 4).alias("v"))


# ---- descent ------------------------------------------------------------------------------------------------------

_LINE = "path(s, a0, a1, a2) AS (SELECT 0, 0.0::DOUBLE, 0.0::DOUBLE, 0.0::DOUBLE UNION ALL SELECT s + 1, a0 - t * r0, a1 - t * r1, a2 - t * r2 FROM (SELECT *, (r0 * r0 + r1 * r1 + r2 * r2) / (g00 * r0 * r0 + g11 * r1 * r1 + g22 * r2 * r2 + 2 * (g01 * r0 * r1 + g02 * r0 * r2 + g12 * r1 * r2)) AS t FROM (SELECT *, " + ", ".join(f"{' + '.join(f'g{min(i, j)}{max(i, j)} * a{j}' for j in range(3))} - c{i} AS r{i}" for i in range(3)) + " FROM path, tot WHERE s < 400)))"
_STOPS = "steps AS (SELECT s, 2 * sqrt(" + " + ".join(f"pow({' + '.join(f'g{min(i, j)}{max(i, j)} * a{j}' for j in range(3))} - c{i}, 2)" for i in range(3)) + ") AS grad, sqrt(pow(a0 - b0, 2) + pow(a1 - b1, 2) + pow(a2 - b2, 2)) AS far, sqrt(a0 * a0 + a1 * a1 + a2 * a2) AS size, sqrt(" + " + ".join(f"pow(lead(a{i}) OVER (ORDER BY s) - a{i}, 2)" for i in range(3)) + ") AS move FROM path, tot, best)"


@query("g13_stop_rules", with_stats("events", _BEST, _LINE, _STOPS, body="SELECT (SELECT min(s) + 1 FROM steps WHERE grad <= 3.0)::BIGINT AS by_gradient, (SELECT min(s) FROM steps WHERE far <= 0.003 AND s > 0)::BIGINT AS by_target, (SELECT min(s) + 1 FROM steps WHERE move <= 0.003 * size)::BIGINT AS by_step", recursive=True))
def _(spark: SparkSession, d: str) -> DataFrame:
    """Iterations until each rule ends a run with the exact line search."""
    total = block_scores(spark, d, "events")[3]
    run = lambda stop: len(descent.descend_on_stats(total, None, [0.0] * 3, descent.line_search(), stop).xs) - 1
    return one_row(spark, by_gradient=run(Stop(400, gradient_norm=3.0)), by_target=run(Stop(400, target=total.solution(), distance=0.003)), by_step=run(Stop(400, relative=0.003)))


_NEWTON = "path(s, a0, a1, a2) AS (SELECT 0, 0.0::DOUBLE, 0.0::DOUBLE, 0.0::DOUBLE UNION ALL SELECT s + 1, " + ", ".join("a{i} - ({h})".format(i=i, h=" + ".join(f"v.i{min(i, j)}{max(i, j)} * ({' + '.join(f'tot.g{min(j, k)}{max(j, k)} * a{k}' for k in range(3))} - tot.c{j})" for j in range(3))) for i in range(3)) + f" FROM path, tot, sinv v WHERE v.iteration = s AND s < {STEPS})"


@query("g15_newton", with_stats("documents", DRAWS, SQL_SKETCHED, _inverse("sk", "sinv", "iteration,"), _BEST, _NEWTON, body="SELECT (s - 1)::INT AS s, round(sum(pow(a0 * x0 + a1 * x1 + a2 * x2 - y, 2)) / sum(pow(b0 * x0 + b1 * x1 + b2 * x2 - y, 2)) - 1, 6) + 0.0 AS excess FROM path, best, design WHERE s > 0 GROUP BY s", recursive=True))
def _(spark: SparkSession, d: str) -> DataFrame:
    """Excess objective after Newton steps with fresh sketched Hessians."""
    _, held, _, total, _, w = drawn(spark, d)
    x, best, out = np.zeros(3), total.solution(), []
    for i, t in enumerate(descent.sketch_totals(held, w, 3)):
        x = descent.newton_step(total, t, x)
        out.append((i, round(total.objective(x) / total.objective(best) - 1, 6) + 0.0))
    return spark.createDataFrame(out, "s int, excess double")


def _runs_sql(steps: int, runs: int, xi: str, power: float = 0.0, shift: int = 1) -> str:
    """rpath(run, s, a0..): independent runs, run r with the sketches r steps .. (r + 1) steps - 1."""
    step = f"({xi}) / pow(s + {shift}, {power})" if power else f"({xi})"
    g = [f"2 * ({' + '.join(f'sk.g{min(i, j)}{max(i, j)} * a{j}' for j in range(3))} - sk.c{i})" for i in range(3)]
    return f"rpath(run, s, a0, a1, a2) AS (SELECT range, 0, 0.0::DOUBLE, 0.0::DOUBLE, 0.0::DOUBLE FROM range({runs}) UNION ALL SELECT run, s + 1, {', '.join(f'a{i} - {step} * ({g[i]})' for i in range(3))} FROM rpath JOIN sk ON iteration = run * {steps} + s WHERE s < {steps})"


@query("a8_contraction", with_stats("documents", _MANY, SQL_SKETCHED, _runs_sql(STEPS, RUNS, XI), sql_path(STEPS, XI, "tot"), body="SELECT s::INT AS s, " + ", ".join(f"round(any_value(m{i}), 5) + 0.0 AS mean{i}, round(any_value(a{i}), 5) + 0.0 AS plain{i}" for i in range(3)) + " FROM path JOIN (SELECT s, " + ", ".join(f"avg(a{i}) AS m{i}" for i in range(3)) + " FROM rpath GROUP BY s) USING (s) GROUP BY s", recursive=True))
def _(spark: SparkSession, d: str) -> DataFrame:
    """Mean iterates of 40 independent runs with scored draws beside plain descent, which they equal in expectation."""
    held, total, w = many(spark, d)
    step = fixed_step(xi_of(total))
    means = descent.many_runs(total, descent.sketch_totals(held, w, 3), [0.0] * 3, step, STEPS, RUNS).mean(0)
    plain = descent.many_runs(total, None, [0.0] * 3, step, STEPS, 1)[0]
    rows = [(s, *(round(float(v), 5) + 0.0 for pair in zip(means[s], plain[s], strict=True) for v in pair)) for s in range(STEPS + 1)]
    return spark.createDataFrame(rows, "s int, " + ", ".join(f"mean{i} double, plain{i} double" for i in range(3)))


@query("a8_contraction_rates")
def _(spark: SparkSession, d: str) -> DataFrame:
    """For several steps: the norm that bounds the mean error's contraction, the printed rate, and what 40 runs show."""
    held, total, w = many(spark, d)
    made, best, out = descent.sketch_totals(held, w, 3), total.solution(), []
    for share in (0.1, 0.2, 0.4):
        xi = xi_of(total, share)
        means = descent.many_runs(total, made, [0.0] * 3, fixed_step(xi), STEPS, RUNS).mean(0)
        far = np.linalg.norm(means - best, axis=1)
        rate = descent.contraction_rate(total, xi)
        out.append((share, rate["norm"], rate["largest"], float((far[-1] / far[0]) ** (1 / STEPS))))
    return spark.createDataFrame(out, "share double, norm double, largest double, seen double")


LONG, SEEDS = 200, 20
_LONG = sql_draws(Q, LONG * SEEDS, SEED)


def long_runs(spark: SparkSession, d: str, share: float, power: float, shift: float) -> tuple[stats.Total, np.ndarray]:
    """20 independent runs of 200 iterations on the events with a diminishing step."""
    _, held, dist, total = block_scores(spark, d, "events")
    w = sampling.weights(sampling.draw_blocks(stored(dist, "dist"), Q, LONG * SEEDS, SEED), Q)
    return total, descent.many_runs(total, descent.sketch_totals(held, w, 3), [0.0] * 3, descent.diminishing_step(xi_of(total, share), power, shift), LONG, SEEDS)


_OFF = ", ".join(f"a{i} - b{i} AS e{i}" for i in range(3))
_EXCESS = "g00 * e0 * e0 + g11 * e1 * e1 + g22 * e2 * e2 + 2 * (g01 * e0 * e1 + g02 * e0 * e2 + g12 * e1 * e2)"
_REGRETS = f"ex AS (SELECT s, avg({_EXCESS}) AS v FROM (SELECT run, s, {_OFF} FROM rpath, best WHERE s > 0), tot GROUP BY s), reg AS (SELECT s, sum(v) OVER (ORDER BY s) / s AS v FROM ex)"


@query("a6_regret_slope", with_stats("events", _LONG, SQL_SKETCHED, _BEST, _runs_sql(LONG, SEEDS, XI, 0.5), _REGRETS, body="SELECT round(regr_slope(ln(v), ln(s)), 4) AS slope, round(max(v) FILTER (WHERE s = 200), 4) AS last FROM reg", recursive=True))
def _(spark: SparkSession, d: str) -> DataFrame:
    """Slope of the regret, a mean over 20 runs with steps falling as 1/sqrt(s): -1/2 or steeper."""
    total, xs = long_runs(spark, d, 0.4, 0.5, 1.0)
    values = np.mean([metrics.regret(total, descent.Trace(list(run)), total.solution()) for run in xs], 0)
    return one_row(spark, slope=round(metrics.decay_slope(values), 4), last=round(float(values[-1]), 4))


@query("a7_squared_error_slope", with_stats("events", _LONG, SQL_SKETCHED, _BEST, _runs_sql(LONG, SEEDS, XI.replace("0.4", "14.0"), 1.0, 25), f"er AS (SELECT s, avg(e0 * e0 + e1 * e1 + e2 * e2) AS v FROM (SELECT run, s, {_OFF} FROM rpath, best WHERE s > 0) GROUP BY s)", body="SELECT round(regr_slope(ln(v), ln(s)), 4) AS slope, round(max(v) FILTER (WHERE s = 200), 5) AS last FROM er", recursive=True))
def _(spark: SparkSession, d: str) -> DataFrame:
    """Slope of the squared error, a mean over 20 runs; steps fall as 1/s, their factor near the inverse of the smallest curvature."""
    total, xs = long_runs(spark, d, 14.0, 1.0, 25.0)
    values = ((xs[:, 1:] - total.solution()) ** 2).sum(2).mean(0)
    return one_row(spark, slope=round(metrics.decay_slope(values), 4), last=round(float(values[-1]), 5))


_TRADE = "qs AS (SELECT * FROM (VALUES (2), (5), (10), (20), (40)) t(q)), wq AS (SELECT q, iteration, block_id, count(*) / (q * p) AS w FROM draws, qs WHERE trial < q GROUP BY q, iteration, block_id, p), sq AS MATERIALIZED (SELECT q, iteration, " + _SUMS.replace("sum(w *", "sum(wq.w *") + " FROM wq JOIN stats s USING (block_id) GROUP BY q, iteration)"
_TRADE_PATH = (
    "tpath(q, s, a0, a1, a2) AS (SELECT q, 0, 0.0::DOUBLE, 0.0::DOUBLE, 0.0::DOUBLE FROM qs UNION ALL SELECT q, s + 1, " + ", ".join(f"a{i} - t * d{i}" for i in range(3)) + " FROM (SELECT *, (d0 * r0 + d1 * r1 + d2 * r2) / (h00 * d0 * d0 + h11 * d1 * d1 + h22 * d2 * d2 + 2 * (h01 * d0 * d1 + h02 * d0 * d2 + h12 * d1 * d2)) AS t FROM (SELECT tpath.q, s, a0, a1, a2, "
    + ", ".join(f"2 * ({' + '.join(f'sq.g{min(i, j)}{max(i, j)} * a{j}' for j in range(3))} - sq.c{i}) AS d{i}, {' + '.join(f'tot.g{min(i, j)}{max(i, j)} * a{j}' for j in range(3))} - tot.c{i} AS r{i}" for i in range(3))
    + ", "
    + ", ".join(f"tot.g{i}{j} AS h{i}{j}" for i, j in _D3)
    + " FROM tpath JOIN sq ON tpath.q = sq.q AND sq.iteration = s, tot WHERE s < 40)))"
)


@query("a13_tradeoff", with_stats("documents", sql_draws(40, 40, SEED), _TRADE, _BEST, _TRADE_PATH, body="SELECT q::INT AS q, round(sqrt(pow(a0 - b0, 2) + pow(a1 - b1, 2) + pow(a2 - b2, 2)), 5) AS distance FROM tpath, best WHERE s = 40", recursive=True))
def _(spark: SparkSession, d: str) -> DataFrame:
    """Accuracy after a fixed number of steps against the number of draws."""
    _, held, dist, total = block_scores(spark, d, "documents")
    dist, best, out = stored(dist, "dist"), total.solution(), []
    for q in (2, 5, 10, 20, 40):
        w = sampling.weights(sampling.draw_blocks(dist, q, 40, SEED), q)
        trace = descent.descend_on_stats(total, descent.sketch_totals(held, w, 3), [0.0] * 3, descent.line_search(), Stop(40))
        out.append((q, round(float(np.linalg.norm(trace.xs[-1] - best)), 5)))
    return spark.createDataFrame(out, "q int, distance double")


@query("a10_prediction_floor", with_stats("documents", DRAWS, SQL_SKETCHED, "first AS (SELECT * FROM sk WHERE iteration = 0)", _inverse("first", "sinv"), "sol AS (SELECT " + ", ".join(f"{' + '.join(f'i{min(i, j)}{max(i, j)} * first.c{j}' for j in range(3))} AS b{i}" for i in range(3)) + " FROM sinv, first), used AS (SELECT sum(n * times) AS r FROM weights JOIN stats USING (block_id) WHERE iteration = 0)", body=f"SELECT any_value(r)::BIGINT AS rows, round(avg(pow((b0 - {PLANTED['documents'][0]}) * x0 + (b1 - {PLANTED['documents'][1]}) * x1 + (b2 + 2.0) * x2, 2)), 9) + 0.0 AS prediction_error, round(pow({NOISE['documents']}, 2) * 3 / least(any_value(r), count(*)), 9) + 0.0 AS floor FROM design, sol, used"))
def _(spark: SparkSession, d: str) -> DataFrame:
    """Prediction error of a sketch-and-solve estimate, and the floor under any estimate from as many rows."""
    rows, held, _, total, draws, w = drawn(spark, d)
    x = descent.sketch_totals(held, w, 3)[0].solution()
    r = w.where("iteration = 0").join(held.select("block_id", "n"), "block_id").agg(F.sum(F.col("n") * F.col("times")).alias("r")).first()["r"]
    error = metrics.prediction_error(rows, x.tolist(), PLANTED["documents"]).first()["prediction_error"]
    return one_row(spark, rows=int(r), prediction_error=round(error, 9) + 0.0, floor=round(metrics.prediction_floor(NOISE["documents"], 3, r, total.n), 9) + 0.0)


# ---- columns and rows ---------------------------------------------------------------------------------------------

_PAIR = f"WITH {SQL['events']}, g AS (SELECT count(*)::DOUBLE AS a, sum(x1) AS b, sum(x1 * x1) AS c FROM design), e AS (SELECT *, (a + c + sqrt((a - c) * (a - c) + 4 * b * b)) / 2 AS top FROM g), v AS (SELECT *, b * b / (b * b + (top - a) * (top - a)) AS first FROM e)"


def _two_columns(spark: SparkSession, d: str) -> tuple[DataFrame, stats.Total]:
    rows = load(spark, d, "events").withColumn("features", F.slice("features", 1, 2))
    return rows, stats.collect_total(stats.block_stats(rows, 2), 2)


@query("p5_columns", _PAIR + " SELECT 0::INT AS i, round(first, 8) AS leverage, first >= 0.5 AS chosen FROM v UNION ALL SELECT 1, round(1 - first, 8), first < 0.5 FROM v")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Column leverage in the best subspace of rank one, and the column chosen by it."""
    _, total = _two_columns(spark, d)
    order = products.select_columns(total, 1, 1)
    return spark.createDataFrame([(i, round(float(v), 8), i in order) for i, v in enumerate(products.column_leverage(total, 1))], "i int, leverage double, chosen boolean")


@query("p3_cur", _PAIR + ", top3 AS (SELECT row_number() OVER (ORDER BY lev DESC, row_id) - 1 AS place, x1 FROM (SELECT row_id, x1, round((c - 2 * b * x1 + a * x1 * x1) / (a * c - b * b), 12) AS lev FROM design, g)) SELECT place::INT AS place, round(x1, 9) AS x1, CASE WHEN first >= 0.5 THEN 0 ELSE 1 END::INT AS col, round(sqrt(CASE WHEN first >= 0.5 THEN c - b * b / a ELSE a - b * b / c END), 5) AS error FROM top3, v WHERE place < 3")
def _(spark: SparkSession, d: str) -> DataFrame:
    """CUR of two columns with one column and three rows: the rows, the column, and the error of the product."""
    rows, total = _two_columns(spark, d)
    scored = scores.row_leverage(rows, 2, total=total).withColumn("leverage", F.round("leverage", 12))
    columns, picked, u = products.cur(scored, total, 1, 1, 3)
    error = products.cur_error(total, columns, picked, u)
    return spark.createDataFrame([(i, round(p[1], 9), columns[0], round(error, 5)) for i, p in enumerate(picked)], "place int, x1 double, col int, error double")


@query("p6_top_rows", with_stats("documents", f"lev AS (SELECT block_id, row_id, round({_ROW_LEVERAGE}, 10) AS l FROM design, inv)", body="SELECT block_id, place::INT AS place, row_id FROM (SELECT *, row_number() OVER (PARTITION BY block_id ORDER BY l DESC, row_id) AS place FROM lev) WHERE place <= 3"))
def _(spark: SparkSession, d: str) -> DataFrame:
    """The three rows of largest leverage in each block."""
    rows = scores.row_leverage(load(spark, d, "documents"), 3).withColumn("leverage", F.round("leverage", 10))
    return products.top_rows(rows, 3).select("block_id", F.col("place").cast("int").alias("place"), "row_id")


@query("b4_blocks_range", "SELECT event_id, (" + " + ".join(f"(event_id > (SELECT quantile_disc(event_id, {i / 5}) FROM events))::INT" for i in range(1, 5)) + ")::INT AS block_id FROM events")
def _(spark: SparkSession, d: str) -> DataFrame:
    from blocksketch.operators import design

    return design.assign_blocks(load(spark, d, "events"), 5, "range").select(F.col("row_id").alias("event_id"), "block_id")


@query("b9_spectrum_three", with_stats("events", body="SELECT round(sqrt(g00 + g11 + g22), 5) AS frobenius, round(ln(g00 * (g11 * g22 - g12 * g12) - g01 * (g01 * g22 - g12 * g02) + g02 * (g01 * g12 - g11 * g02)), 5) AS log_volume FROM tot"))
def _(spark: SparkSession, d: str) -> DataFrame:
    """All three columns: root of the sum, and logarithm of the product, of the squared singular values."""
    total = block_scores(spark, d, "events")[3]
    values = np.linalg.eigvalsh(total.gram)
    return one_row(spark, frobenius=round(total.spectrum()["frobenius"], 5), log_volume=round(float(np.log(values).sum()), 5))


@query("u_replicas_udtf", "SELECT * FROM (VALUES (0::INT, 3::BIGINT), (1, 3), (2, 4), (3, 5), (4, 5)) AS t(block_id, r)")
def _(spark: SparkSession, d: str) -> DataFrame:
    udfs.register(spark)
    return spark.sql("SELECT * FROM bs_replicas(array(0.15D, 0.15D, 0.2D, 0.25D, 0.25D), 20)")
