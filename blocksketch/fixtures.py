"""Design views of the given tables, the same in Spark and in SQL.

``SQL[name]`` is a CTE ``design(row_id, block_id, x0.., y)`` for the oracle;
``load(spark, sf_dir, name)`` is the DataFrame.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from blocksketch.functions.core import hash_normal
from blocksketch.operators.design import design_matrix, plant_labels
from blocksketch.operators.scores import hashed_heavy_tail
from blocksketch.sources.tables import table

#: Planted parameters of each view.
PLANTED = {"lineitem": [1.0, 2.0, -1.0], "documents": [0.5, 1.0, -2.0], "events": [0.3, 1.0, 0.5], "star": [1.0, 0.5, -0.5, 0.2, 0.1, -0.3, 0.4]}
NOISE = {"lineitem": 0.5, "documents": 0.1, "events": 0.2, "star": 0.3}
BLOCKS = {"lineitem": 20, "documents": 20, "events": 31, "star": 25}
WIDTH = {"lineitem": 3, "documents": 3, "events": 3, "star": 7, "embeddings": 40}


def row_hash(key: Column) -> Column:
    """A 60-bit id from the row's own key."""
    return F.conv(F.substring(F.md5(key), 1, 15), 16, 10).cast("long")


def _lineitem(spark: SparkSession, d: str) -> DataFrame:
    key = F.concat_ws("|", *[F.col(c).cast("string") for c in ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")])
    return design_matrix(table(spark, d, "lineitem"), [F.col("l_quantity") / 50, F.col("l_extendedprice") / 1e5], F.lit(0.0), row_hash(key), F.pmod("l_orderkey", F.lit(20)))


def _documents(spark: SparkSession, d: str) -> DataFrame:
    lines = F.length("text") - F.length(F.regexp_replace("text", "\n", "")) + 1
    docs = table(spark, d, "documents").where("text is not null and n_chars is not null")
    return design_matrix(docs, [F.col("n_chars") / 1e4, lines / 100], F.lit(0.0), F.col("doc_id"), F.pmod("doc_id", F.lit(20)))


def _events(spark: SparkSession, d: str) -> DataFrame:
    return design_matrix(table(spark, d, "events"), [F.col("value") / 100, F.hour("ts") / 24], F.lit(0.0), F.col("event_id"), F.dayofmonth("ts"))


def _star(spark: SparkSession, d: str) -> DataFrame:
    t = lambda n: table(spark, d, n)
    rows = (
        t("lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity")
        .join(t("orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey", "o_totalprice"), "l_orderkey")
        .join(t("customer").select(F.col("c_custkey").alias("o_custkey"), "c_acctbal", "c_nationkey"), "o_custkey")
        .join(t("part").select(F.col("p_partkey").alias("l_partkey"), "p_retailprice", "p_size"), "l_partkey")
        .join(t("supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_acctbal"), "l_suppkey")
    )
    key = F.concat_ws("|", *[F.col(c).cast("string") for c in ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")])
    features = [F.col("l_quantity") / 50, F.col("o_totalprice") / 5e5, F.col("c_acctbal") / 1e4, F.col("p_retailprice") / 1e3, F.col("p_size") / 50, F.col("s_acctbal") / 1e4]
    return design_matrix(rows, features, F.lit(0.0), row_hash(key), F.col("c_nationkey"))


def _embeddings(spark: SparkSession, d: str, tau: int = 20) -> DataFrame:
    """The first 40 coordinates with a heavy-tailed row scale; contiguous blocks of 20 rows by vec_id."""
    vecs = table(spark, d, "embeddings")
    n = vecs.count()
    k = max(1, n // tau)
    scale = hashed_heavy_tail("vec_id")
    features = [F.get("embedding", F.lit(i)).cast("double") * scale for i in range(40)]
    base = design_matrix(vecs, features, F.lit(0.0), F.col("vec_id"), F.floor(F.col("vec_id") * k / n), intercept=False)
    return plant_labels(base, [0.1 * (i % 7 - 3) for i in range(40)], 0.1)


_LOADERS = {"lineitem": _lineitem, "documents": _documents, "events": _events, "star": _star}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A design view with planted labels."""
    if name == "embeddings":
        return _embeddings(spark, sf_dir)
    return plant_labels(_LOADERS[name](spark, sf_dir), PLANTED[name], NOISE[name])


def sql_int(*parts: str) -> str:
    """The SQL twin of ``hash_int``; parts are SQL expressions."""
    return f"('0x' || substr(md5(concat_ws('|', {', '.join(parts)})), 1, 8))::BIGINT"


def sql_uniform(*parts: str) -> str:
    return f"({sql_int(*parts)} / 4294967296.0::DOUBLE)"


def sql_normal(*parts: str) -> str:
    first, second = sql_int("'r'", *parts), sql_uniform("'t'", *parts)
    return f"(sqrt(-2.0::DOUBLE * ln(({first} + 1) / 4294967297.0::DOUBLE)) * cos(2.0::DOUBLE * pi() * {second}))"


def _labelled(name: str, inner: str) -> str:
    x = PLANTED[name]
    dot = " + ".join(f"({v!r})::DOUBLE * x{i}" for i, v in enumerate(x))
    cols = ", ".join(f"x{i}" for i in range(len(x)))
    noise = sql_normal("'noise'", "row_id")
    return f"design AS MATERIALIZED (SELECT row_id, block_id, {cols}, {dot} + {NOISE[name]!r}::DOUBLE * {noise} AS y FROM ({inner}))"


_KEY = "md5(concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber))"
SQL: dict[str, str] = {
    "lineitem": _labelled("lineitem", f"SELECT ('0x' || substr({_KEY}, 1, 15))::BIGINT AS row_id, (l_orderkey % 20)::INT AS block_id, 1.0::DOUBLE AS x0, l_quantity / 50 AS x1, l_extendedprice / 1e5 AS x2 FROM lineitem"),
    "documents": _labelled("documents", "SELECT doc_id AS row_id, (doc_id % 20)::INT AS block_id, 1.0::DOUBLE AS x0, n_chars / 1e4 AS x1, (length(text) - length(replace(text, chr(10), '')) + 1) / 100.0::DOUBLE AS x2 FROM documents WHERE text IS NOT NULL AND n_chars IS NOT NULL"),
    "events": _labelled("events", "SELECT event_id AS row_id, day(ts)::INT AS block_id, 1.0::DOUBLE AS x0, value / 100 AS x1, hour(ts) / 24.0::DOUBLE AS x2 FROM events"),
    "star": _labelled("star", f"SELECT ('0x' || substr({_KEY}, 1, 15))::BIGINT AS row_id, c_nationkey::INT AS block_id, 1.0::DOUBLE AS x0, l_quantity / 50 AS x1, o_totalprice / 5e5 AS x2, c_acctbal / 1e4 AS x3, p_retailprice / 1e3 AS x4, p_size / 50.0::DOUBLE AS x5, s_acctbal / 1e4 AS x6 FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey"),
}

_PAIRS = [(i, j) for i in range(3) for j in range(i, 3)]
_SUMS = ", ".join([*(f"sum(x{i} * x{j}) AS g{i}{j}" for i, j in _PAIRS), *(f"sum(x{i} * y) AS c{i}" for i in range(3)), "sum(y * y) AS btb"])
_AGAIN = ", ".join([*(f"sum(g{i}{j}) AS g{i}{j}" for i, j in _PAIRS), *(f"sum(c{i}) AS c{i}" for i in range(3)), "sum(btb) AS btb"])
_WEIGHTED = ", ".join([*(f"sum(w * g{i}{j}) AS g{i}{j}" for i, j in _PAIRS), *(f"sum(w * c{i}) AS c{i}" for i in range(3)), "sum(w * btb) AS btb"])
#: Block statistics, their total, its closed inverse and the block leverage distribution, for three columns.
SQL_STATS = f"""stats AS MATERIALIZED (SELECT block_id, count(*)::BIGINT AS n, {_SUMS} FROM design GROUP BY block_id),
tot AS MATERIALIZED (SELECT sum(n)::BIGINT AS n, {_AGAIN} FROM stats),
det AS (SELECT *, g00 * (g11 * g22 - g12 * g12) - g01 * (g01 * g22 - g12 * g02) + g02 * (g01 * g12 - g11 * g02) AS det FROM tot),
inv AS MATERIALIZED (SELECT (g11 * g22 - g12 * g12) / det AS i00, (g02 * g12 - g01 * g22) / det AS i01, (g01 * g12 - g02 * g11) / det AS i02,
  (g00 * g22 - g02 * g02) / det AS i11, (g01 * g02 - g00 * g12) / det AS i12, (g00 * g11 - g01 * g01) / det AS i22 FROM det),
dist AS MATERIALIZED (SELECT block_id, (i00 * g00 + 2 * i01 * g01 + 2 * i02 * g02 + i11 * g11 + 2 * i12 * g12 + i22 * g22) / 3 AS p FROM stats, inv)"""


def sql_draws(q: int, iterations: int, seed: int, dist: str = "dist") -> str:
    """draws(iteration, trial, block_id, p) and weights(iteration, block_id, times, w) from ``dist``."""
    u = sql_uniform(f"'{seed}'", "it.range", "tr.range")
    return f"""cdf AS (SELECT block_id, p, sum(p) OVER (ORDER BY block_id) - p AS lo, CASE WHEN lead(block_id) OVER (ORDER BY block_id) IS NULL THEN 1.0 ELSE sum(p) OVER (ORDER BY block_id) END AS hi FROM {dist}),
trials AS (SELECT it.range::INT AS iteration, tr.range::INT AS trial, {u} AS u FROM range({iterations}) it, range({q}) tr),
draws AS MATERIALIZED (SELECT iteration, trial, block_id, p FROM trials JOIN cdf ON u >= lo AND u < hi),
weights AS MATERIALIZED (SELECT iteration, block_id, count(*)::BIGINT AS times, count(*) / ({q} * p) AS w FROM draws GROUP BY iteration, block_id, p)"""


SQL_SKETCHED = f"sk AS MATERIALIZED (SELECT iteration, {_WEIGHTED} FROM weights JOIN stats USING (block_id) GROUP BY iteration)"


def sql_path(steps: int, xi: str, source: str = "sk", project: float | None = None, ridge: float = 0.0) -> str:
    """path(s, a0, a1, a2): descent by recursion; ``source`` has a row per iteration, or is the single row ``tot``."""
    g = [f"2 * ({' + '.join(f'g{min(i, j)}{max(i, j)} * a{j}' for j in range(3))} - c{i})" + (f" + {2 * ridge} * a{i}" if ridge else "") for i in range(3)]
    join = "" if source == "tot" else " AND iteration = s"
    inner = f"SELECT s + 1 AS s, {', '.join(f'a{i} - ({xi}) * ({g[i]}) AS a{i}' for i in range(3))} FROM path, {source} WHERE s < {steps}{join}"
    if project:
        size = "sqrt(a0 * a0 + a1 * a1 + a2 * a2)"
        inner = f"SELECT s, {', '.join(f'a{i} * CASE WHEN {size} > {project} THEN {project} / {size} ELSE 1.0 END' for i in range(3))} FROM ({inner})"
    return f"path(s, a0, a1, a2) AS (SELECT 0, 0.0::DOUBLE, 0.0::DOUBLE, 0.0::DOUBLE UNION ALL {inner})"
