"""Registered queries, third part: relational operators, streams, SQL functions and whole experiments."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from blocksketch import sqlapi, workloads
from blocksketch.fixtures import SQL, load
from blocksketch.functions import udfs
from blocksketch.functions.core import rounded
from blocksketch.operators import network, relational, sampling, scores, sketches, stats
from blocksketch.queries import DRAWS, Q, SEED, STEPS, block_scores, drawn, query, replied, with_stats
from blocksketch.queries_methods import _REPLY_SQL
from blocksketch.sources import generated
from blocksketch.sources.tables import stored, table
from blocksketch.streaming import events as ev


@query("r_join_broadcast", "SELECT n_name, count(*)::BIGINT AS n, round(sum(c_acctbal), 2) AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def _(spark: SparkSession, d: str) -> DataFrame:
    both = table(spark, d, "customer").join(F.broadcast(table(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    return both.groupBy("n_name").agg(F.count("*").alias("n"), F.round(F.sum("c_acctbal"), 2).alias("balance"))


@query("r_join_sortmerge", "SELECT flag, count(*)::BIGINT AS n, round(sum(o_totalprice) / 1e6, 4) AS total FROM (SELECT l_orderkey, l_returnflag AS flag FROM lineitem) JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def _(spark: SparkSession, d: str) -> DataFrame:
    both = table(spark, d, "lineitem").select("l_orderkey", "l_returnflag").join(table(spark, d, "orders").select("o_orderkey", "o_totalprice").hint("merge"), F.col("l_orderkey") == F.col("o_orderkey"))
    return both.groupBy(F.col("l_returnflag").alias("flag")).agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice") / 1e6, 4).alias("total"))


@query("r_join_range_cdf", "WITH b AS (SELECT range AS b, range * 10.0 AS lo, range * 10.0 + 10.0 AS hi FROM range(60)) SELECT b::BIGINT AS b, count(*)::BIGINT AS n FROM events JOIN b ON value >= lo AND value < hi GROUP BY b")
def _(spark: SparkSession, d: str) -> DataFrame:
    spans = spark.range(60).select(F.col("id").alias("b"), (F.col("id") * 10.0).alias("lo"), (F.col("id") * 10.0 + 10.0).alias("hi"))
    return relational.interval_join(table(spark, d, "events").select("value"), spans, "value", "lo", "hi", 7.0).groupBy("b").agg(F.count("*").alias("n"))


@query("r_join_asof", "WITH a AS (SELECT event_id, user_id, ts FROM events WHERE event_type = (SELECT min(event_type) FROM events)), b AS (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = (SELECT max(event_type) FROM events) GROUP BY ALL) SELECT event_id, b.value AS last_value FROM a ASOF LEFT JOIN b ON a.user_id = b.user_id AND a.ts >= b.ts")
def _(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events")
    low, high = e.agg(F.min("event_type").alias("a"), F.max("event_type").alias("b")).first()
    left = e.where(F.col("event_type") == low).select("event_id", "user_id", "ts")
    right = e.where(F.col("event_type") == high).groupBy("user_id", "ts").agg(F.max("value").alias("last_value"))
    return relational.asof_join(left, right, "ts", ["user_id"], ["last_value"]).select("event_id", "last_value")


@query("r_join_interval", _REPLY_SQL.format("SELECT iteration, floor(t / 6)::BIGINT AS slot, count(*)::BIGINT AS n FROM replies WHERE t < 60 GROUP BY ALL"))
def _(spark: SparkSession, d: str) -> DataFrame:
    spans = spark.range(10).select(F.col("id").alias("slot"), (F.col("id") * 6.0).alias("lo"), (F.col("id") * 6.0 + 6.0).alias("hi"))
    return relational.interval_join(replied(spark, d)[1], spans, "t", "lo", "hi", 6.0).groupBy("iteration", "slot").agg(F.count("*").alias("n"))


@query("r_semi_drawn", with_stats("documents", DRAWS, body="SELECT row_id FROM design WHERE block_id IN (SELECT block_id FROM draws WHERE iteration = 0)"))
def _(spark: SparkSession, d: str) -> DataFrame:
    rows, _, _, _, draws, _ = drawn(spark, d)
    return rows.join(F.broadcast(draws.where("iteration = 0").select("block_id").distinct()), "block_id", "left_semi").select("row_id")


@query("r_anti_stragglers", _REPLY_SQL.format("SELECT i.range::INT AS iteration, server_id FROM servers, range(6) i WHERE (i.range, server_id) NOT IN (SELECT iteration, server_id FROM replies WHERE t <= 24)"))
def _(spark: SparkSession, d: str) -> DataFrame:
    counts, replies = replied(spark, d)
    each = network.allocate(counts).crossJoin(spark.range(STEPS).select(F.col("id").cast("int").alias("iteration")))
    return each.join(replies.where("t <= 24").select("iteration", "server_id"), ["iteration", "server_id"], "left_anti").select("iteration", "server_id")


@query("r_outer_compare", with_stats("documents", DRAWS, body="SELECT dist.block_id, round(p, 8) + 0.0 AS p, coalesce(n, 0)::BIGINT AS n FROM dist LEFT JOIN (SELECT block_id, count(*) AS n FROM draws WHERE iteration = 1 GROUP BY block_id) USING (block_id)"))
def _(spark: SparkSession, d: str) -> DataFrame:
    _, _, dist, _, draws, _ = drawn(spark, d)
    seen = draws.where("iteration = 1").groupBy("block_id").agg(F.count("*").alias("n"))
    return dist.join(seen, "block_id", "full").select("block_id", rounded(F.col("p"), 8).alias("p"), F.coalesce("n", F.lit(0)).alias("n"))


def _regional(spark: SparkSession, d: str) -> DataFrame:
    c, n = table(spark, d, "customer"), table(spark, d, "nation")
    rows = c.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey"))
    return rows.select("n_regionkey", "c_mktsegment", F.array(F.lit(1.0), F.col("c_acctbal") / 1e4).alias("features"))


def _keys() -> list[Column]:
    """Grouping keys with -1 and 'all' where a set leaves them out."""
    return [F.coalesce("n_regionkey", F.lit(-1)).alias("region"), F.coalesce("c_mktsegment", F.lit("all")).alias("segment")]


_REG = "FROM customer JOIN nation ON c_nationkey = n_nationkey"
_REG_SUM = "count(*)::BIGINT AS n, round(sum(c_acctbal / 1e4), 8) + 0.0 AS g01, round(sum(pow(c_acctbal / 1e4, 2)), 8) + 0.0 AS g11"
for _kind, _clause in (("rollup", "ROLLUP (n_regionkey, c_mktsegment)"), ("cube", "CUBE (n_regionkey, c_mktsegment)"), ("group", "n_regionkey, c_mktsegment")):
    _id = {"rollup": "r_rollup_stats", "cube": "r_cube_stats", "group": "r_group_stats"}[_kind]
    query(_id, f"SELECT coalesce(n_regionkey, -1)::INT AS region, coalesce(c_mktsegment, 'all') AS segment, {_REG_SUM} {_REG} GROUP BY {_clause}")(lambda spark, d, kind=_kind: relational.grouped_stats(_regional(spark, d), 2, kind, "n_regionkey", "c_mktsegment").select(*_keys(), "n", rounded(F.col("g01"), 8).alias("g01"), rounded(F.col("g11"), 8).alias("g11")))


@query("r_grouping_sets", f"SELECT coalesce(n_regionkey, -1)::INT AS region, coalesce(c_mktsegment, 'all') AS segment, count(*)::BIGINT AS n {_REG} GROUP BY GROUPING SETS ((n_regionkey), (c_mktsegment), ())")
def _(spark: SparkSession, d: str) -> DataFrame:
    rows = _regional(spark, d)
    return rows.groupingSets([["n_regionkey"], ["c_mktsegment"], []], "n_regionkey", "c_mktsegment").agg(F.count("*").alias("n")).select(*_keys(), "n")


@query("r_distinct", "SELECT DISTINCT event_type, user_id FROM events")
def _(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events").select("event_type", "user_id").distinct()


@query("r_approx_distinct")
def _(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("approx"), F.count_distinct("l_partkey").alias("exact"))


@query("r_window_rank", "SELECT event_id, rank() OVER (PARTITION BY event_type ORDER BY value DESC, event_id)::INT AS place FROM events QUALIFY place <= 5")
def _(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("event_type").orderBy(F.col("value").desc(), "event_id")
    return table(spark, d, "events").select("event_id", F.rank().over(w).alias("place")).where("place <= 5")


@query("r_window_frame", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS smooth FROM events")
def _(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)
    return table(spark, d, "events").select("event_id", F.round(F.avg("value").over(w), 6).alias("smooth"))


@query("r_topk_blocks", with_stats("documents", body="SELECT block_id, round(p, 8) + 0.0 AS p FROM dist ORDER BY p DESC, block_id LIMIT 5"))
def _(spark: SparkSession, d: str) -> DataFrame:
    return block_scores(spark, d, "documents")[2].orderBy(F.col("p").desc(), "block_id").limit(5).select("block_id", rounded(F.col("p"), 8).alias("p"))


_SETS = {"union_sketches": "UNION ALL", "intersect_draws": "INTERSECT", "except_draws": "EXCEPT"}
for _n, _op in _SETS.items():

    def _set(spark: SparkSession, d: str, op: str = _op) -> DataFrame:
        draws = drawn(spark, d)[4]
        a, b = (draws.where(F.col("iteration") == i).select("block_id") for i in (0, 1))
        return {"UNION ALL": a.unionByName(b), "INTERSECT": a.intersect(b), "EXCEPT": a.subtract(b)}[op]

    query(f"r_{_n}", with_stats("documents", DRAWS, body=f"SELECT block_id FROM draws WHERE iteration = 0 {_op} SELECT block_id FROM draws WHERE iteration = 1"))(_set)


@query("r_string_features", "SELECT page_id, length(html)::INT AS size, (length(html) - length(replace(html, '<', '')))::INT AS tags, starts_with(url, 'https') AS secure FROM pages")
def _(spark: SparkSession, d: str) -> DataFrame:
    size = F.length("html")
    return table(spark, d, "pages").select("page_id", size.alias("size"), (size - F.length(F.translate("html", "<", ""))).alias("tags"), F.col("url").startswith("https").alias("secure"))


@query("r_date_features", "SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, dayofyear(o_orderdate)::INT AS day FROM orders")
def _(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.dayofyear("o_orderdate").alias("day"))


@query("r_array_features", "SELECT vec_id, round(list_max(embedding)::DOUBLE, 6) AS top, round(list_aggregate(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE), 'sum'), 6) AS norm2 FROM embeddings")
def _(spark: SparkSession, d: str) -> DataFrame:
    v = F.transform("embedding", lambda x: x.cast("double"))
    return table(spark, d, "embeddings").select("vec_id", F.round(F.array_max(v), 6).alias("top"), F.round(F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x), 6).alias("norm2"))


@query("r_map_weights", with_stats("documents", DRAWS, body="SELECT iteration, round(sum(w * n), 5) AS weighted_rows FROM weights JOIN stats USING (block_id) GROUP BY iteration"))
def _(spark: SparkSession, d: str) -> DataFrame:
    """Weights as a map per iteration, opened again to meet the blocks."""
    _, held, _, _, _, w = drawn(spark, d)
    maps = w.groupBy("iteration").agg(F.map_from_entries(F.collect_list(F.struct("block_id", "w"))).alias("m"))
    each = maps.select("iteration", F.explode("m").alias("block_id", "w"))
    return each.join(held.select("block_id", "n"), "block_id").groupBy("iteration").agg(F.round(F.sum(F.col("w") * F.col("n")), 5).alias("weighted_rows"))


@query("r_json_props", "SELECT event_type, count(*)::BIGINT AS n, sum(CAST(props->>'$.k' AS BIGINT))::BIGINT AS k FROM events GROUP BY event_type")
def _(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.sum(F.get_json_object("props", "$.k").cast("long")).alias("k"))


@query("r_salted_sum", "SELECT event_type, round(sum(value), 4) AS total, count(*)::BIGINT AS n FROM events GROUP BY event_type")
def _(spark: SparkSession, d: str) -> DataFrame:
    return relational.salted_sum(table(spark, d, "events").select("event_id", "event_type", "value"), "event_type", "value").withColumn("total", F.round("total", 4))


@query("r_anti_unlabelled", "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def _(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents").select("doc_id").join(table(spark, d, "labels").select("doc_id"), "doc_id", "left_anti")


@query("r_quality_by_features", "SELECT quality, count(*)::BIGINT AS n, round(avg(n_chars), 4) AS chars FROM documents JOIN labels USING (doc_id) GROUP BY quality")
def _(spark: SparkSession, d: str) -> DataFrame:
    both = table(spark, d, "documents").select("doc_id", "n_chars").join(table(spark, d, "labels").select("doc_id", "quality"), "doc_id")
    return both.groupBy("quality").agg(F.count("*").alias("n"), F.round(F.avg("n_chars"), 4).alias("chars"))


@query("r_conversation_turns", "SELECT role, count(*)::BIGINT AS n, sum(length(text))::BIGINT AS chars, max(turn)::BIGINT AS last FROM conversations GROUP BY role")
def _(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "conversations").groupBy("role").agg(F.count("*").alias("n"), F.sum(F.length("text")).alias("chars"), F.max("turn").alias("last"))


# ---- streams ------------------------------------------------------------------------------------------------------


def _ts() -> Column:
    return F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start")


@query("t1_tumbling_stats", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, count(*)::BIGINT AS n, round(sum(value / 100), 6) AS g01, round(sum(pow(value / 100, 2)), 6) AS g11 FROM events GROUP BY 1")
def _(spark: SparkSession, d: str) -> DataFrame:
    return ev.finish(ev.tumbling_stats(ev.read_events(spark, d))).select(_ts(), "n", F.round("g01", 6).alias("g01"), F.round("g11", 6).alias("g11"))


@query("t2_sliding_stats", "SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, count(*)::BIGINT AS n, round(sum(value), 4) AS total FROM (SELECT value, unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS s FROM events) GROUP BY 1")
def _(spark: SparkSession, d: str) -> DataFrame:
    return ev.finish(ev.sliding_stats(ev.read_events(spark, d))).select(_ts(), "n", F.round("total", 4).alias("total"))


@query("t3_session_stats", "WITH g AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*)::BIGINT AS n, round(sum(value), 4) AS total FROM s GROUP BY user_id, k")
def _(spark: SparkSession, d: str) -> DataFrame:
    return ev.session_stats(ev.batch_events(spark, d)).select("user_id", _ts(), "n", F.round("total", 4).alias("total"))


@query("t3_session_stream")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Sessions that the watermark has closed."""
    return ev.finish(ev.session_stats(ev.read_events(spark, d)), "append")


@query("t4_late_rows", "SELECT count(*) FILTER (WHERE ts >= TIMESTAMP '2024-01-20')::BIGINT AS kept, count(*) FILTER (WHERE ts < TIMESTAMP '2024-01-20')::BIGINT AS late FROM events")
def _(spark: SparkSession, d: str) -> DataFrame:
    """The last days are replayed before the first ones, which are late then: counted, not only dropped.

    A batch is judged by the watermark that the batch before the last had left, so two batches go first.
    """
    events = ev.batch_events(spark, d).select("event_id", "ts")
    path = ev.replay(events, ["2024-01-20", "2024-01-25", "2024-01-25", "2025-01-01", "2023-01-01", "2024-01-20"])
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(path)
    return ev.count_late(stream)


@query("t5_deadline_replies", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, sum(CASE WHEN value <= 24 THEN 1 ELSE 0 END)::BIGINT AS came, sum(CASE WHEN value <= 24 THEN 0 ELSE 1 END)::BIGINT AS late FROM events GROUP BY 1")
def _(spark: SparkSession, d: str) -> DataFrame:
    return ev.finish(ev.replies_by_deadline(ev.read_events(spark, d), 24.0)).select(_ts(), "came", "late")


@query("t6_running_gram", "SELECT count(*)::BIGINT AS n, round(sum(value / 100), 6) AS g01, round(sum(pow(value / 100, 2)), 6) AS g11 FROM events")
def _(spark: SparkSession, d: str) -> DataFrame:
    return ev.running_gram(ev.read_events(spark, d)).select("n", F.round("g01", 6).alias("g01"), F.round("g11", 6).alias("g11"))


@query("t7_stream_static", "SELECT event_type, round(sum(value * length(event_type)), 4) AS weighted, count(*)::BIGINT AS n FROM events GROUP BY event_type")
def _(spark: SparkSession, d: str) -> DataFrame:
    weights = table(spark, d, "events").select("event_type").distinct().select("event_type", F.length("event_type").cast("double").alias("w"))
    return ev.finish(ev.weighted_by_static(ev.read_events(spark, d), stored(weights, "weights"))).select("event_type", F.round("weighted", 4).alias("weighted"), "n")


@query("t8_dedup_stream", "SELECT DISTINCT event_id FROM events")
def _(spark: SparkSession, d: str) -> DataFrame:
    return ev.finish(ev.first_of_each(ev.read_events(spark, d)).select("event_id"), "append")


@query("t9_stream_sketch", "WITH e AS (SELECT *, ('0x' || substr(md5(concat_ws('|', 'cs0', event_id)), 1, 8))::BIGINT % 16 AS b, CASE WHEN ('0x' || substr(md5(concat_ws('|', 'sg0', event_id)), 1, 8))::BIGINT % 2 = 0 THEN 1.0 ELSE -1.0 END AS s FROM events) SELECT b::INT AS sketch_row, round(sum(s), 6) + 0.0 AS s0, round(sum(s * value / 100), 6) + 0.0 AS s1 FROM e GROUP BY b")
def _(spark: SparkSession, d: str) -> DataFrame:
    return ev.finish(ev.hashed_sketch(ev.read_events(spark, d))).select("sketch_row", rounded(F.col("s0"), 6).alias("s0"), rounded(F.col("s1"), 6).alias("s1"))


# ---- SQL functions ------------------------------------------------------------------------------------------------


@query("u_dot", f"WITH {SQL['lineitem']} SELECT row_id, round(0.2 * x0 - 0.4 * x1 + 0.7 * x2, 9) + 0.0 AS v FROM design")
def _(spark: SparkSession, d: str) -> DataFrame:
    udfs.register(spark)
    load(spark, d, "lineitem").createOrReplaceTempView("bs_design")
    return spark.sql("SELECT row_id, round(bs_dot(features, array(0.2D, -0.4D, 0.7D)), 9) + 0.0D AS v FROM bs_design")


@query("u_gram_udaf", with_stats("events", body="SELECT block_id, round(g01, 5) + 0.0 AS g01, round(g22, 5) + 0.0 AS g22 FROM stats"))
def _(spark: SparkSession, d: str) -> DataFrame:
    udfs.register(spark)
    load(spark, d, "events").createOrReplaceTempView("bs_events")
    return spark.sql("SELECT block_id, round(g[1], 5) + 0.0D AS g01, round(g[5], 5) + 0.0D AS g22 FROM (SELECT block_id, bs_gram(features) AS g FROM bs_events GROUP BY block_id)")


@query("u_draw_udtf", "WITH b AS (SELECT (o_custkey % 20)::INT AS block_id, count(o_totalprice)::BIGINT AS n FROM orders GROUP BY 1) SELECT trial, block_id, n FROM (SELECT range::INT AS trial, floor((('0x' || substr(md5('7|0|' || range), 1, 8))::BIGINT / 4294967296.0::DOUBLE) * (SELECT count(*) FROM b))::INT AS block_id FROM range(30)) JOIN b USING (block_id)")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Draws of the orders' blocks, with the rows that each drawn block has."""
    udfs.register(spark)
    blocks = table(spark, d, "orders").groupBy(F.pmod("o_custkey", F.lit(20)).cast("int").alias("block_id")).agg(F.count("o_totalprice").alias("n"))
    stored(blocks, "blocks").createOrReplaceTempView("bs_order_blocks")
    return spark.sql("SELECT t.trial, b.block_id, b.n FROM (SELECT cast(count(*) AS int) AS k FROM bs_order_blocks) c, LATERAL bs_draw(c.k, 30, 7) t JOIN bs_order_blocks b ON b.block_id = t.block_id")


@query("u_solve", with_stats("events", body="SELECT " + ", ".join(f"round({' + '.join(f'i{min(i, j)}{max(i, j)} * c{j}' for j in range(3))}, 5) + 0.0 AS a{i}" for i in range(3)) + " FROM inv, tot"))
def _(spark: SparkSession, d: str) -> DataFrame:
    total = stats.total_stats(stats.block_stats(load(spark, d, "events"), 3), 3)
    out = total.select(udfs.solve_udf("gram", "atb").alias("x"))
    return out.select(*[rounded(F.get("x", F.lit(i)), 5).alias(f"a{i}") for i in range(3)])


@query("u_views", with_stats("documents", body="SELECT block_id, count(*)::BIGINT AS n FROM design GROUP BY block_id"))
def _(spark: SparkSession, d: str) -> DataFrame:
    """The registered views together: rows of each scored block."""
    sqlapi.register_views(spark, d)
    return spark.sql("SELECT s.block_id, count(*) AS n FROM bs_scores s JOIN bs_design USING (block_id) GROUP BY s.block_id")


@query("r_data_source", "SELECT (o_custkey % 500 * 20 // 500)::INT AS block_id, count(*)::BIGINT AS n, round(sum(o_totalprice) / 1e6, 4) AS total FROM orders GROUP BY 1")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Orders meet the source's row of their customer: a matrix of 500 rows, each of 40 entries, in 20 blocks."""
    generated.register(spark)
    orders = table(spark, d, "orders").select(F.pmod("o_custkey", F.lit(500)).alias("row_id"), "o_totalprice")
    rows = spark.read.format("blocksketch_t").option("n", "500").option("blocks", "20").load()
    both = orders.join(F.broadcast(rows.where(F.size("features") == 40).select("row_id", "block_id")), "row_id")
    return both.groupBy("block_id").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice") / 1e6, 4).alias("total"))


@query("u_hash_uniform", "SELECT event_id, (('0x' || substr(md5('x' || event_id), 1, 8))::BIGINT / 4294967296.0::DOUBLE) AS u FROM events")
def _(spark: SparkSession, d: str) -> DataFrame:
    udfs.register(spark)
    table(spark, d, "events").createOrReplaceTempView("bs_raw_events")
    return spark.sql("SELECT event_id, bs_hash_uniform(concat('x', event_id)) AS u FROM bs_raw_events")


# ---- whole experiments --------------------------------------------------------------------------------------------


@query("w1_residual_table")
def _(spark: SparkSession, d: str) -> DataFrame:
    return workloads.residual_table(spark, d)


@query("w1_residual_table_t_matrix")
def _(spark: SparkSession, d: str) -> DataFrame:
    return workloads.residual_table(spark, d, "t")


@query("w2_convergence")
def _(spark: SparkSession, d: str) -> DataFrame:
    """method, s, log_residual: curves over all iterations at the sweep's largest step."""
    rows = stored(load(spark, d, "embeddings"), "design")
    out = workloads.curves(rows, 40, workloads.half_the_blocks(rows), workloads.ITERATIONS, workloads.SHARES[-1], 50)
    return spark.createDataFrame(out, "method string, s int, log_residual double")


def _line_search(spark: SparkSession, rows: DataFrame) -> DataFrame:
    out = workloads.compare_methods(rows, 40, workloads.half_the_blocks(rows), workloads.ITERATIONS, [1.0], line=True, dense=True, signs=True, fixed=True)
    return spark.createDataFrame(out, "method string, share double, log_residual double").drop("share")


@query("w3_line_search")
def _(spark: SparkSession, d: str) -> DataFrame:
    """The exact line search with block leverage, uniform, Gaussian, block SRHT and sign sketches, new in every step and fixed, and stochastic blocks."""
    return _line_search(spark, stored(load(spark, d, "embeddings"), "design"))


@query("w3_line_search_t_matrix")
def _(spark: SparkSession, d: str) -> DataFrame:
    """The same on a matrix of t-distributed entries."""
    return _line_search(spark, stored(workloads.heavy_matrix(spark), "design"))


@query("w3_dense_baselines")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Fixed steps: dense and sign sketches, new in every step and fixed."""
    rows = stored(load(spark, d, "embeddings"), "design")
    out = workloads.compare_methods(rows, 40, workloads.half_the_blocks(rows), workloads.ITERATIONS, workloads.SHARES, dense=True, signs=True, fixed=True)
    return spark.createDataFrame(out, "method string, share double, log_residual double")


@query("w5_other_tables")
def _(spark: SparkSession, d: str) -> DataFrame:
    """The sweep's methods on the given tables, and with lognormal and Cauchy-like row scales (these with dense sketches too)."""
    out = []
    for name, width in (("lineitem", 3), ("documents", 3), ("events", 3), ("star", 7)):
        rows = workloads.compare_methods(load(spark, d, name), width, Q, workloads.ITERATIONS, workloads.SHARES, SEED)
        out += [(name, m, share, v) for m, share, v in rows]
    for kind in ("lognormal", "cauchy"):
        rows = stored(workloads.scaled_matrix(spark, kind), "design")
        out += [(kind, m, share, v) for m, share, v in workloads.compare_methods(rows, 40, workloads.half_the_blocks(rows), workloads.ITERATIONS, workloads.SHARES, SEED, dense=True)]
    return spark.createDataFrame(out, "source string, method string, share double, log_residual double")


@query("w8_srht_and_leverage")
def _(spark: SparkSession, d: str) -> DataFrame:
    """Embedding errors on [A | b] of leverage draws, uniform draws and block SRHT at the same number of blocks, five seeds each.

    The Hadamard blocks are those of the padded table: at 2000 rows 16 rows each, where drawn blocks have 20.
    """
    rows = stored(load(spark, d, "embeddings"), "design")
    held = stored(stats.block_stats(rows, 40), "stats")
    total = stats.collect_total(held, 40)
    dist = stored(scores.block_leverage(held, 40, total), "dist")
    out, q = [], workloads.half_the_blocks(rows)
    for name in ("leverage", "uniform"):
        w = workloads.weights_for(name, dist, 5, SEED, q)
        made = sorted(sampling.sketched_stats(held, w, 40).collect(), key=lambda r: r["iteration"])
        out += [(name, i, e) for i, e in enumerate(sampling.embedding_error(total, made, 40))]
    upper = np.triu_indices(40)
    for i in range(5):
        s = sketches.sketch_total(sketches.block_srht(rows, 40, held.count(), q, SEED + i), 40)
        out.append(("block srht", i, sampling.embedding_error(total, [{"gram": s.gram[upper].tolist(), "atb": s.atb.tolist(), "btb": s.btb}], 40)[0]))
    return spark.createDataFrame(out, "method string, iteration int, eps double")
