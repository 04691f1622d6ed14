"""Temporary views of a whole design for use from SQL."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from blocksketch import fixtures
from blocksketch.functions import udfs
from blocksketch.operators import descent, network, sampling, scores, stats
from blocksketch.plans.rewrites import small
from blocksketch.sources.tables import stored, table

VIEWS = ("design", "blocks", "scores", "draws", "allocation", "responses", "trace")


def register_views(spark: SparkSession, sf_dir: str, name: str = "documents", q: int = 10, m: int = 60, iterations: int = 5, seed: int = 7, prefix: str = "bs_") -> list[str]:
    """Registers the functions and the views design, blocks, scores, draws, allocation, responses and trace."""
    udfs.register(spark)
    rows, d = fixtures.load(spark, sf_dir, name), fixtures.WIDTH[name]
    held = stored(stats.block_stats(rows, d), "stats")
    total = stats.collect_total(held, d)
    dist = stored(scores.block_leverage(held, d, total), "dist")
    counts = stored(network.apportion_exact(dist, m), "counts")
    servers = network.allocate(counts)
    law = stored(network.runtime_law(table(spark, sf_dir, "events"), "value"), "law")
    replies = stored(network.simulate_responses(servers, law, iterations, seed), "replies")
    share = small(counts.select("block_id", (F.col("r") / F.lit(float(m))).alias("p")))
    w = sampling.weights(sampling.draw_fastest(replies, q).join(share, "block_id"), q)
    trace = descent.descend_on_stats(total, descent.sketch_totals(held, w, d), [0.0] * d, descent.safe_step(total, 0.2), descent.Stop(iterations))
    made = {"design": rows, "blocks": held, "scores": dist, "draws": sampling.draw_blocks(dist, q, iterations, seed), "allocation": servers, "responses": replies, "trace": trace.table(spark)}
    for view in VIEWS:
        made[view].createOrReplaceTempView(prefix + view)
    return [prefix + v for v in VIEWS]
