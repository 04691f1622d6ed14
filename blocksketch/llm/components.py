"""Connected components by alternating large-star and small-star steps.

Edges stay distributed; every round is written to the shared scratch folder, so
the plan does not grow and a lost executor costs a reread.  A hot centre's
neighbours meet only an aggregate (one minimum per node), never one another:
it is broadcast up to a counted size, and beyond it written first, so that the
join's two sides are plain exchanges, which adaptive execution can split at a
hot centre.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blocksketch.llm.common import discard, materialise

#: Edges (both ways) up to which the minima of all nodes, two longs each, are broadcast.
MOST_BROADCAST_EDGES = 1_000_000


def _print(edges: DataFrame) -> tuple:
    r = edges.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("u", "v")).alias("x")).first()
    return r["n"], r["x"]


def components(edges: DataFrame, src: str = "src", dst: str = "dst", most_rounds: int = 60) -> DataFrame:
    """(node, component) of every node that has an edge; component is its smallest node.

    Loops and null ends are ignored; repeated edges count once; no edges give
    an empty table.
    """
    now = edges.select(F.greatest(src, dst).alias("u"), F.least(src, dst).alias("v")).where("u is not null and v is not null and u <> v").distinct()
    now = materialise(now, "edges")
    before = _print(now)
    for _ in range(most_rounds):
        if before[0] == 0:
            break
        few, held = 2 * before[0] <= MOST_BROADCAST_EDGES, [now]

        def kept(df: DataFrame, label: str, held: list[DataFrame] = held) -> DataFrame:
            held.append(materialise(df, label))
            return held[-1]

        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("_u"), F.least("u", "m").alias("m"))
        # large star: every larger neighbour of u points to the smallest around u
        large = both.where("v > u").join(F.broadcast(low) if few else kept(low, "minima"), F.col("u") == F.col("_u")).select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        large = large if few else kept(large, "stars")
        # small star: every smaller neighbour of u, and u, point to the smallest of them
        least = large.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("_u"), "m")
        rest = large.join(F.broadcast(least) if few else kept(least, "minima"), F.col("u") == F.col("_u")).where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        small = rest.unionByName(least.select(F.col("_u").alias("u"), F.col("m").alias("v"))).distinct()
        after = materialise(small, "edges")
        for df in held:
            discard(df)
        now, last = after, before
        before = _print(now)
        if before == last:
            break
    else:
        raise RuntimeError("components did not settle")
    roots = now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots)
