"""Design matrices and their row blocks.

A design is a DataFrame ``row_id BIGINT, block_id INT, features ARRAY<DOUBLE>,
label DOUBLE``; a block is the unit of scoring, drawing and replication.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from blocksketch.functions.core import dot, hash_normal
from blocksketch.sources.tables import stored


def design_matrix(df: DataFrame, features: Sequence[Column], label: Column, row_id: Column, block_id: Column | None = None, intercept: bool = True, on_null: str = "error") -> DataFrame:
    """Rows of numbers from any table; only the columns named are read.

    A null or NaN in a feature or the label raises when the row is met
    (``on_null='error'``) or drops the row (``'drop'``); nothing is imputed.
    """
    if on_null not in ("error", "drop"):
        raise ValueError("on_null is 'error' or 'drop'")
    cols = [c.cast("double") for c in features]
    if intercept:
        cols = [F.lit(1.0), *cols]
    if not cols:
        raise ValueError("a design needs a feature")
    out = df.select(row_id.cast("long").alias("row_id"), (block_id if block_id is not None else F.lit(0)).cast("int").alias("block_id"), F.array(*cols).alias("features"), label.cast("double").alias("label"))
    bad = F.exists("features", lambda v: v.isNull() | F.isnan(v)) | F.col("label").isNull() | F.isnan("label")
    if on_null == "drop":
        return out.where(~bad)
    return out.withColumn("label", F.when(bad, F.raise_error(F.lit("null or NaN in a design row")).cast("double")).otherwise(F.col("label")))


def plant_labels(design: DataFrame, x: Sequence[float], noise_sd: float = 0.0, seed: str = "noise", key: Column | None = None) -> DataFrame:
    """label = a.x plus normal noise from a hash of ``key`` (row_id by default)."""
    key = F.col("row_id") if key is None else key
    clean = dot(F.col("features"), x)
    return design.withColumn("label", clean + noise_sd * hash_normal(seed, key) if noise_sd else clean)


def block_sizes(spark: SparkSession, n: int, k: int) -> DataFrame:
    """(block_id, n_rows): sizes that differ by at most one, larger ones first."""
    if k < 1 or n < 0:
        raise ValueError("k >= 1 and n >= 0")
    return block_sizes_of(spark.range(1).select(F.lit(n).cast("long").alias("n")), k).select("block_id", "n_rows")


def block_sizes_of(counts: DataFrame, k: int) -> DataFrame:
    """``counts`` (with n rows each), block_id, n_rows: the same for every row of a table of counts."""
    each = counts.withColumn("block_id", F.explode(F.sequence(F.lit(0), F.lit(k - 1))))
    return each.withColumn("n_rows", F.floor(F.col("n") / k) + (F.col("block_id") < F.col("n") % k).cast("long"))


def block_of_position(pos: Column, n: int, k: int) -> Column:
    """Block of the pos-th row (from 0) of n, contiguous and near-equal."""
    small, extra = n // k, n % k
    head = F.floor(pos / F.lit(small + 1))
    if small == 0:
        return head.cast("int")
    tail = extra + F.floor((pos - F.lit(extra * (small + 1))) / F.lit(small))
    return F.when(pos < extra * (small + 1), head).otherwise(tail).cast("int")


def number_rows(df: DataFrame, keys: Sequence[str], name: str = "pos", rows_per_range: int = 1_000_000) -> DataFrame:
    """Adds the row's position in the order of ``keys``, without a single-task window.

    Rows are dealt by ranges of all keys together, as many as the counted rows
    ask for, so one value of the leading key may fill many ranges.  Each range
    is sorted and numbered as it is written; the stored numbers are then shifted
    by the counts of lower ranges, one row per range.
    """
    ranges = max(1, df.count() // rows_per_range)
    local = F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))  # the row's number in its partition
    dealt = stored(df.repartitionByRange(ranges, *keys).sortWithinPartitions(*keys).withColumns({"_range": F.spark_partition_id(), "_r": local}), "numbered")
    before, rows = 0, []
    for r, n in sorted(tuple(x) for x in dealt.groupBy("_range").agg(F.count("*").alias("n")).collect()):  # one row per range
        rows.append((r, before))
        before += n
    offsets = df.sparkSession.createDataFrame(rows, "_range int, _before long")
    return dealt.join(F.broadcast(offsets), "_range").withColumn(name, F.col("_before") + F.col("_r")).drop("_range", "_before", "_r")


def running_total(df: DataFrame, key: str, value: str, name: str, keys_per_range: int = 1_000_000) -> DataFrame:
    """``df`` (one row per ``key``) with the sum of ``value`` up to and including the key, by ranges as in number_rows."""
    ranges = max(1, df.count() // keys_per_range)
    dealt = stored(df.repartitionByRange(ranges, key).withColumn("_range", F.spark_partition_id()), "ranges")
    before, rows = 0, []
    for r, n in sorted(tuple(x) for x in dealt.groupBy("_range").agg(F.sum(value).alias("n")).collect()):  # one row per range
        rows.append((r, before))
        before += n
    offsets = df.sparkSession.createDataFrame(rows, f"_range int, _before {dict(dealt.groupBy('_range').agg(F.sum(value).alias('n')).dtypes)['n']}")
    inside = F.sum(value).over(Window.partitionBy("_range").orderBy(key))
    return dealt.join(F.broadcast(offsets), "_range").withColumn(name, F.col("_before") + inside).drop("_range", "_before")


def assign_blocks(design: DataFrame, k: int, how: str = "contiguous", keys: Sequence[str] = ("row_id",)) -> DataFrame:
    """Replaces block_id by near-equal contiguous blocks, a hash, a key modulus or value ranges.

    ``contiguous``: exact near-equal sizes in the order of ``keys``;
    ``hash``: md5-free modulus of the first key's digits; ``key``: the first
    key modulo k; ``range``: quantile ranges of the first key.
    """
    if k < 1:
        raise ValueError("k >= 1")
    if how == "contiguous":
        n = design.count()
        numbered = number_rows(design, keys)
        return numbered.withColumn("block_id", block_of_position(F.col("pos"), n, k)).drop("pos")
    if how == "hash":
        from blocksketch.functions.core import hash_int

        return design.withColumn("block_id", F.pmod(hash_int("block", F.col(keys[0])), F.lit(k)).cast("int"))
    if how == "key":
        return design.withColumn("block_id", F.pmod(F.col(keys[0]), F.lit(k)).cast("int"))
    if how == "range":
        points = sorted(set(design.approxQuantile(keys[0], [i / k for i in range(1, k)], 0.0)))
        place = F.lit(0)
        for p in points:
            place = place + (F.col(keys[0]) > F.lit(p)).cast("int")
        return design.withColumn("block_id", place.cast("int"))
    raise ValueError(f"unknown how: {how}")


def pad_blocks(design: DataFrame, k: int, d: int) -> DataFrame:
    """Adds zero rows (negative row_id) until every block is as large as the largest."""
    sizes = design.groupBy("block_id").agg(F.count("*").alias("n"))
    blocks = design.sparkSession.range(k).select(F.col("id").cast("int").alias("block_id")).join(sizes, "block_id", "left").select("block_id", F.coalesce("n", F.lit(0)).alias("n"))
    most = sizes.agg(F.max("n")).first()[0] or 0
    lacking = blocks.where(F.col("n") < most).select("block_id", F.explode(F.sequence(F.lit(1), F.lit(most) - F.col("n"))).alias("i"))
    zero = F.array(*[F.lit(0.0)] * d)
    rows = lacking.select((-(F.col("block_id").cast("long") * most + F.col("i"))).alias("row_id"), "block_id", zero.alias("features"), F.lit(0.0).alias("label"))
    return design.select("row_id", "block_id", "features", "label").unionByName(rows)
