"""Replica design for a network of workers of which some are late, and its simulation.

Tables have a row per block or per worker, but for an empirical law, which has a
row per distinct runtime and is summed by ranges.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from blocksketch.functions.core import half_up, hash_uniform
from blocksketch.operators.design import running_total
from blocksketch.plans.rewrites import small

Law = Callable[[float], float]


def runtime_law(df: DataFrame, col: str) -> DataFrame:
    """Empirical law t, cdf of a column; distinct values, counted before they are ordered and summed by ranges."""
    counts = df.where(F.col(col).isNotNull()).groupBy(F.col(col).cast("double").alias("t")).agg(F.count("*").alias("n"))
    summed = running_total(counts, "t", "n", "upto")
    total = summed.agg(F.max("upto")).first()[0] or 1
    return summed.select("t", (F.col("upto") / F.lit(total)).alias("cdf"))


def runtime_law_sketch(df: DataFrame, col: str, points: int = 1000) -> DataFrame:
    """The same for any size: quantiles of a mergeable sketch instead of a sort."""
    levels = [(i + 1) / points for i in range(points)]
    q = df.agg(F.percentile_approx(col, levels, 100 * points).alias("q"))
    return q.select(F.posexplode("q").alias("i", "t")).groupBy(F.col("t").cast("double").alias("t")).agg(F.max((F.col("i") + 1) / points).alias("cdf"))


def closed_law(kind: str, scale: float = 1.0, shape: float = 1.0, shift: float = 0.0) -> Law:
    """Closed laws: shifted exponential, Pareto, Weibull."""
    if kind == "exponential":
        return lambda t: 0.0 if t <= shift else 1 - math.exp(-(t - shift) / scale)
    if kind == "pareto":
        return lambda t: 0.0 if t <= scale else 1 - (scale / t) ** shape
    if kind == "weibull":
        return lambda t: 0.0 if t <= shift else 1 - math.exp(-(((t - shift) / scale) ** shape))
    raise ValueError(f"unknown law: {kind}")


def task_law(law: Law, scale: str, n: int, tau: int) -> Law:
    """Law of one block's task: unchanged, shrunk with the task, or the printed (inverse) scaling."""
    if scale == "none":
        return law
    if scale == "shrink":
        return lambda t: law(t * n / tau)
    if scale == "printed":
        return lambda t: law(t * tau / n)
    raise ValueError("scale is 'none', 'shrink' or 'printed'")


def replies_by(df: DataFrame, col: str, endings: Sequence[float], m: int) -> DataFrame:
    """ending, phi (chance of being late), q = floor(F(T) m), in one scan."""
    times = df.sparkSession.createDataFrame([(float(t),) for t in endings], "ending double")
    sums = df.agg(*[F.avg((F.col(col) <= float(t)).cast("double")).alias(f"f{i}") for i, t in enumerate(endings)])
    held = F.array(*[F.struct(F.lit(float(t)).alias("ending"), F.col(f"f{i}").alias("f")) for i, t in enumerate(endings)])
    rows = sums.select(F.explode(held).alias("x")).select("x.ending", "x.f")
    return times.join(rows, "ending").select("ending", (1 - F.col("f")).alias("phi"), F.floor(F.col("f") * m + 1e-9).cast("long").alias("q"))


def ending_time(df: DataFrame, col: str, m: int, q: int) -> DataFrame:
    """Smallest time by which q of m replies are expected."""
    if not 0 < q <= m:
        raise ValueError("0 < q <= m")
    return runtime_law(df, col).where(F.floor(F.col("cdf") * m + 1e-9) >= q).agg(F.min("t").alias("ending"))


def replicas_channel(dist: DataFrame, phi: float) -> DataFrame:
    """rho solves 1 - phi**rho = p; r is its nearest integer (may be 0: reported, never encoded)."""
    if not 0 < phi < 1:
        raise ValueError("0 < phi < 1")
    rho = F.when(F.col("p") < 1, F.log1p(-F.col("p")) / F.lit(math.log(phi))).otherwise(F.lit(1e9))
    return dist.select("block_id", "p", rho.alias("rho")).withColumn("r", half_up(F.col("rho")).cast("long"))


def replicas_channel_scaled(dist: DataFrame, phi: float, m: int) -> DataFrame:
    """The same shares scaled to about m replicas, at least one each."""
    base = replicas_channel(dist, phi)
    total = F.sum("rho").over(Window.partitionBy())
    return base.withColumn("r", F.greatest(F.lit(1), half_up(F.col("rho") * m / total)).cast("long"))


def replicas_multiple(dist: DataFrame, phi: float, m: int) -> DataFrame:
    """round(m / sum r) copies of the rounded counts."""
    base = replicas_channel(dist, phi)
    total = F.sum("r").over(Window.partitionBy())
    return base.withColumn("r", (F.when(total > 0, half_up(m / total)).otherwise(0) * F.col("r")).cast("long"))


def replicas_ratio(dist: DataFrame, nu: int = 1) -> DataFrame:
    """Nearest integers of nu p / min p (over positive p)."""
    least = F.min(F.when(F.col("p") > 0, F.col("p"))).over(Window.partitionBy())
    return dist.select("block_id", "p", half_up(nu * F.col("p") / least).cast("long").alias("r"))


def replicas_lcm(spark: SparkSession, numerators: Sequence[int], denominators: Sequence[int]) -> DataFrame:
    """Counts that emulate rational p exactly: R is the least common denominator."""
    reduced = [(a // math.gcd(a, b), b // math.gcd(a, b)) for a, b in zip(numerators, denominators, strict=True)]
    total = math.lcm(*[b for _, b in reduced])
    return spark.createDataFrame([(i, total // b * a) for i, (a, b) in enumerate(reduced)], "block_id int, r long")


def is_perfect(numerators: Sequence[int], denominators: Sequence[int], total: int) -> bool:
    """Whether counts summing to ``total`` can equal the shares exactly."""
    return all(total * a % b == 0 for a, b in zip(numerators, denominators, strict=True))


def adjust_replicas(p: Sequence[float], r: Sequence[int], m: int, min_replicas: int = 1) -> list[int]:
    """Counts moved one by one until they sum to m, always at the block whose share is worst off.

    The signed gap between share and target says where: the block most above
    target gives, the most below takes; a block chosen twice running whose move
    would cross its target is parked.  Ties go to the lowest block.
    """
    k = len(p)
    if m < k * min_replicas:
        raise ValueError("m must allow min_replicas for every block")
    r = [max(min_replicas, int(x)) for x in r]
    total = sum(r)
    grow = total < m
    sign = -1.0 if grow else 1.0

    def gap(i: int) -> float:
        return sign * (p[i] - r[i] / m)

    heap = [(gap(i), i) for i in range(k) if grow or r[i] > min_replicas]
    heapq.heapify(heap)
    last = -1
    while total != m:
        value, i = heapq.heappop(heap)
        step = 1 if grow else -1
        after = sign * (p[i] - (r[i] + step) / m)
        if i == last and value < 0 < after and heap:
            heapq.heappush(heap, (1.0 + after, i))
            last = -1
            continue
        r[i] += step
        total += step
        last = i
        if grow or r[i] > min_replicas:
            heapq.heappush(heap, (gap(i), i))
    return r


def apportion_exact(dist: DataFrame, m: int, min_replicas: int = 1) -> DataFrame:
    """Counts summing to m with the least sum of |p - r/m|, by windows over K rows.

    With a floor of 0: whole parts, then largest remainders.  With a floor of 1:
    every block has one, and the other m - K units go where the next unit helps
    most.
    """
    if min_replicas == 0:
        w = Window.orderBy(F.col("rest").desc(), "block_id")
        base = dist.select("block_id", "p", F.floor(F.col("p") * m + 1e-12).alias("whole")).withColumn("rest", F.col("p") * m - F.col("whole"))
        lack = F.lit(m) - F.sum("whole").over(Window.partitionBy())
        return base.select("block_id", "p", (F.col("whole") + (F.row_number().over(w) <= lack).cast("long")).cast("long").alias("r"))
    if min_replicas != 1:
        raise ValueError("min_replicas is 0 or 1")
    k_rows = dist.count()
    if m < k_rows:
        raise ValueError("m must be at least the number of blocks")
    units = dist.select("block_id", "p", F.explode(F.sequence(F.lit(2), F.greatest(F.lit(2), F.least(F.lit(m), F.ceil(F.col("p") * m).cast("int") + 1 + m // max(1, k_rows))))).alias("unit"))
    gain = F.abs(F.col("p") - (F.col("unit") - 1) / m) - F.abs(F.col("p") - F.col("unit") / m)
    w = Window.orderBy(F.round(gain, 12).desc(), "block_id", "unit")
    given = units.withColumn("place", F.row_number().over(w)).where(F.col("place") <= m - k_rows).groupBy("block_id").agg(F.count("*").alias("more"))
    return dist.select("block_id", "p").join(given, "block_id", "left").select("block_id", "p", (F.lit(1) + F.coalesce("more", F.lit(0))).cast("long").alias("r"))


def allocate(counts: DataFrame) -> DataFrame:
    """server_id, block_id: consecutive servers of each block, one block per server."""
    ends = F.sum("r").over(Window.orderBy("block_id"))
    spans = counts.where("r > 0").select("block_id", "r", ends.alias("end"))
    return spans.select(F.explode(F.sequence((F.col("end") - F.col("r")).cast("int"), (F.col("end") - 1).cast("int"))).alias("server_id"), "block_id")


def encoding(counts: DataFrame, q: int) -> DataFrame:
    """block_id, p (share r/R), scale = 1/sqrt(q p): the one scalar a block is encoded with.

    The share must be that of the counts themselves: with any other
    distribution the expanded problem has another optimum.
    """
    total = F.sum("r").over(Window.partitionBy())
    return counts.where("r > 0").select("block_id", "r", (F.col("r") / total).alias("p")).withColumn("scale", 1 / F.sqrt(q * F.col("p")))


def expand(design: DataFrame, counts: DataFrame, q: int) -> DataFrame:
    """The expanded, encoded problem written out (tests only: in work replicas stay metadata)."""
    held = small(encoding(counts, q))
    rows = design.join(held, "block_id").withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("r"))))
    return rows.select("row_id", "block_id", "copy", F.transform("features", lambda v: v * F.col("scale")).alias("features"), (F.col("label") * F.col("scale")).alias("label"))


def simulate_responses(allocation: DataFrame, law: DataFrame, iterations: int, seed: int, late_servers: Sequence[int] = ()) -> DataFrame:
    """iteration, server_id, block_id, t: independent times from the inverse of an empirical law.

    Servers named in ``late_servers`` never answer.
    """
    spark = allocation.sparkSession
    steps = spark.range(iterations).select(F.col("id").cast("int").alias("iteration"))
    work = allocation.where(~F.col("server_id").isin([int(s) for s in late_servers])) if late_servers else allocation
    each = work.crossJoin(steps).withColumn("u", hash_uniform(f"reply{seed}", F.col("iteration"), F.col("server_id")))  # m x S rows
    # the step of the law below t, without ordering all of it in one task: laws stay sorted by their own cdf
    cdf = _with_lower(law)
    bins = 1024
    spread = cdf.withColumn("bin", F.explode(F.sequence(F.floor(F.col("lo") * bins), F.least(F.floor(F.col("cdf") * bins), F.lit(bins - 1)))))
    found = each.withColumn("bin", F.floor(F.col("u") * bins)).join(spread, "bin").where((F.col("u") >= F.col("lo")) & (F.col("u") < F.col("cdf")))
    return found.select("iteration", "server_id", "block_id", "t")


def _with_lower(law: DataFrame) -> DataFrame:
    """t, lo, cdf: every value with the law just below it.

    The rows meet on 1/4096 bins of the law; a bin's first row takes the highest
    value of lower bins, of which there is one number per bin.
    """
    binned = law.withColumn("_bin", F.floor(F.col("cdf") * 4096))
    tops = sorted((r["_bin"], r["top"]) for r in binned.groupBy("_bin").agg(F.max("cdf").alias("top")).collect())  # at most 4097 rows
    before = [(b, tops[i - 1][1] if i else 0.0) for i, (b, _) in enumerate(tops)]
    held = law.sparkSession.createDataFrame(before, "_bin long, _below double")
    inside = F.lag("cdf").over(Window.partitionBy("_bin").orderBy("t"))
    return binned.join(F.broadcast(held), "_bin").select("t", F.coalesce(inside, F.col("_below")).alias("lo"), "cdf")


def channel_counts(dist: DataFrame, phi: float, m: int, form: str = "scaled") -> DataFrame:
    """block_id, p, r: replica counts of the channel rule at ``phi``, then moved step by step until they sum to m.

    ``form`` says what the rule's real counts become before: ``literal`` rounds
    them, ``multiple`` takes copies of the rounded ones, ``scaled`` scales them
    to about m.  K rows are adjusted on the driver.
    """
    made = {"literal": lambda: replicas_channel(dist, phi), "multiple": lambda: replicas_multiple(dist, phi, m), "scaled": lambda: replicas_channel_scaled(dist, phi, m)}
    if form not in made:
        raise ValueError(f"form is one of {sorted(made)}")
    rows = sorted((r["block_id"], r["p"], r["r"]) for r in made[form]().select("block_id", "p", "r").collect())
    counts = adjust_replicas([p for _, p, _ in rows], [r for *_, r in rows], m)
    return dist.sparkSession.createDataFrame([(b, p, int(r)) for (b, p, _), r in zip(rows, counts, strict=True)], "block_id int, p double, r long")


def design_network(scores_for: Callable[[int], DataFrame], df: DataFrame, col: str, ending: float, m: int, candidates: Sequence[int], form: str = "literal") -> list[dict[str, float]]:
    """For each number of blocks: total of the channel rule's own counts, then q, beta, d and Delta of the adjusted ones.

    ``scores_for(k)`` gives the distribution over k blocks.  ``chosen`` marks
    the number of blocks whose counts come closest to m before any adjustment,
    ties to fewer blocks; of more blocks than servers none can be chosen.
    """
    from blocksketch.operators import distances

    r = replies_by(df, col, [ending], m).first()
    phi = min(max(r["phi"], 1e-9), 1 - 1e-9)
    out = []
    for k in candidates:
        if k > m:
            continue
        dist = scores_for(k)
        rule = replicas_channel(dist, phi).agg(F.sum("r")).first()[0]
        counts = channel_counts(dist, phi, m, form)
        share = counts.withColumn("p", F.col("r") / F.lit(float(m)))
        beta = distances.misestimation(dist, share).first()["beta"]
        d = distances.distortion(dist, counts).first()["d"]
        delta = distances.channel_distortion(dist, counts, phi).first()["delta"]
        out.append({"k": k, "rule_total": rule, "q": r["q"], "beta": beta, "d": d, "delta": delta})
    best = min(out, key=lambda x: (abs(x["rule_total"] - m), x["k"]), default=None)
    return [x | {"chosen": x is best} for x in out]
