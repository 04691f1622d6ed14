"""The engine against closed forms, NumPy, enumeration and the paper's worked values."""

from __future__ import annotations

import itertools
import math
import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from blocksketch import fixtures
from blocksketch.operators import coding, descent, design, distances, gradients, metrics, network, products, sampling, scores, sketches, stats
from blocksketch.operators.descent import Stop, fixed_step
from blocksketch.plans import rewrites
from blocksketch.sources import tables

DESIGN = "row_id long, block_id int, features array<double>, label double"


def frame(spark, a, b, blocks):
    return spark.createDataFrame([(i, int(blocks[i]), [float(v) for v in a[i]], float(b[i])) for i in range(len(a))], DESIGN)


@pytest.fixture(scope="module")
def small(spark):
    rng = np.random.default_rng(2)
    a = rng.standard_t(3, size=(120, 4))
    b = a @ [1, -2, 0.5, 3] + rng.normal(size=120)
    blocks = np.arange(120) // 10
    df = frame(spark, a, b, blocks).cache()
    return a, b, blocks, df


# ---- designs ----


def test_split_of_100_into_7(spark):
    assert sorted(r.n_rows for r in design.block_sizes(spark, 100, 7).collect()) == [14] * 5 + [15] * 2


@pytest.mark.parametrize(("n", "k"), [(100, 7), (5, 7), (6, 6), (1, 1), (10, 1)])
def test_contiguous_blocks_are_near_equal_and_in_order(spark, n, k):
    rows = spark.range(n).select(((F.col("id") * 7919) % 10007).alias("row_id"), F.lit(0).alias("block_id"), F.array(F.lit(1.0)).alias("features"), F.lit(0.0).alias("label")).repartition(5)
    out = sorted((r.row_id, r.block_id) for r in design.assign_blocks(rows, k).collect())
    sizes = np.bincount([b for _, b in out], minlength=k)
    assert sizes.max() - sizes.min() <= 1 and sizes.sum() == n
    assert [b for _, b in out] == sorted(b for _, b in out)


def test_blocks_do_not_depend_on_partitioning(small):
    df = small[3]
    a = sorted(map(str, design.assign_blocks(df.repartition(1), 7).select("row_id", "block_id").collect()))
    assert a == sorted(map(str, design.assign_blocks(df.repartition(8), 7).select("row_id", "block_id").collect()))


def test_nulls_raise_or_drop(spark):
    src = spark.createDataFrame([(1, 1.0), (2, None), (3, float("nan"))], "i long, v double")
    make = lambda how: design.design_matrix(src, [F.col("v")], F.lit(0.0), F.col("i"), on_null=how)
    assert make("drop").count() == 1
    with pytest.raises(Exception, match="null or NaN"):
        make("error").collect()
    with pytest.raises(ValueError, match="on_null"):
        make("guess")


def test_padding_evens_blocks(spark):
    df = frame(spark, np.ones((7, 2)), np.ones(7), [0, 0, 0, 1, 1, 2, 2])
    out = design.pad_blocks(df, 4, 2)
    assert {r.block_id: r["count"] for r in out.groupBy("block_id").count().collect()} == {0: 3, 1: 3, 2: 3, 3: 3}
    assert out.agg(F.sum(F.get("features", F.lit(0)))).first()[0] == 7


# ---- statistics and scores ----


@pytest.mark.parametrize("engine", ["sql", "arrow"])
def test_block_statistics(small, engine):
    a, b, blocks, df = small
    for r in stats.block_stats(df, 4, engine=engine).collect():
        part, y = a[blocks == r.block_id], b[blocks == r.block_id]
        assert np.allclose(stats.unpack(r.gram, 4), part.T @ part) and np.allclose(r.atb, part.T @ y) and np.isclose(r.btb, y @ y) and r.n == 10


def test_tsqr_is_the_triangular_factor(small):
    a, _, _, df = small
    for parts in (1, 40):
        r = stats.tsqr(df.repartition(parts), 4, fan=4)
        assert np.allclose(r.T @ r, a.T @ a) and np.allclose(r, np.triu(r))


def test_scores_agree_and_sum_to_one(small):
    a, _, blocks, df = small
    u = np.linalg.qr(a)[0]
    want = np.array([(u[blocks == k] ** 2).sum() / 4 for k in range(12)])
    held = stats.block_stats(df, 4)
    for table in (scores.block_leverage(held, 4), scores.block_leverage_by_rows(df, 4), scores.block_leverage_by_rows(df, 4, "tsqr")):
        got = np.array([r.p for r in table.orderBy("block_id").collect()])
        assert np.allclose(got, want) and np.isclose(got.sum(), 1)
    leverage = [r.leverage for r in scores.row_leverage(df, 4).collect()]
    assert max(leverage) <= 1 + 1e-9 and np.isclose(sum(leverage), 4)


def test_scores_do_not_depend_on_the_basis(small):
    a, b, blocks, df = small
    turned = frame(df.sparkSession, a @ np.random.default_rng(0).normal(size=(4, 4)), b, blocks)
    one, two = (np.array([r.p for r in scores.block_leverage(stats.block_stats(x, 4), 4).orderBy("block_id").collect()]) for x in (df, turned))
    assert np.allclose(one, two)


def test_rank_deficient_zero_and_dominant_blocks(spark):
    a = np.array([[1.0, 2.0], [2.0, 4.0], [0.0, 0.0], [0.0, 0.0]])
    got = {r.block_id: r.p for r in scores.block_leverage(stats.block_stats(frame(spark, a, np.zeros(4), [0, 1, 2, 2]), 2), 2).collect()}
    assert np.allclose([got[0], got[1], got[2]], [0.2, 0.8, 0])


def test_approximate_scores_are_usable(spark):
    df = tables.t_matrix(spark, 3000, 5, seed=1, blocks=30).withColumn("label", F.lit(0.0)).cache()
    exact = scores.block_leverage(stats.block_stats(df, 5), 5)
    for approx in (scores.approx_leverage(df, 5, 400, 0), scores.approx_leverage(df, 5, 400, 8), scores.sampled_scores(df, 5, 0.5)):
        beta = distances.misestimation(exact, approx).first()["beta"]
        assert 0.05 < beta <= 1


# ---- replicas ----


def brute_counts(p, m, floor):
    best = None
    for r in itertools.product(range(floor, m + 1), repeat=len(p)):
        if sum(r) == m:
            cost = sum(abs(x - y / m) for x, y in zip(p, r, strict=True))
            best = cost if best is None else min(best, cost)
    return best


@pytest.mark.parametrize("seed", range(8))
@pytest.mark.parametrize("floor", [0, 1])
def test_apportionment_is_optimal(spark, seed, floor):
    rng = random.Random(seed)
    k, m = rng.randint(1, 4), rng.randint(4, 9)
    w = [rng.choice([0.01, 0.3, 1, 1, 5]) for _ in range(k)]
    p = [x / sum(w) for x in w]
    r = [x.r for x in network.apportion_exact(spark.createDataFrame(list(enumerate(p)), "block_id int, p double"), m, floor).orderBy("block_id").collect()]
    assert sum(r) == m and min(r) >= floor
    assert math.isclose(sum(abs(a - b / m) for a, b in zip(p, r, strict=True)), brute_counts(p, m, floor), abs_tol=1e-9)


@settings(max_examples=150, deadline=None)
@given(st.lists(st.floats(0.001, 1), min_size=1, max_size=12), st.integers(0, 60), st.integers(0, 10**6))
def test_adjustment_ends_at_m(weights, extra, seed):
    p = [w / sum(weights) for w in weights]
    m = len(p) + extra
    rng = random.Random(seed)
    r = network.adjust_replicas(p, [rng.randint(0, 8) for _ in p], m)
    assert sum(r) == m and min(r) >= 1
    best = [x / m for x in r]
    assert sum(abs(a - b) for a, b in zip(p, best, strict=True)) <= 2 + 1e-9


def test_adjustment_never_beats_the_optimum(spark):
    rng = random.Random(1)
    for _ in range(5):
        w = [rng.random() for _ in range(6)]
        p = [x / sum(w) for x in w]
        r = network.adjust_replicas(p, [rng.randint(1, 9) for _ in p], 20)
        opt = [x.r for x in network.apportion_exact(spark.createDataFrame(list(enumerate(p)), "block_id int, p double"), 20).collect()]
        assert sum(abs(a - b / 20) for a, b in zip(p, r, strict=True)) >= sum(abs(a - b / 20) for a, b in zip(p, opt, strict=True)) - 1e-9


def test_worked_example_counts_and_mean():
    counts, m, q = [3, 3, 4, 5, 5], 20, 3
    assert network.is_perfect(counts, [20] * 5, 20) and not network.is_perfect(counts, [20] * 5, 30)
    assert network.adjust_replicas([c / 20 for c in counts], counts, m) == counts
    block = [b for b, r in enumerate(counts) for _ in range(r)]
    replies = [sum((block[i] + 1) * m / (q * counts[block[i]]) for i in s) for s in itertools.combinations(range(m), q)]
    assert len(replies) == 1140 and math.isclose(np.mean(replies), 15.0)


def test_channel_counts_can_be_zero_and_bad_input_is_refused(spark):
    dist = scores.uniform_scores(spark, 100)
    assert network.replicas_channel(dist, 0.1).where("r > 0").count() == 0
    assert network.replicas_channel_scaled(dist, 0.1, 500).agg(F.sum("r")).first()[0] == 500
    with pytest.raises(ValueError, match="phi"):
        network.replicas_channel(dist, 1.0)
    with pytest.raises(ValueError, match="at least"):
        network.apportion_exact(dist, 99)
    with pytest.raises(ValueError, match="allow"):
        network.adjust_replicas([0.5, 0.5], [1, 1], 1)


def test_lcm_counts_are_exact(spark):
    rows = network.replicas_lcm(spark, [1, 1, 1], [2, 3, 6]).orderBy("block_id").collect()
    assert [r.r for r in rows] == [3, 2, 1]


def test_laws_and_ending_times(spark):
    df = spark.createDataFrame([(float(i),) for i in range(1, 11)], "t double")
    assert [r.cdf for r in network.runtime_law(df, "t").orderBy("t").collect()] == pytest.approx([i / 10 for i in range(1, 11)])
    assert network.ending_time(df, "t", 20, 10).first()["ending"] == 5.0
    assert [r.q for r in network.replies_by(df, "t", [0.5, 5, 50], 20).orderBy("ending").collect()] == [0, 10, 20]
    sketch = {r.t: r.cdf for r in network.runtime_law_sketch(df, "t", 10).collect()}
    assert sketch[10.0] == 1.0
    for kind in ("exponential", "pareto", "weibull"):
        law = network.closed_law(kind, 2.0, 1.5)
        assert law(0) == 0 and 0.9 < law(1e3) <= 1
        assert network.task_law(law, "shrink", 100, 10)(3.0) == law(30.0)


# ---- draws ----


def test_draws_follow_the_distribution_and_ignore_partitions(spark):
    p = [0.5, 0.3, 0.15, 0.05]
    dist = spark.createDataFrame(list(enumerate(p)), "block_id int, p double")
    draws = sampling.draw_blocks(dist, 50, 200, 3).cache()
    seen = np.array([draws.where(F.col("block_id") == b).count() for b in range(4)])
    assert ((seen - 10_000 * np.array(p)) ** 2 / (10_000 * np.array(p))).sum() < 16
    again = sampling.draw_blocks(dist.repartition(3), 50, 200, 3)
    assert draws.exceptAll(again).count() == 0


def test_binned_draws_equal_broadcast_draws(spark, monkeypatch):
    dist = scores.uniform_scores(spark, 37)
    a = sampling.draw_blocks(dist, 20, 5, 1).collect()
    monkeypatch.setattr(sampling, "MOST_BROADCAST_BLOCKS", 1)
    assert sorted(a) == sorted(sampling.draw_blocks(dist, 20, 5, 1).collect())


def test_weighted_and_plain_sketches_agree(small):
    a, b, blocks, df = small
    dist = scores.block_leverage(stats.block_stats(df, 4), 4).cache()
    draws = sampling.draw_blocks(dist, 8, 2, 5).cache()
    w = sampling.weights(draws, 8)
    x = [0.3, -1.0, 2.0, 0.5]
    plain = sampling.block_sketch(df, draws.where("iteration = 0"), 8)
    g1 = gradients.gradient(plain, x).first()["g"]
    g2 = gradients.sketched_gradient(df, x, w.where("iteration = 0")).first()["g"]
    g3 = gradients.gradient(sampling.weighted_sketch(df, w.where("iteration = 0")), x).first()["g"]
    assert np.allclose(g1, g2) and np.allclose(g2, g3)
    assert all(r.zeta >= 1 for r in sampling.compression(draws).collect())


def test_expected_distinct_by_enumeration(spark):
    p, q = [0.5, 0.3, 0.2], 3
    dist = spark.createDataFrame(list(enumerate(p)), "block_id int, p double")
    want = sum(math.prod(p[i] for i in s) * len(set(s)) for s in itertools.product(range(3), repeat=q))
    assert math.isclose(sampling.expected_distinct(dist, q).first()["expected"], want)
    counts = [3, 3, 4, 5, 5]
    block = [b for b, r in enumerate(counts) for _ in range(r)]
    mean = np.mean([len({block[i] for i in s}) for s in itertools.combinations(range(20), 3)])
    got = sampling.expected_distinct_fastest(spark.createDataFrame(list(enumerate(counts)), "block_id int, r long"), 3).first()["expected"]
    assert math.isclose(got, mean) and round(got, 3) == 2.518
    assert round(sampling.expected_distinct(spark.createDataFrame([(i, c / 20) for i, c in enumerate(counts)], "block_id int, p double"), 3).first()["expected"], 3) == 2.416


def test_proved_number_of_draws_holds_and_the_printed_does_not():
    """Each of 40 blocks spans its own direction: coupon collecting decides, whatever the block size."""
    d, eps, delta = 40, 0.5, 0.1
    rng = np.random.default_rng(0)

    def fails(q):
        return np.mean([np.abs(np.bincount(rng.integers(0, d, q), minlength=d) * d / q - 1).max() > eps for _ in range(200)])

    assert fails(sampling.trials_needed(d, eps, delta)) <= delta
    assert fails(sampling.trials_needed(d, eps, delta, tau=50, form="printed")) == 1.0
    assert sampling.failure_bound(d, sampling.trials_needed(d, eps, delta), eps) <= delta


def test_embedding_error_bounds_gradients(small):
    a, b, _, df = small
    held = stats.block_stats(df, 4).cache()
    total = stats.collect_total(held, 4)
    dist = scores.block_leverage(held, 4, total).cache()
    w = sampling.weights(sampling.draw_blocks(dist, 20, 10, 9), 20)
    made = descent.sketch_totals(held, w, 4)
    rows = [{"gram": t.gram[np.triu_indices(4)].tolist(), "atb": t.atb.tolist(), "btb": t.btb} for t in made]
    for t, eps in zip(made, sampling.embedding_error(total, rows, 4), strict=True):
        for x in (np.zeros(4), np.ones(4), total.solution()):
            gap = np.linalg.norm(2 * (t.gram @ x - t.atb) - 2 * (total.gram @ x - total.atb))
            assert gap <= metrics.gradient_error_bound(total, x, eps) * (1 + 1e-9)
        if eps < 1:
            bounds = metrics.solution_bounds(eps)
            best, x = total.solution(), t.solution()
            assert math.sqrt(total.objective(x) / total.objective(best)) <= bounds["ratio"] * (1 + 1e-9)
            assert np.linalg.norm(a @ (best - x)) <= bounds["in_span"] * np.linalg.norm(a @ best - b) * (1 + 1e-9)


# ---- optimum, descent ----


def test_expansion_keeps_the_optimum_only_with_its_own_shares(small):
    a, b, blocks, df = small
    held = stats.block_stats(df, 4)
    counts = network.apportion_exact(scores.block_leverage(held, 4), 40).cache()
    best = np.linalg.lstsq(a, b, rcond=None)[0]
    again = stats.collect_total(stats.block_stats(network.expand(df, counts, 5), 4), 4).solution()
    assert np.allclose(best, again)
    code = network.encoding(counts, 5)
    only = df.join(code, "block_id").select("row_id", "block_id", F.transform("features", lambda v: v * F.col("scale")).alias("features"), (F.col("label") * F.col("scale")).alias("label"))
    assert not np.allclose(best, stats.collect_total(stats.block_stats(only, 4), 4).solution(), atol=1e-4)


def test_descent_reaches_the_optimum_and_long_steps_do_not(small):
    a, b, _, df = small
    total = stats.collect_total(stats.block_stats(df, 4), 4)
    best = total.solution()
    assert np.allclose(best, np.linalg.lstsq(a, b, rcond=None)[0])
    run = lambda share: descent.descend_on_stats(total, None, [0.0] * 4, descent.safe_step(total, share), Stop(3000)).xs[-1]
    assert np.linalg.norm(run(0.5) - best) < 1e-8
    with pytest.raises(FloatingPointError):
        run(2.0)
    trace = descent.steepest_descent(df, [0.0] * 4, descent.line_search(), Stop(6))
    values = [total.objective(x) for x in trace.xs]
    assert all(y <= x + 1e-9 for x, y in zip(values, values[1:], strict=False))


def test_rows_and_statistics_give_the_same_path(small):
    _, _, _, df = small
    held = stats.block_stats(df, 4).cache()
    total = stats.collect_total(held, 4)
    w = sampling.weights(sampling.draw_blocks(scores.block_leverage(held, 4, total), 6, 4, 2), 6).cache()
    step, stop = descent.safe_step(total, 0.2), Stop(4)
    one = descent.sketched_descent(df, [0.0] * 4, step, stop, w)
    two = descent.descend_on_stats(total, descent.sketch_totals(held, w, 4), [0.0] * 4, step, stop)
    assert np.allclose(one.xs, two.xs)
    assert all(c["blocks_read"] <= 6 and c["rows_read"] == 10 * c["blocks_read"] for c in one.costs)


def test_mean_of_all_draws_contracts_as_plain_descent(small):
    _, _, _, df = small
    held = stats.block_stats(df, 4).collect()
    total = stats.collect_total(stats.block_stats(df, 4), 4)
    xi, x, best = 0.3 / total.spectrum()["sigma_max"] ** 2, np.ones(4), total.solution()
    dist = {r.block_id: r.p for r in scores.block_leverage(stats.block_stats(df, 4), 4, total).collect()}
    mean = sum(dist[r.block_id] * (x - xi * 2 * (stats.unpack(r.gram, 4) @ x - np.array(r.atb)) / dist[r.block_id]) for r in held)
    assert np.allclose(mean - best, (np.eye(4) - 2 * xi * total.gram) @ (x - best))
    assert np.linalg.norm(mean - best) <= descent.contraction_rate(total, xi)["norm"] * np.linalg.norm(x - best) + 1e-9


def test_regret_vanishes_with_diminishing_steps(small):
    _, _, _, df = small
    held = stats.block_stats(df, 4).cache()
    total = stats.collect_total(held, 4)
    w = sampling.weights(sampling.draw_blocks(scores.block_leverage(held, 4, total), 6, 400, 2), 6)
    trace = descent.descend_on_stats(total, descent.sketch_totals(held, w, 4), [0.0] * 4, descent.diminishing_step(0.5 / total.spectrum()["sigma_max"] ** 2), Stop(400))
    assert metrics.decay_slope(metrics.regret(total, trace, total.solution())) < -0.4


def test_late_servers_bias_and_zero_shares_are_seen(spark, small):
    counts = spark.createDataFrame([(0, 2), (1, 2)], "block_id int, r long")
    servers = network.allocate(counts)
    assert sorted(map(tuple, servers.collect())) == [(0, 0), (1, 0), (2, 1), (3, 1)]
    law = spark.createDataFrame([(1.0, 0.5), (2.0, 1.0)], "t double, cdf double")
    replies = network.simulate_responses(servers, law, 3, 1, [0, 1]).collect()
    assert {r.block_id for r in replies} == {1} and len(replies) == 6


# ---- baselines ----


def test_hadamard_and_srht(spark):
    h = sketches.hadamard(np.eye(8))
    assert np.allclose(h @ h.T, 8 * np.eye(8))
    rng = np.random.default_rng(1)
    a, b = rng.normal(size=(64, 3)), rng.normal(size=64)
    df = frame(spark, a, b, np.arange(64) // 4)
    whole = a.T @ a
    means = np.mean([sketches.sketch_total(sketches.block_srht(df, 3, 16, 16, seed=s), 3).gram for s in range(6)], 0)
    assert np.linalg.norm(means - whole) < 0.5 * np.linalg.norm(whole)


def test_srht_rows_are_those_of_single_row_blocks(spark):
    rng = np.random.default_rng(2)
    df = frame(spark, rng.normal(size=(50, 3)), rng.normal(size=50), np.arange(50) // 5)
    values = lambda s: np.array([[*r["features"], r["label"]] for r in sorted(s.collect(), key=lambda r: r["sketch_row"])])
    want = values(sketches.block_srht(df, 3, 50, 12, seed=3))
    assert want.shape == (12, 4) and np.abs(want).max() > 0
    for tau in (1, 8, 256):
        assert np.allclose(values(sketches.srht_rows(df, 3, 12, 3, tau)), want)


def test_srht_rows_query_reads_the_whole_table(spark, sf_dir, monkeypatch):
    from blocksketch import queries

    seen = []
    whole = sketches.srht_rows
    monkeypatch.setattr(sketches, "srht_rows", lambda design, *a: seen.append(design.count()) or whole(design, *a))
    assert queries.QUERIES["x4_srht_rows"](spark, sf_dir).first()["rows"] == 200
    assert seen == [spark.read.parquet(f"{sf_dir}/embeddings.parquet").count()]


def test_srht_stands_beside_leverage(spark, sf_dir):
    from blocksketch import queries, queries_engine  # noqa: F401

    out = queries.QUERIES["w8_srht_and_leverage"](spark, sf_dir).collect()
    assert sorted((r.method, r.iteration) for r in out) == sorted((m, i) for m in ("leverage", "uniform", "block srht") for i in range(5))
    assert len({r.eps for r in out}) == 15 and all(0 < r.eps < 20 for r in out)


def test_new_dense_sketches_of_every_iteration(spark):
    rng = np.random.default_rng(4)
    ab = np.c_[rng.normal(size=(60, 3)), rng.normal(size=60)]
    df = frame(spark, ab[:, :3], ab[:, 3], np.arange(60) // 4)
    whole, seeds = ab.T @ ab, [(0, s) for s in range(400)]
    total = stats.collect_total(stats.block_stats(df, 3), 3)
    direct = np.array([(lambda z: z.T @ z / 40)(rng.normal(size=(40, 60)) @ ab) for _ in range(400)])
    made = np.array([sampling.with_label(t) for t in sketches.gaussian_totals(total, 40, seeds)])
    assert np.abs(made.mean(0) - whole).max() < 0.1 * np.abs(whole).max()
    assert np.allclose(np.diagonal(made.std(0)), np.diagonal(direct.std(0)), rtol=0.25)
    srht = np.array([sampling.with_label(t) for t in sketches.srht_totals(df, 3, 15, 8, seeds)])
    assert np.abs(srht.mean(0) - whole).max() < 0.1 * np.abs(whole).max() and srht.std(0).min() > 0
    x = np.r_[ab, np.zeros((4, 4))]
    r = np.random.default_rng((0, 7))
    sign, drawn = r.integers(0, 2, 64) * 2.0 - 1, r.integers(0, 16, 8)
    y = (sketches.hadamard(np.eye(64)) @ (sign[:, None] * x)).reshape(16, 4, 4)[drawn].reshape(-1, 4)
    assert np.allclose(srht[7], y.T @ y / 32)


def test_many_draws_of_many_blocks_leave_no_nested_loop(spark, monkeypatch):
    dist = spark.createDataFrame([(i, (i % 7 + 1) / 399) for i in range(100)] + [(100, 1 - sum((i % 7 + 1) / 399 for i in range(100)))], "block_id int, p double")
    plain = sampling.draw_blocks(dist, 40, 30, 3)
    assert "NestedLoop" in plain._jdf.queryExecution().executedPlan().toString()
    monkeypatch.setattr(sampling, "MOST_BROADCAST_PAIRS", 1000)
    binned = sampling.draw_blocks(dist, 40, 30, 3)
    assert "NestedLoop" not in binned._jdf.queryExecution().executedPlan().toString()
    assert sorted(map(tuple, plain.collect())) == sorted(map(tuple, binned.collect())) and plain.count() == 1200


def test_weighted_totals_are_sums_over_the_drawn_blocks(small, monkeypatch):
    from blocksketch import workloads

    _, _, _, df = small
    monkeypatch.setattr(workloads, "MOST_WEIGHTS", 40)  # a few iterations at a time
    blocks = workloads.block_table(df, 4)
    w = workloads.weights_for("leverage", blocks.dist, 9, 2, 5)
    want = descent.sketch_totals(blocks.held, w, 4)
    got = blocks.totals(w, 9)
    assert len(got) == len(want) == 9
    assert all(np.allclose(g.gram, t.gram) and np.allclose(g.atb, t.atb) for g, t in zip(got, want, strict=True))


def test_residual_table_has_all_methods_and_instances(spark, sf_dir, monkeypatch):
    from blocksketch import workloads

    seeds, compare = [], workloads.compare_methods
    monkeypatch.setattr(workloads, "compare_methods", lambda *a, **k: seeds.append(a[5]) or compare(*a, **k))
    out = workloads.residual_table(spark, sf_dir, iterations=3).collect()
    assert seeds == list(range(6))
    assert {r.method for r in out} == {"plain", "leverage", "uniform", "stochastic", "gaussian", "block srht", "leverage fixed"} and len(out) == 28


@pytest.mark.parametrize("kind", ["gaussian", "rademacher"])
def test_dense_sketches_keep_the_gram_matrix_in_the_mean(small, kind):
    a, _, _, df = small
    means = np.mean([sketches.sketch_total(sketches.dense_sketch(df, 4, 100, kind, s), 4).gram for s in range(5)], 0)
    assert np.linalg.norm(means - a.T @ a) < 0.3 * np.linalg.norm(a.T @ a)


def test_group_coding_is_exact_for_every_q_replies(spark, small):
    a, b, blocks, df = small
    m, q, x = 6, 5, [0.1, 0.2, -0.3, 1.0]
    code = coding.group_code(spark, m, q)
    parts = gradients.partial_gradients(df, x).cache()
    want = 2 * a.T @ (a @ x - b)
    replies = [(i, s) for i, sub in enumerate(itertools.combinations(range(m), q)) for s in sub]
    out = coding.group_decode(parts, code, spark.createDataFrame(replies, "iteration int, server_id int"), 4).collect()
    assert len(out) == 6 and all(np.allclose(r.g, want) for r in out)
    assert np.allclose(coding.uncoded(parts).first()["g"], want)
    with pytest.raises(ValueError, match="divide"):
        coding.group_code(spark, 7, 5)


def test_decoding_error_is_zero_or_one():
    g = np.random.default_rng(0).normal(size=(6, 4))
    assert [round(coding.decoding_error(g, range(k)), 9) for k in (2, 3, 4, 6)] == [1, 1, 0, 0]


def test_products_and_cur(spark, small):
    a, b, blocks, df = small
    other = df.select("row_id", "block_id", F.array("label").alias("features"))
    exact = {(r.i, r.j): r.v for r in products.exact_product(df, other, 4, 1).collect()}
    assert np.allclose([exact[i, 0] for i in range(4)], a.T @ b)
    many = products.cr_product(df, other, 4, 1, 30, 1, 40).groupBy("i", "j").agg(F.avg("v").alias("v")).collect()
    assert np.linalg.norm([r.v - exact[r.i, r.j] for r in many]) < 0.25 * np.linalg.norm(a.T @ b)
    total = stats.collect_total(stats.block_stats(df, 4), 4)
    columns, picked, u = products.cur(scores.row_leverage(df, 4), total, 4, 4, 4)
    assert products.cur_error(total, columns, picked, u) < 1e-6 * np.linalg.norm(a)
    assert np.isclose(np.linalg.norm(a - a[:, columns] @ u @ np.array(picked)), products.cur_error(total, columns, picked, u), atol=1e-6)


# ---- plans ----


def plan_of(df):
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def test_block_store_reads_only_drawn_blocks(spark, small, tmp_path):
    df = small[3]
    tables.write_block_store(df, str(tmp_path / "store"), 4)
    some = tables.read_blocks(spark, str(tmp_path / "store"), [1, 5], 4)
    assert some.count() == 20
    text = plan_of(some.select("label"))
    assert "PartitionFilters: [isnotnull" in text or "PartitionFilters: [block_bucket" in text or "block_bucket" in text
    assert "PushedFilters: [In(block_id" in text
    assert rewrites.choose_mode(10**6, 3, 100, 600, 10**5) == "stats" and rewrites.choose_mode(10**6, 400, 10**6, 5, 10**4) == "rows"


def test_scans_are_pruned_and_pushed(spark, sf_dir):
    text = plan_of(stats.block_stats(fixtures.load(spark, sf_dir, "lineitem"), 3))
    assert "l_extendedprice" in text and "l_shipdate" not in text and "CartesianProduct" not in text
    text = plan_of(gradients.sketched_gradient(fixtures.load(spark, sf_dir, "documents"), [0.0] * 3, spark.createDataFrame([(0, 1, 1.0)], "iteration int, block_id int, w double")))
    assert "BroadcastHashJoin" in text and "BatchEvalPython" not in text


# ---- scale of the engine ----


def test_rows_are_numbered_by_ranges_of_all_keys(spark):
    rows = spark.range(3000).select(F.lit("same").alias("a"), F.concat(F.lit("k"), F.lpad(((F.col("id") * 7919) % 3001).cast("string"), 5, "0")).alias("b")).repartition(7)
    out = sorted((r.b, r.pos) for r in design.number_rows(rows, ("a", "b"), rows_per_range=200).collect())
    assert [p for _, p in out] == list(range(3000))
    assert design.number_rows(rows.limit(0), ("a", "b")).count() == 0


def test_running_totals_by_ranges(spark):
    rows = [((i * 37) % 1009 / 10, i % 5) for i in range(1009)]
    df = spark.createDataFrame(rows, "t double, n long").repartition(6)
    got = {r.t: r.upto for r in design.running_total(df, "t", "n", "upto", keys_per_range=100).collect()}
    total = 0
    for t, n in sorted(rows):
        total += n
        assert got[t] == total


def test_an_iteration_opens_the_files_of_its_draw(small):
    _, _, _, df = small
    store = tables.stored_blocks(df.repartition(3), 12)
    assert [store.files([b]) for b in (0, 5)] == [1, 1] and store.files(list(range(12))) == 12 and store.files([1, 2, 3]) == 3
    opened = store.blocks([1, 2, 3]).select(F.input_file_name().alias("f")).distinct().count()
    scan = store.blocks([1, 2, 3])._jdf.queryExecution().executedPlan().toString()
    assert opened == 3 and "PartitionFilters: [" in scan and "block_bucket" in scan and "PushedFilters: [In(block_id" in scan
    w = df.sparkSession.createDataFrame([(s, b, 2.0) for s in range(2) for b in (1, 4, 7)], "iteration int, block_id int, w double")
    step, stop = fixed_step(1e-3), Stop(2)
    a, b = (descent.sketched_descent(x, [0.0] * 4, step, stop, w) for x in (store, df))
    assert np.allclose(a.xs, b.xs) and [c["files_read"] for c in a.costs] == [3, 3]


def test_replies_are_decoded_as_least_squares_says(spark):
    k, rng = 7, np.random.default_rng(3)
    g = rng.normal(size=(k, 3))
    matrix = np.array([[1.0 + 0.1 * i if (j - i) % k < 3 else 0.0 for j in range(k)] for i in range(k)])
    parts = spark.createDataFrame([(b, [float(v) for v in g[b]]) for b in range(k)], "block_id int, g array<double>")
    code = spark.createDataFrame([(i, j, float(matrix[i, j])) for i in range(k) for j in range(k) if matrix[i, j]], "server_id int, block_id int, c double")
    came = {0: [0, 2, 5], 1: list(range(k)), 2: [6]}
    replies = spark.createDataFrame([(i, s) for i, v in came.items() for s in v], "iteration int, server_id int")
    for r in coding.decode_replies(parts, code, replies).collect():
        part = matrix[came[r.iteration]]
        a = np.linalg.lstsq(part.T, np.ones(k), rcond=None)[0]
        assert np.allclose(r.g, a @ part @ g)


def test_row_draws_follow_the_scores(small):
    _, _, _, df = small
    rows = scores.row_leverage(df, 4).cache()
    pi = {r.row_id: r.pi for r in rows.collect()}
    draws = [r.row_id for r in sampling.draw_rows(rows, 500, 8, 5).collect()]
    assert len(draws) == 4000
    seen = np.bincount(draws, minlength=len(pi)) / 4000
    assert np.abs(seen - [pi[i] for i in range(len(pi))]).max() < 0.02


def test_signs_of_a_hadamard_sketch_once_or_every_time(small):
    _, _, _, df = small
    total = stats.collect_total(stats.block_stats(df, 4), 4)
    seeds = [(1, i) for i in range(60)]
    for resign in ("once", "every"):
        made = sketches.srht_totals(df, 4, 12, 8, seeds, resign)
        assert np.allclose(np.mean([t.gram for t in made], 0), total.gram, rtol=0.25, atol=0.12 * np.abs(total.gram).max())
    signs = sketches.rademacher_totals(df, 4, 40, seeds)
    assert np.allclose(np.mean([t.gram for t in signs], 0), total.gram, rtol=0.2, atol=0.1 * np.abs(total.gram).max())


def test_gradients_under_sign_sketches_are_those_of_their_statistics(spark):
    rng = np.random.default_rng(8)
    ab = rng.normal(size=(1003, 4))
    df = frame(spark, ab[:, :3], ab[:, 3], np.arange(1003) // 20)
    xs, seeds = rng.normal(size=(2, 3)), [(3, s) for s in range(3)]
    for r in (5, 333, 1003):
        totals = sketches.rademacher_totals(df, 3, r, seeds)
        made = sketches.SignGradients(df, 3, r, seeds)
        for s, t in enumerate(totals):
            signs = np.vstack([sketches.sign_rows(seeds[s], run, r, 1003) for run in range(-(-r // sketches.RUN))]) * 2.0 - 1
            assert signs.shape == (r, 1003) and set(np.unique(signs)) == {-1, 1} and abs(signs.mean()) < 5 / np.sqrt(signs.size)
            assert np.allclose(sampling.with_label(t), (signs @ ab).T @ (signs @ ab) / r)
            assert np.allclose(made(s, xs), 2 * (xs @ t.gram - t.atb))
        made.free()
    # all sketches in tasks of their own, not split by rows, are the same
    many = sketches.rademacher_totals(df, 3, 333, [(3, s) for s in range(9)])
    assert all(np.allclose(a.gram, b.gram) for a, b in zip(many, sketches.rademacher_totals(df, 3, 333, seeds), strict=False))


@pytest.mark.parametrize("line", [False, True])
def test_large_sign_sketches_are_multiplied_with_residuals_only(spark, monkeypatch, line):
    from blocksketch import workloads

    rng = np.random.default_rng(9)
    ab = rng.normal(size=(400, 5))
    df = frame(spark, ab[:, :4], ab[:, 4], np.arange(400) // 20)
    asked, totals = [], sketches.rademacher_totals
    monkeypatch.setattr(sketches, "rademacher_totals", lambda *a: asked.append(len(a[3])) or totals(*a))
    blocks = workloads.block_table(df, 4)
    want, got = ([], [])
    for out, most in ((want, 1 << 30), (got, 1000)):
        monkeypatch.setattr(workloads, "MOST_SIGNS", most, raising=False)
        out += workloads.compare_methods(df, 4, 10, 12, [1.0] if line else [0.025, 0.25], line=line, signs=True, fixed=True, blocks=blocks)
    assert asked == [12, 1]
    assert [g[:2] for g in got] == [w[:2] for w in want] and "rademacher" in {g[0] for g in got}
    assert np.allclose([g[2] for g in got], [w[2] for w in want], rtol=1e-9)


def test_channel_counts_sum_to_the_servers(spark):
    dist = spark.createDataFrame([(i, p) for i, p in enumerate([0.1, 0.3, 0.05, 0.25, 0.3])], "block_id int, p double")
    for form in ("literal", "multiple", "scaled"):
        for phi in (0.2, 0.7, 0.95):
            r = [x.r for x in network.channel_counts(dist, phi, 23, form).orderBy("block_id").collect()]
            assert sum(r) == 23 and min(r) >= 1
    with pytest.raises(ValueError):
        network.channel_counts(dist, 0.5, 20, "other")


def test_a_side_is_broadcast_by_its_counted_size(spark):
    many = spark.createDataFrame([(1,)] * 50, "a int")
    assert "broadcast" in rewrites.small(many)._jdf.queryExecution().logical().toString().lower()
    assert "broadcast" not in rewrites.small(spark.range(10_000_000), 100)._jdf.queryExecution().logical().toString().lower()
