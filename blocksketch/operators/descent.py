"""Steepest descent: plain, stochastic, sketched, coded, weighted, projected, and with Newton steps.

An iteration is one job: the plan starts from the stored design and returns one
row.  From a block store it opens the files of the drawn blocks' buckets only;
from any other table it scans all rows and drops what was not drawn.  Draws of all iterations are made in
one job beforehand.  ``mode='stats'`` iterates on block statistics instead
(K d^2 numbers), for checks and for many cheap iterations.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blocksketch.functions.core import hash_uniform
from blocksketch.operators import gradients, network, sampling
from blocksketch.operators.stats import Total, unpack
from blocksketch.sources.tables import BlockStore
from blocksketch.plans.rewrites import small

Step = Callable[[int, np.ndarray, np.ndarray, float, float], float]


@dataclass
class Trace:
    """Iterates of a run and what each cost."""

    xs: list[np.ndarray]
    steps: list[float] = field(default_factory=list)
    gradients: list[np.ndarray] = field(default_factory=list)
    costs: list[dict] = field(default_factory=list)

    def table(self, spark, run: str = "run") -> DataFrame:
        """run, s, x, step (null for the start)."""
        rows = [(run, i, [float(v) for v in x], float(self.steps[i - 1]) if i else None) for i, x in enumerate(self.xs)]
        return spark.createDataFrame(rows, "run string, s int, x array<double>, step double")


def fixed_step(xi: float) -> Step:
    return lambda s, x, g, along, length: xi


def safe_step(total: Total, share: float = 0.5) -> Step:
    """share / sigma_max^2: the gradient's factor 2 makes 1 / sigma_max^2 the edge of stability."""
    return fixed_step(share / total.spectrum()["sigma_max"] ** 2)


def diminishing_step(xi: float, power: float = 0.5, shift: float = 1.0) -> Step:
    """xi / (s+shift)^power: 0.5 for a vanishing regret, 1 for the 1/(eta s) rule; a shift keeps first steps stable."""
    return lambda s, x, g, along, length: xi / (s + shift) ** power


def line_search() -> Step:
    """<A g, Ax - b> / ||A g||^2, exact along the direction used."""
    step: Step = lambda s, x, g, along, length: along / length if length > 0 else 0.0
    step.needs_line = True  # type: ignore[attr-defined]
    return step


@dataclass
class Stop:
    """Ends a run: most iterations, gradient norm, step norm, relative change of x, distance to a target."""

    iterations: int
    gradient_norm: float = 0.0
    step_norm: float = 0.0
    relative: float = 0.0
    target: np.ndarray | None = None
    distance: float = 0.0

    def now(self, x: np.ndarray, new: np.ndarray, g: np.ndarray) -> bool:
        move = float(np.linalg.norm(new - x))
        near = self.target is not None and float(np.linalg.norm(new - self.target)) <= self.distance
        return float(np.linalg.norm(g)) <= self.gradient_norm or move <= self.step_norm or move <= self.relative * float(np.linalg.norm(x)) or near


def _descend(x0: Sequence[float], step: Step, stop: Stop, grad: Callable[[int, np.ndarray], tuple[np.ndarray, dict]], line: Callable[[int, np.ndarray, np.ndarray], tuple[float, float]], project: float | None = None, ridge: float = 0.0) -> Trace:
    x = np.array(x0, float)
    trace = Trace([x])
    for s in range(stop.iterations):
        g, cost = grad(s, x)
        g = g + 2 * ridge * x
        along, length = line(s, x, g) if getattr(step, "needs_line", False) else (0.0, 0.0)
        xi = step(s, x, g, along, length)
        new = x - xi * g
        if project is not None and (size := float(np.linalg.norm(new))) > project:
            new = new * (project / size)
        if not np.isfinite(new).all():
            raise FloatingPointError("the iterates left the range of doubles: the step is too long")
        trace.xs.append(new)
        trace.steps.append(xi)
        trace.gradients.append(g)
        trace.costs.append(cost)
        done = stop.now(x, new, g)
        x = new
        if done:
            break
    return trace


def _line_of(design: DataFrame) -> Callable:
    def line(s: int, x: np.ndarray, g: np.ndarray) -> tuple[float, float]:
        r = gradients.line_sums(design, x.tolist(), g.tolist()).first()
        return r["along"], r["length"]

    return line


def steepest_descent(design: DataFrame, x0: Sequence[float], step: Step, stop: Stop, ridge: float = 0.0, project: float | None = None) -> Trace:
    """No sketch, no coding: every row in every iteration."""

    def grad(s: int, x: np.ndarray) -> tuple[np.ndarray, dict]:
        return np.array(gradients.gradient(design, x.tolist()).first()["g"]), {}

    return _descend(x0, step, stop, grad, _line_of(design), project, ridge)


def stochastic_descent(design: DataFrame, x0: Sequence[float], step: Step, stop: Stop, share: float, seed: int, unit: str = "row") -> Trace:
    """Unscored batches: each row, or each block, joins an iteration with chance ``share``, weight 1/share."""
    key = {"row": "row_id", "block": "block_id"}[unit]

    def grad(s: int, x: np.ndarray) -> tuple[np.ndarray, dict]:
        batch = design.where(hash_uniform(f"sgd{seed}", F.lit(s), F.col(key)) < share)
        g = gradients.gradient(batch, x.tolist()).first()["g"]
        return np.array([v or 0.0 for v in g]) / share, {}

    return _descend(x0, step, stop, grad, _line_of(design))


def sketched_descent(design: DataFrame | BlockStore, x0: Sequence[float], step: Step, stop: Stop, weights: DataFrame, line_on: str = "full", project: float | None = None, fixed: bool = False) -> Trace:
    """A new sketch in every iteration: ``weights`` has iteration, block_id, w; a block store is read by draw.

    ``fixed`` uses iteration 0's sketch throughout; ``line_on='sketch'`` takes
    the line search's sums from the sketch instead of the full data.
    """
    held: dict[int, list] = {}
    for r in weights.collect():  # metadata: at most K rows an iteration
        held.setdefault(r["iteration"], []).append((r["block_id"], r["w"]))
    store = design if isinstance(design, BlockStore) else None
    design = store.rows() if store else design
    spark = design.sparkSession

    def of(s: int) -> DataFrame:
        return spark.createDataFrame([(0, int(b), float(w)) for b, w in held.get(0 if fixed else s, [])], "iteration int, block_id int, w double")

    def grad(s: int, x: np.ndarray) -> tuple[np.ndarray, dict]:
        drawn = held.get(0 if fixed else s, [])
        if not drawn:
            return np.zeros(len(x)), {"rows_read": 0, "blocks_read": 0}
        wanted = [int(b) for b, _ in drawn]
        part = store.blocks(wanted) if store else design.where(F.col("block_id").isin(wanted))
        r = gradients.sketched_gradient(part, x.tolist(), of(s), step_sums=True).first()
        return np.array(r["g"]), {"rows_read": r["rows_read"], "blocks_read": r["blocks_read"]} | ({"files_read": store.files(wanted)} if store else {})

    def line(s: int, x: np.ndarray, g: np.ndarray) -> tuple[float, float]:
        if line_on == "full":
            return _line_of(design)(s, x, g)
        scaled = sampling.weighted_sketch(design, of(s))
        r = gradients.line_sums(scaled, x.tolist(), g.tolist()).first()
        return r["along"], r["length"]

    return _descend(x0, step, stop, grad, line, project)


def descend_on_stats(total: Total, sketches: Sequence[Total] | None, x0: Sequence[float], step: Step, stop: Stop, fixed: bool = False, line_on: str = "full") -> Trace:
    """The same iterations on Gram matrices: one Total per iteration's sketch, or none for plain descent."""

    def of(s: int) -> Total:
        return total if sketches is None else sketches[0 if fixed else s]

    def grad(s: int, x: np.ndarray) -> tuple[np.ndarray, dict]:
        t = of(s)
        return 2 * (t.gram @ x - t.atb), {}

    def line(s: int, x: np.ndarray, g: np.ndarray) -> tuple[float, float]:
        t = total if line_on == "full" else of(s)
        return float(g @ (t.gram @ x - t.atb)), float(g @ t.gram @ g)

    return _descend(x0, step, stop, grad, line)


def descend_together(total: Total, gradients: Callable[[int, np.ndarray], np.ndarray], x0: Sequence[float], steps: Sequence[Step], stop: Stop) -> np.ndarray:
    """The last iterates of one run for each step rule: runs x d.

    The runs go side by side, so that ``gradients(s, xs)`` gives those of all
    under the s-th sketch at once; a line search takes its sums from the full data.
    """
    xs, going = np.tile(np.array(x0, float), (len(steps), 1)), list(range(len(steps)))
    for s in range(stop.iterations):
        if not going:
            break
        for i, g in zip(list(going), gradients(s, xs[going]), strict=True):
            x = xs[i].copy()
            line = (float(g @ (total.gram @ x - total.atb)), float(g @ total.gram @ g)) if getattr(steps[i], "needs_line", False) else (0.0, 0.0)
            xs[i] = x - steps[i](s, x, g, *line) * g
            if not np.isfinite(xs[i]).all():
                raise FloatingPointError("the iterates left the range of doubles: the step is too long")
            if stop.now(x, xs[i], g):
                going.remove(i)
    return xs


def sketch_totals(stats: DataFrame, weights: DataFrame, d: int) -> list[Total]:
    """Sketched statistics of every iteration, in order: iterations x d^2 numbers."""
    rows = sorted(sampling.sketched_stats(stats, weights, d).collect(), key=lambda r: r["iteration"])
    return [Total(unpack(r["gram"], d), np.array(r["atb"]), r["btb"], 0) for r in rows]


def many_runs(total: Total, sketches: Sequence[Total] | None, x0: Sequence[float], step: Step, steps: int, runs: int) -> np.ndarray:
    """runs x (steps + 1) x d iterates; run r takes the sketches r steps .. (r+1) steps - 1."""
    made = []
    for r in range(runs):
        mine = None if sketches is None else sketches[r * steps : (r + 1) * steps]
        made.append(descend_on_stats(total, mine, x0, step, Stop(steps)).xs)
    return np.array(made)


def coded_descent(design: DataFrame | BlockStore, dist: DataFrame, law: DataFrame, m: int, x0: Sequence[float], step: Step, stop: Stop, seed: int, q: int | None = None, ending: float | None = None, late_servers: Sequence[int] = (), counts: DataFrame | None = None) -> tuple[Trace, DataFrame]:
    """The whole procedure: counts from scores, servers, replies, weights, descent.

    ``counts`` (block_id, r, summing to m) may come from any rule, such as
    ``network.channel_counts``; the exact apportionment is the default.  Waits
    for the q fastest, or for all replies up to ``ending``.  Returns the trace
    and the weights used.
    """
    if (q is None) == (ending is None):
        raise ValueError("give q or ending")
    counts = network.apportion_exact(dist, m) if counts is None else counts
    servers = network.allocate(counts)
    replies = network.simulate_responses(servers, law, stop.iterations, seed, late_servers)
    came = sampling.draw_fastest(replies, q) if q else sampling.draw_deadline(replies, ending)
    share = counts.select("block_id", (F.col("r") / F.lit(float(m))).alias("p"))
    used = sampling.weights(came.join(small(share), "block_id"), q)
    return sketched_descent(design, x0, step, stop, used), used


def newton_step(total: Total, sketched: Total, x: Sequence[float]) -> np.ndarray:
    """x - H^-1 g with a sketched Hessian and the full gradient."""
    x = np.array(x, float)
    return x - np.linalg.lstsq(sketched.gram, total.gram @ x - total.atb, rcond=None)[0]


def contraction_rate(total: Total, xi: float) -> dict[str, float]:
    """Norm of I - 2 xi A'A (what bounds the mean error), and its largest eigenvalue (the printed rate)."""
    values = np.linalg.eigvalsh(total.gram)
    rates = 1 - 2 * xi * values
    return {"norm": float(np.abs(rates).max()), "largest": float(rates.max())}
