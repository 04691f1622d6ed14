"""Sufficient statistics of blocks: one scan from which scores, gradients and checks follow."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blocksketch.sources.tables import stored

#: Groups into which the tasks' matrices of one block are dealt before they meet.
FAN = 256
#: Up to this many columns sums are built-in expressions; beyond, Arrow batches and BLAS.
MOST_SQL_COLUMNS = 8


def packed(d: int) -> list[tuple[int, int]]:
    """Index pairs of the packed upper triangle."""
    return [(i, j) for i in range(d) for j in range(i, d)]


@dataclass
class Total:
    """Gram matrix, A'b, b'b and row count, on the driver (d x d numbers)."""

    gram: np.ndarray
    atb: np.ndarray
    btb: float
    n: int

    def inverse(self) -> np.ndarray:
        """Pseudo-inverse, so that rank-deficient designs are scored on their span."""
        return np.linalg.pinv(self.gram, rcond=1e-12, hermitian=True)

    def rank(self) -> int:
        return int(np.linalg.matrix_rank(self.gram, tol=1e-12 * max(1e-300, np.abs(self.gram).max()) * len(self.gram), hermitian=True))

    def solution(self, ridge: float = 0.0) -> np.ndarray:
        """Least-squares optimum of the normal equations, or of ridge regression."""
        m = self.gram + ridge * np.eye(len(self.gram))
        return np.linalg.lstsq(m, self.atb, rcond=None)[0]

    def spectrum(self) -> dict[str, float]:
        """Extreme singular values of A, condition number, rank and Frobenius norm."""
        values = np.clip(np.linalg.eigvalsh(self.gram), 0, None)
        top, low = float(np.sqrt(values[-1])), float(np.sqrt(values[0]))
        return {"sigma_max": top, "sigma_min": low, "cond": top / low if low > 0 else float("inf"), "rank": self.rank(), "frobenius": float(np.sqrt(np.trace(self.gram)))}

    def objective(self, x: np.ndarray) -> float:
        return float(x @ self.gram @ x - 2 * x @ self.atb + self.btb)


def block_stats(design: DataFrame, d: int, by: tuple[str, ...] = ("block_id",), engine: str | None = None) -> DataFrame:
    """``by``, n, gram (packed), atb, btb: partial sums in each task, then a shuffle of d*d numbers per block."""
    engine = engine or ("sql" if d <= MOST_SQL_COLUMNS else "arrow")
    if engine == "sql":
        at = [F.get("features", F.lit(i)) for i in range(d)]
        sums = {f"g{i}_{j}": F.sum(at[i] * at[j]) for i, j in packed(d)} | {f"c{i}": F.sum(at[i] * F.col("label")) for i in range(d)}
        out = design.groupBy(*by).agg(F.count("*").alias("n"), *[v.alias(k) for k, v in sums.items()], F.sum(F.col("label") * F.col("label")).alias("btb"))
        return out.select(*by, "n", F.array(*[f"g{i}_{j}" for i, j in packed(d)]).alias("gram"), F.array(*[f"c{i}" for i in range(d)]).alias("atb"), "btb")
    if by != ("block_id",):
        raise ValueError("the arrow engine groups by block_id")
    upper = tuple(np.array(packed(d)).T)

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, np.ndarray] = {}
        counts: dict[int, int] = {}
        for batch in batches:
            if not batch.num_rows:
                continue
            block = batch.column(0).to_numpy()
            rows = np.column_stack([batch.column(1).flatten().to_numpy().reshape(-1, d), batch.column(2).to_numpy()])
            order = np.argsort(block, kind="stable")
            block, rows = block[order], rows[order]
            cuts = np.flatnonzero(np.r_[True, np.diff(block) != 0, True])
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                part = rows[a:b]
                k = int(block[a])
                held[k] = held.get(k, 0) + part.T @ part
                counts[k] = counts.get(k, 0) + b - a
        blocks = list(held)
        yield pa.RecordBatch.from_pydict({"block_id": pa.array(blocks, pa.int32()), "part": pa.array([TaskContext.get().partitionId() % FAN] * len(blocks), pa.int32()), "n": pa.array([counts[k] for k in blocks], pa.int64()), "m": pa.array([np.asarray(held[k]).tobytes() for k in blocks], pa.binary())})

    def add(key: tuple, table: pa.Table) -> pa.Table:
        total = sum((np.frombuffer(x, np.float64) for x in table["m"].to_pylist()), np.zeros((d + 1) ** 2))
        return pa.table({"block_id": pa.array([key[0].as_py()], pa.int32()), "n": pa.array([int(np.sum(table["n"].to_numpy()))], pa.int64()), "m": pa.array([total.tobytes()], pa.binary())})

    def unpacked(key: tuple, table: pa.Table) -> pa.Table:
        one = add(key, table)
        m = np.frombuffer(one["m"][0].as_py(), np.float64).reshape(d + 1, d + 1)
        return pa.table({"block_id": one["block_id"], "n": one["n"], "gram": pa.array([m[:d, :d][upper].tolist()], pa.list_(pa.float64())), "atb": pa.array([m[:d, d].tolist()], pa.list_(pa.float64())), "btb": pa.array([float(m[d, d])])})

    parts = design.select("block_id", "features", "label").mapInArrow(partial, "block_id int, part int, n long, m binary")
    # two levels, so that a block that every task shares is no single group of all their matrices
    some = parts.groupBy("block_id", "part").applyInArrow(lambda key, t: add(key, t), "block_id int, n long, m binary")
    return some.groupBy("block_id").applyInArrow(lambda key, t: unpacked(key, t), "block_id int, n long, gram array<double>, atb array<double>, btb double")


def total_stats(stats: DataFrame, d: int) -> DataFrame:
    """One row: n, gram, atb, btb summed over the blocks."""
    m = len(packed(d))
    sums = stats.agg(F.sum("n").alias("n"), *[F.sum(F.get("gram", F.lit(i))).alias(f"g{i}") for i in range(m)], *[F.sum(F.get("atb", F.lit(i))).alias(f"c{i}") for i in range(d)], F.sum("btb").alias("btb"))
    return sums.select("n", F.array(*[f"g{i}" for i in range(m)]).alias("gram"), F.array(*[f"c{i}" for i in range(d)]).alias("atb"), "btb")


def unpack(gram: list[float], d: int) -> np.ndarray:
    out = np.zeros((d, d))
    for v, (i, j) in zip(gram, packed(d), strict=True):
        out[i, j] = out[j, i] = v
    return out


def collect_total(stats: DataFrame, d: int) -> Total:
    """The summed statistics on the driver: d*d numbers whatever the data."""
    r = total_stats(stats, d).first()
    if not r["n"]:
        return Total(np.zeros((d, d)), np.zeros(d), 0.0, 0)
    return Total(unpack(r["gram"], d), np.array(r["atb"]), r["btb"], r["n"])


def tsqr(design: DataFrame, d: int, fan: int = 16) -> np.ndarray:
    """R of A = QR without forming the Gram matrix, by a tree of small factorisations.

    Each task reduces its rows to a d x d factor; the stored factors, one per
    task, are stacked and factored again ``fan`` at a time until few are left.
    """
    schema = "part int, r binary"

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        r, part = np.zeros((0, d)), 0
        for batch in batches:
            if batch.num_rows:
                part = batch.column(0)[0].as_py()
                r = np.linalg.qr(np.vstack([r, batch.column(1).flatten().to_numpy().reshape(-1, d)]), mode="r")
        if len(r):
            yield pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int32()), "r": pa.array([r.tobytes()], pa.binary())})

    def again(key: tuple, table: pa.Table) -> pa.Table:
        stack = np.vstack([np.frombuffer(x, np.float64).reshape(-1, d) for x in table["r"].to_pylist()])
        return pa.table({"part": pa.array([key[0].as_py()], pa.int32()), "r": pa.array([np.linalg.qr(stack, mode="r").tobytes()], pa.binary())})

    level = stored(design.select(F.spark_partition_id().alias("part"), "features").mapInArrow(local, schema), "factors")
    n = (level.agg(F.max("part")).first()[0] or 0) + 1
    while n > fan:
        level = level.select(F.floor(F.col("part") / fan).cast("int").alias("part"), "r").groupBy("part").applyInArrow(lambda key, t: again(key, t), schema)
        n = -(-n // fan)
    rows = level.orderBy("part").collect()  # at most `fan` small factors
    stack = [np.frombuffer(bytes(r["r"]), np.float64).reshape(-1, d) for r in rows]
    r = np.linalg.qr(np.vstack(stack), mode="r") if stack else np.zeros((d, d))
    return r * np.where(np.diag(r) < 0, -1.0, 1.0)[:, None]
