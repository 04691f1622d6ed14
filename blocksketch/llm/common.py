"""Helpers shared by the text operators: scratch tables, package shipping, buffers."""

from __future__ import annotations

import atexit
import io
import os
import tempfile
import uuid
import zipfile
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
_made: dict[str, SparkSession] = {}
#: Session setting (not fixed at start) by which Spark deletes a finished query's shuffle files at once.
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"

#: Session setting for the most bytes of an Arrow batch, its default (no bound to speak of), and ours.
_BATCH, _UNBOUNDED, BATCH_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch", ("2147483647", "2147483647b", "2147483646", "-1"), 8 << 20


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables, by any path that Spark can read."""
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def ascii_lower(col: Column) -> Column:
    """Lower-cases A-Z and nothing else."""
    return F.translate(col, UPPER, UPPER.lower())


def scratch_root(spark: SparkSession) -> str:
    """The shared folder named by ``spark.checkpoint.dir``.

    Where the session names none (tests on one machine) a folder of this
    process is made and set, so that ``checkpoint()`` works as well.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    current = spark.sparkContext._jsc.sc().getCheckpointDir()
    if current.isDefined():
        return current.get().rstrip("/")
    if spark.sparkContext.master.split("[")[0] not in ("local",):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    own = tempfile.mkdtemp(prefix="blocksketch-")
    spark.sparkContext.setCheckpointDir(own)
    return own


def materialise(df: DataFrame, label: str = "t") -> DataFrame:
    """Writes ``df`` to the shared scratch folder and reads it back.

    Cuts the lineage: a lost executor costs a reread, not the work above. The
    shuffle files of the plan go as soon as the table is written; the table is
    deleted by ``discard`` or when the driver ends.
    """
    spark = df.sparkSession
    path = f"{scratch_root(spark)}/scratch/{label}-{uuid.uuid4().hex}"
    before = spark.conf.get(_CLEANUP, None)
    spark.conf.set(_CLEANUP, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(_CLEANUP, before) if before is not None else spark.conf.unset(_CLEANUP)
    _made[path] = spark
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    return out


def discard(df: DataFrame) -> None:
    """Deletes a table made by ``materialise`` that nothing reads any more."""
    path = getattr(df, "_scratch_path", None)
    if path and (spark := _made.pop(path, None)) is not None:
        _delete(spark, path)


def _delete(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


@atexit.register
def _clean() -> None:
    for path, spark in list(_made.items()):
        try:
            _delete(spark, path)
        except Exception:  # the session may have ended before  # noqa: BLE001
            return


def ship(spark: SparkSession) -> None:
    """Makes this package importable on executors, once per application.

    Bounds the bytes of an Arrow batch too, where the session does not: texts
    may be very long, and a batch of the usual number of rows any size.
    """
    sc = spark.sparkContext
    if spark.conf.get(_BATCH, None) in (None, *_UNBOUNDED):
        spark.conf.set(_BATCH, str(BATCH_BYTES))
    if getattr(sc, "_blocksketch_shipped", False):
        return
    top = Path(__file__).resolve().parents[2]
    if top.suffix != ".zip":
        buffer = io.BytesIO()
        with zipfile.ZipFile(buffer, "w") as z:
            for p in sorted((top / "blocksketch").rglob("*.py")):
                z.write(p, p.relative_to(top).as_posix())
        at = os.path.join(tempfile.mkdtemp(prefix="blocksketch-py-"), "blocksketch_pkg.zip")
        Path(at).write_bytes(buffer.getvalue())
        sc.addPyFile(at)
    sc._blocksketch_shipped = True


def text_buffer(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of a string column end to end, and the row offsets; nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
        if isinstance(column, pa.ChunkedArray):
            column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.string())
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    buffers = column.buffers()
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(buffers[1], np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = np.frombuffer(buffers[2], np.uint8) if buffers[2] is not None else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def row_runs(offsets: np.ndarray, most: int) -> list[tuple[int, int]]:
    """Runs of rows of about ``most`` bytes each; a longer row is a run of its own."""
    out, start, n = [], 0, len(offsets) - 1
    while start < n:
        end = max(start + 1, int(np.searchsorted(offsets, offsets[start] + most, "right")) - 1)
        out.append((start, min(end, n)))
        start = out[-1][1]
    return out


def mix(x: np.ndarray) -> np.ndarray:
    """A fixed 64-bit finaliser (public splitmix constants)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))
