"""Sources and sinks: given tables, generated matrices, and the block store."""

from __future__ import annotations

import atexit
import tempfile
import uuid
import zipfile
from collections import Counter
from functools import cached_property
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, StructField, StructType

from blocksketch.functions.core import hash_normal, hash_uniform


def ship(spark: SparkSession) -> None:
    """Makes this package importable on executors, once per application."""
    sc = spark.sparkContext
    if getattr(sc, "_blocksketch_shipped", False):
        return
    top = Path(__file__).resolve().parents[2]
    if top.suffix != ".zip":
        at = Path(tempfile.mkdtemp(prefix="blocksketch-py-")) / "blocksketch_pkg.zip"
        with zipfile.ZipFile(at, "w") as z:
            for p in sorted((top / "blocksketch").rglob("*.py")):
                z.write(p, p.relative_to(top).as_posix())
        sc.addPyFile(str(at))
    sc._blocksketch_shipped = True


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given Parquet tables."""
    ship(spark)
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


_made: list[tuple[SparkSession, str]] = []


def scratch_path(spark: SparkSession, label: str) -> str:
    """A fresh path in the folder that ``spark.checkpoint.dir`` names (own folder where unset)."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        root = held.get() if held.isDefined() else None
    if not root:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        root = tempfile.mkdtemp(prefix="blocksketch-")
        spark.sparkContext.setCheckpointDir(root)
    path = f"{root.rstrip('/')}/scratch/{label}-{uuid.uuid4().hex}"
    _made.append((spark, path))
    return path


@atexit.register
def _clean() -> None:
    for spark, path in _made:
        try:
            at = spark._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)
        except Exception:  # noqa: BLE001  the session may have ended
            return


def stored(df: DataFrame, label: str = "t") -> DataFrame:
    """Written to the shared folder and read back: no lineage, no recomputation."""
    path = scratch_path(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def write_block_store(design: DataFrame, path: str, buckets: int = 64) -> None:
    """Parquet partitioned by block bucket and sorted by block, so that a draw reads only its blocks.

    Buckets, not blocks, are folders: files stay large when there are many
    blocks, and row-group bounds skip the other blocks of a bucket.
    """
    with_bucket = design.withColumn("block_bucket", F.pmod("block_id", F.lit(buckets)).cast("int"))
    with_bucket.repartition(buckets, "block_bucket").sortWithinPartitions("block_id").write.partitionBy("block_bucket").mode("overwrite").parquet(path)


def read_blocks(spark: SparkSession, path: str, blocks: list[int], buckets: int = 64, schema: StructType | None = None) -> DataFrame:
    """The rows of some blocks: partition pruning on buckets, pushed filter on blocks; a known schema saves a look at a file."""
    wanted = sorted({b % buckets for b in blocks})
    reader = spark.read if schema is None else spark.read.schema(schema)
    return reader.parquet(path).where(F.col("block_bucket").isin(wanted) & F.col("block_id").isin(sorted(set(blocks)))).drop("block_bucket")


class BlockStore:
    """A stored design of which an iteration opens the drawn blocks' files only."""

    def __init__(self, spark: SparkSession, path: str, buckets: int, schema: StructType) -> None:
        self.spark, self.path, self.buckets = spark, path, buckets
        self.schema = StructType([*schema.fields, StructField("block_bucket", IntegerType())])

    def rows(self) -> DataFrame:
        """The whole design."""
        return self.spark.read.schema(self.schema).parquet(self.path).drop("block_bucket")

    def blocks(self, wanted: list[int]) -> DataFrame:
        """The rows of some blocks."""
        return read_blocks(self.spark, self.path, wanted, self.buckets, self.schema)

    @cached_property
    def _per_bucket(self) -> Counter:
        return Counter(int(f.split("block_bucket=")[1].split("/")[0]) for f in self.rows().inputFiles())

    def files(self, wanted: list[int]) -> int:
        """How many files a read of these blocks opens: those of their buckets, which partition pruning leaves."""
        return sum(self._per_bucket[b] for b in {b % self.buckets for b in wanted})


def stored_blocks(design: DataFrame, buckets: int = 64) -> BlockStore:
    """The design in a block store of the shared scratch folder."""
    path = scratch_path(design.sparkSession, "blocks")
    write_block_store(design, path, buckets)
    return BlockStore(design.sparkSession, path, buckets, design.schema)


def t_matrix(spark: SparkSession, n: int, d: int, dof: int = 2, seed: int = 0, blocks: int = 100) -> DataFrame:
    """Rows of independent t-distributed entries (normal over root mean square of ``dof`` normals).

    Returns row_id, block_id (contiguous) and features; entries come from
    hashes of (seed, row, column), so any partitioning gives the same matrix.
    """
    ship(spark)
    size = F.floor(F.col("id") * F.lit(blocks) / F.lit(n)).cast("int")
    return t_entries(spark.range(n).select(F.col("id").alias("row_id"), size.alias("block_id")), d, dof, seed)


def t_entries(rows: DataFrame, d: int, dof: int = 2, seed: int = 0) -> DataFrame:
    """``rows`` (with row_id) and features: d independent t-distributed entries each, from hashes of (seed, row_id, column)."""
    i = F.col("row_id")

    def entry(j: int):
        # chi-square with dof = 2 m degrees is -2 ln of a product of m uniforms
        chi = -2.0 * sum((F.log(hash_uniform(f"chi{seed}", i, F.lit(j * 64 + m)) + 1e-12) for m in range(max(1, dof // 2))), F.lit(0.0))
        return hash_normal(f"t{seed}", i, F.lit(j)) / F.sqrt(chi / F.lit(float(2 * max(1, dof // 2))))

    return rows.withColumn("features", F.array(*[entry(j) for j in range(d)]))
