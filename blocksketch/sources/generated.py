"""A Python data source for heavy-tailed matrices, and readers and writers by format."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

FORMATS = ("parquet", "orc", "json", "csv")


class _Rows(InputPartition):
    def __init__(self, start: int, end: int):
        self.start, self.end = start, end


class _Reader(DataSourceReader):
    def __init__(self, options: dict[str, str]):
        self.n, self.d = int(options.get("n", "2000")), int(options.get("d", "40"))
        self.dof, self.seed = float(options.get("dof", "2")), int(options.get("seed", "0"))
        self.blocks, self.parts = int(options.get("blocks", "100")), int(options.get("partitions", "8"))

    def partitions(self) -> Sequence[InputPartition]:
        cuts = [self.n * i // self.parts for i in range(self.parts + 1)]
        return [_Rows(a, b) for a, b in zip(cuts[:-1], cuts[1:], strict=True) if a < b]

    def read(self, partition: _Rows) -> Iterator[pa.RecordBatch]:
        for a in range(partition.start, partition.end, 4096):
            b = min(partition.end, a + 4096)
            ids = np.arange(a, b)
            # a generator per row: the matrix is the same however it is split
            rows = np.stack([np.random.default_rng((self.seed, int(i))).standard_t(self.dof, self.d) for i in ids])
            features = pa.ListArray.from_arrays(pa.array(np.arange(0, (b - a + 1) * self.d, self.d), pa.int32()), pa.array(rows.ravel()))
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array((ids * self.blocks // self.n).astype(np.int32)), features], ["row_id", "block_id", "features"])


class TMatrixSource(DataSource):
    """``spark.read.format("blocksketch_t").option("n", ...)``: rows of independent t-distributed entries."""

    @classmethod
    def name(cls) -> str:
        return "blocksketch_t"

    def schema(self) -> str:
        return "row_id long, block_id int, features array<double>"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


def register(spark: SparkSession) -> None:
    """Makes the source known to a session."""
    from blocksketch.sources.tables import ship

    ship(spark)
    spark.dataSource.register(TMatrixSource)


def read_any(spark: SparkSession, path: str, form: str = "parquet", schema: str | None = None, **options: str) -> DataFrame:
    """Files of one of FORMATS; csv and json need a schema, so that no pass is spent on guessing one."""
    if form not in FORMATS:
        raise ValueError(f"format is one of {FORMATS}")
    if form in ("csv", "json") and schema is None:
        raise ValueError(f"{form} needs a schema")
    reader = spark.read.format(form).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write_any(df: DataFrame, path: str, form: str = "parquet", by: Sequence[str] = ()) -> None:
    """Writes files of one of FORMATS, in folders by ``by``."""
    if form not in FORMATS:
        raise ValueError(f"format is one of {FORMATS}")
    df.write.format(form).partitionBy(*by).mode("overwrite").save(path)
