"""Generated matrices: dense, random sparse, identity; a Python data source; Matrix Market text."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from roundmm.functions.semiring import PLUS_TIMES, Semiring
from roundmm.model import MatrixFrame


def _cells(spark: SparkSession, rows: int, cols: int) -> DataFrame:
    return spark.range(rows * cols).select(F.floor(F.col("id") / cols).cast("long").alias("row"), F.pmod("id", F.lit(cols)).cast("long").alias("col"))


def signed(spark: SparkSession, n: int) -> MatrixFrame:
    """A full matrix of small whole numbers of both signs, by a rule."""
    return MatrixFrame(_cells(spark, n, n).withColumn("val", (F.pmod(31 * F.col("row") + 17 * F.col("col"), F.lit(11)) - 5).cast("double")), n, n)


def dense_random(spark: SparkSession, rows: int, cols: int, seed: int = 1) -> MatrixFrame:
    """Values in [0, 1), from a hash: the same on any partitioning."""
    u = F.pmod(F.xxhash64("row", "col", F.lit(seed)), F.lit(1 << 40)) / F.lit(float(1 << 40))
    return MatrixFrame(_cells(spark, rows, cols).withColumn("val", u), rows, cols)


def er_random(spark: SparkSession, n: int, delta: float, seed: int = 1) -> MatrixFrame:
    """Each cell is 1 with chance ``delta``, independently: every row draws how many entries it has, and which. A row's draws follow from seed and row, so they
    are the same on any partitioning; work follows the entries, not the cells."""

    def draw(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows, cols = [], []
            for row in batch["id"].to_pylist():
                rng = np.random.Generator(np.random.Philox(key=[seed, row]))
                cols.append(np.sort(rng.choice(n, rng.binomial(n, delta), replace=False, shuffle=False)).astype(np.int64))
                rows.append(np.full(len(cols[-1]), row, np.int64))
            if rows:
                at = np.concatenate(rows)
                yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(np.concatenate(cols)), pa.array(np.ones(len(at)))], names=["row", "col", "val"])

    return MatrixFrame(spark.range(n).mapInArrow(draw, "row long, col long, val double"), n, n)


def identity(spark: SparkSession, n: int, semiring: Semiring = PLUS_TIMES) -> MatrixFrame:
    d = spark.range(n).select(F.col("id").alias("row"), F.col("id").alias("col"), F.lit(semiring.one).alias("val"))
    return MatrixFrame(d, n, n, semiring)


def diagonal(values: DataFrame, n: int, semiring: Semiring = PLUS_TIMES) -> MatrixFrame:
    """``values(idx, val)`` on the diagonal."""
    return MatrixFrame(values.select(F.col("idx").cast("long").alias("row"), F.col("idx").cast("long").alias("col"), F.col("val").cast("double").alias("val")), n, n, semiring)


def read_matrix(spark: SparkSession, path: str, fmt: str, n_rows: int, n_cols: int, **options) -> MatrixFrame:
    """``row, col, val`` files (parquet, orc, csv, json), or ``mtx``: Matrix Market coordinates, counted from 1."""
    if fmt == "mtx":
        parts = F.split(F.trim("value"), r"\s+")
        text = spark.read.text(path).select("value", F.col("_metadata.file_path").alias("_file"), F.col("_metadata.file_block_start").alias("_block"), F.monotonically_increasing_id().alias("_line"))
        lines = text.where(~F.col("value").startswith("%") & (F.trim("value") != ""))
        # the first line of a file that is no comment states the sides and the number of entries
        size = lines.where("_block = 0").groupBy("_file").agg(F.min("_line").alias("_line"))
        cells = lines.join(F.broadcast(size), ["_file", "_line"], "left_anti")  # a row a file
        return MatrixFrame(cells.select((parts[0].cast("long") - 1).alias("row"), (parts[1].cast("long") - 1).alias("col"), parts[2].cast("double").alias("val")), n_rows, n_cols)
    return MatrixFrame(spark.read.schema("row long, col long, val double").format(fmt).options(**options).load(path), n_rows, n_cols)


def write_matrix(m: MatrixFrame, path: str, fmt: str = "parquet", partition_by: list[str] | None = None) -> None:
    w = m.df.write.mode("overwrite").format(fmt)
    (w.partitionBy(*partition_by) if partition_by else w).save(path)


class Chunk(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class SignedReader(DataSourceReader):
    def __init__(self, n: int, parts: int):
        self.n, self.parts = n, parts

    def partitions(self) -> list[InputPartition]:
        step = -(-self.n // self.parts)
        return [Chunk(k, min(k + step, self.n)) for k in range(0, self.n, step)]

    def read(self, partition: Chunk) -> Iterator[tuple]:
        for r in range(partition.lo, partition.hi):
            for c in range(self.n):
                yield r, c, float((31 * r + 17 * c) % 11 - 5)


class SignedSource(DataSource):
    """``spark.read.format("signed_matrix").option("n", ...)``: the matrix of :func:`signed`, row ranges as partitions."""

    @classmethod
    def name(cls) -> str:
        return "signed_matrix"

    def schema(self) -> str:
        return "row long, col long, val double"

    def reader(self, schema) -> DataSourceReader:
        return SignedReader(int(self.options.get("n", "8")), int(self.options.get("parts", "4")))


def register_sources(spark: SparkSession) -> None:
    spark.dataSource.register(SignedSource)
