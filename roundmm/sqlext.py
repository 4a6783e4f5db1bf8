"""The SQL side: schedules and costs as table functions, slots and tasks as functions, block functions, products of views."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf
from pyspark.sql.types import BinaryType

from roundmm.functions.schedule import ceil_div
from roundmm.functions.semiring import PLUS_TIMES, SEMIRINGS, Semiring
from roundmm.model import MatrixFrame, pack, unpack
from roundmm.operators.baselines import multiply_join


@udtf(returnType="i int, h int, j int, round int, slot int")
class Schedule3D:
    """``schedule_3d(q, rho)``: every product of a square grid."""

    def eval(self, q: int, rho: int):
        for i in range(q):
            for h in range(q):
                for j in range(q):
                    g = (h - i - j) % q
                    yield i, h, j, g // rho, g % rho


@udtf(returnType="i int, j int, round int")
class Schedule2D:
    """``schedule_2d(s, rho)``."""

    def eval(self, s: int, rho: int):
        for i in range(s):
            for j in range(s):
                yield i, j, ((j - i) % s) // rho


@udtf(returnType="rho int, rounds int, shuffle_words double, total_words double, reducer_words double")
class Cost3D:
    """``cost_3d(side, block)``: a row for each replication."""

    def eval(self, side: int, block: int):
        q, n = ceil_div(side, block), float(side) * side
        for rho in range(1, q + 1):
            yield rho, ceil_div(q, rho) + 1, min(3 * rho, 3 * q) * n, 3 * q * n, 3.0 * block * block


def register(spark: SparkSession) -> None:
    """Register the table functions and ``slot3d``, ``round3d``, ``task3d`` for the session."""
    for name, f in (("schedule_3d", Schedule3D), ("schedule_2d", Schedule2D), ("cost_3d", Cost3D)):
        spark.udtf.register(name, f)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION slot3d(i INT, h INT, j INT, q INT, rho INT) RETURNS INT RETURN pmod(pmod(h - i - j, q), rho)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION round3d(i INT, h INT, j INT, q INT, rho INT) RETURNS INT RETURN pmod(h - i - j, q) div rho")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION task3d(i INT, j INT, slot INT, q INT, rho INT, t INT) RETURNS INT "
        "RETURN CASE WHEN q * q * rho < t THEN pmod((i * q + j) * rho + slot, t) "
        "WHEN (i * q + j) * rho + slot < (q * q * rho div t) * t THEN ((i * q + j) * rho + slot) div (q * q * rho div t) "
        "ELSE pmod(xxhash64(CAST((i * q + j) * rho + slot AS BIGINT), 17), t) END"
    )


def register_matrix(spark: SparkSession, name: str, m: MatrixFrame) -> None:
    m.df.createOrReplaceTempView(name)


def sql_product(spark: SparkSession, a: str, b: str, semiring: Semiring | str = PLUS_TIMES) -> DataFrame:
    """The product of two registered views ``(row, col, val)``, as SQL would write it: a join and an aggregate."""
    sr = SEMIRINGS[semiring] if isinstance(semiring, str) else semiring
    side = lambda v: MatrixFrame(spark.table(v), 0, 0, sr)
    return multiply_join(side(a), side(b)).df


def block_fma(semiring: Semiring = PLUS_TIMES):
    """``f(a, b, c, nr, nk, nc)``: a block's partial sum plus a product, on packed cells (``c`` may be null)."""

    @F.arrow_udf(BinaryType())
    def fma(a: pa.Array, b: pa.Array, c: pa.Array, nr: pa.Array, nk: pa.Array, nc: pa.Array) -> pa.Array:
        out = []
        for x, y, z, r, k, n in zip(a.to_pylist(), b.to_pylist(), c.to_pylist(), nr.to_pylist(), nk.to_pylist(), nc.to_pylist(), strict=True):
            p = semiring.product(unpack(x, r, k), unpack(y, k, n))
            out.append(pack(p if z is None else semiring.merge(p, unpack(z, r, n))))
        return pa.array(out, pa.binary())

    return fma


@F.arrow_udf(BinaryType())
def block_transpose(cells: pa.Array, nr: pa.Array, nc: pa.Array) -> pa.Array:
    """Cells of the transposed block."""
    return pa.array([pack(unpack(x, r, c).T) for x, r, c in zip(cells.to_pylist(), nr.to_pylist(), nc.to_pylist(), strict=True)], pa.binary())


def block_sum(semiring: Semiring = PLUS_TIMES):
    """An aggregate: the sum of blocks of one shape. Spark holds a group's blocks at once, so groups must be small; the
    fold of a product streams instead."""

    @F.pandas_udf(BinaryType())
    def total(cells: pd.Series) -> bytes:
        out: np.ndarray | None = None
        for x in cells:
            y = np.frombuffer(x, "<f8")
            out = y if out is None else semiring.merge(out, y)
        return b"" if out is None else pack(out)

    return total


def scaled_blocks(df: DataFrame, factor: float) -> DataFrame:
    """Block rows with all cells times a number, in Arrow batches."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cells = pa.array([pack(np.frombuffer(x, "<f8") * factor) for x in batch["cells"].to_pylist()], pa.binary())
            yield batch.set_column(batch.schema.get_field_index("cells"), "cells", cells)

    return df.mapInArrow(run, df.schema)


def packed_sum(cells: Column) -> Column:
    return block_sum()(cells)
