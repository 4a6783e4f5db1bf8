"""Matrices as coordinate frames and as frames of blocks."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from roundmm.functions.schedule import ceil_div
from roundmm.functions.semiring import PLUS_TIMES, Semiring
from roundmm.scratch import stored

BLOCK_SCHEMA = "bi int, bj int, nr int, nc int, cells binary"


@dataclass(frozen=True)
class MatrixFrame:
    """``df(row long, col long, val double)``: at most one row a cell; a missing cell is the semiring's zero."""

    df: DataFrame
    n_rows: int
    n_cols: int
    semiring: Semiring = PLUS_TIMES

    @property
    def T(self) -> MatrixFrame:
        return replace(self, df=self.df.select(F.col("col").alias("row"), F.col("row").alias("col"), "val"), n_rows=self.n_cols, n_cols=self.n_rows)

    def rows(self, lo: int, hi: int) -> MatrixFrame:
        """Rows ``lo <= row < hi``, coordinates kept; the filter reaches the scan."""
        return replace(self, df=self.df.where((F.col("row") >= lo) & (F.col("row") < hi)))

    def cols(self, lo: int, hi: int) -> MatrixFrame:
        return replace(self, df=self.df.where((F.col("col") >= lo) & (F.col("col") < hi)))

    def where(self, condition: Column | str) -> MatrixFrame:
        return replace(self, df=self.df.where(condition))

    def over(self, semiring: Semiring) -> MatrixFrame:
        return replace(self, semiring=semiring)

    def dense(self) -> MatrixFrame:
        """All cells, missing ones as zero of the semiring."""
        spark = self.df.sparkSession
        cells = spark.range(self.n_rows * self.n_cols).select(F.floor(F.col("id") / self.n_cols).cast("long").alias("row"), F.pmod("id", F.lit(self.n_cols)).cast("long").alias("col"))
        return replace(self, df=cells.join(self.df, ["row", "col"], "left").select("row", "col", F.coalesce("val", F.lit(self.semiring.zero)).alias("val")))

    def __matmul__(self, other: MatrixFrame):
        from roundmm.plans.rewrite import leaf

        return leaf(self) @ leaf(other)

    def expr(self):
        from roundmm.plans.rewrite import leaf

        return leaf(self)


def matrix_from(df: DataFrame, row: Column, col: Column, val: Column, n_rows: int, n_cols: int, semiring: Semiring = PLUS_TIMES) -> MatrixFrame:
    """A matrix of any table: cells that meet are added in the semiring; rows with a null coordinate or value are left out."""
    cells = df.select(row.cast("long").alias("row"), col.cast("long").alias("col"), val.cast("double").alias("val")).dropna()
    return MatrixFrame(cells.groupBy("row", "col").agg(semiring.plus("val").alias("val")), n_rows, n_cols, semiring)


def transposed(a: MatrixFrame, b: MatrixFrame) -> bool:
    """Whether the plans show that ``b`` is ``a`` transposed. Plans are compared by places of columns, not by their names."""
    if any(m.df.columns != ["row", "col", "val"] for m in (a, b)):
        return False
    return a.T.df.sameSemantics(b.df) or b.T.df.sameSemantics(a.df)


@dataclass(frozen=True)
class BlockFrame:
    """Dense blocks of a matrix; ``cells`` are float64, little-endian, in row order. A short last block is not padded."""

    df: DataFrame
    n_rows: int
    n_cols: int
    block_rows: int
    block_cols: int
    semiring: Semiring = PLUS_TIMES

    def stored(self) -> BlockFrame:
        """The blocks as files in the shared folder: rounds read them again and again."""
        return replace(self, df=stored(self.df, "blocks"))

    @property
    def q_rows(self) -> int:
        return ceil_div(self.n_rows, self.block_rows)

    @property
    def q_cols(self) -> int:
        return ceil_div(self.n_cols, self.block_cols)


def pack(cells: np.ndarray) -> bytes:
    return np.ascontiguousarray(cells, "<f8").tobytes()


def unpack(cells: bytes, rows: int, cols: int) -> np.ndarray:
    return np.frombuffer(cells, "<f8").reshape(rows, cols)


def to_blocks(m: MatrixFrame, block_rows: int, block_cols: int, full: bool = False) -> BlockFrame:
    """One shuffle by block; rows are sorted by block and streamed into one array at a time, so a block is never a list of rows.
    Blocks without cells get no row, or with ``full`` one of zeros, as a dense matrix has."""
    br, bc, zero = block_rows, block_cols, m.semiring.zero
    if br < 1 or bc < 1:
        raise ValueError("a block has at least one row and one column")
    at = m.df.select(
        F.floor(F.col("row") / br).cast("int").alias("bi"), F.floor(F.col("col") / bc).cast("int").alias("bj"),
        F.pmod("row", F.lit(br)).cast("int").alias("r"), F.pmod("col", F.lit(bc)).cast("int").alias("c"), F.col("val").cast("double").alias("v"),
    )
    if full:
        rows, cols = ceil_div(m.n_rows, br), ceil_div(m.n_cols, bc)
        none = [F.lit(None).cast(t).alias(c) for c, t in (("r", "int"), ("c", "int"), ("v", "double"))]
        at = at.unionAll(m.df.sparkSession.range(rows * cols).select(F.floor(F.col("id") / cols).cast("int").alias("bi"), F.pmod("id", F.lit(cols)).cast("int").alias("bj"), *none))

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at: tuple[int, int] | None = None
        cells: np.ndarray | None = None

        def done() -> pa.RecordBatch:
            values = (*at, *cells.shape)
            return pa.RecordBatch.from_arrays([*(pa.array([x], pa.int32()) for x in values), pa.array([pack(cells)], pa.binary())], names=["bi", "bj", "nr", "nc", "cells"])

        for batch in batches:
            if not batch.num_rows:
                continue
            i, j = batch["bi"].to_numpy(), batch["bj"].to_numpy()
            cut = [0, *(np.flatnonzero((i[1:] != i[:-1]) | (j[1:] != j[:-1])) + 1), batch.num_rows]
            for lo, hi in zip(cut, cut[1:], strict=False):
                if at != (i[lo], j[lo]):
                    if at is not None:
                        yield done()
                    at = (int(i[lo]), int(j[lo]))
                    cells = np.full((min(br, m_rows - at[0] * br), min(bc, m_cols - at[1] * bc)), zero)
                part = batch.slice(lo, hi - lo)
                part = part.filter(part["r"].is_valid())
                cells[part["r"].to_numpy(), part["c"].to_numpy()] = part["v"].to_numpy(zero_copy_only=False)
        if at is not None:
            yield done()

    m_rows, m_cols = m.n_rows, m.n_cols
    return BlockFrame(at.repartition("bi", "bj").sortWithinPartitions("bi", "bj").mapInArrow(packed, BLOCK_SCHEMA), m.n_rows, m.n_cols, br, bc, m.semiring)


def to_coordinates(b: BlockFrame) -> MatrixFrame:
    """All cells of the blocks that exist."""
    br, bc = b.block_rows, b.block_cols

    def cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                nr, nc = batch["nr"][k].as_py(), batch["nc"][k].as_py()
                r, c = np.divmod(np.arange(nr * nc), nc)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(r + batch["bi"][k].as_py() * br), pa.array(c + batch["bj"][k].as_py() * bc), pa.array(unpack(batch["cells"][k].as_py(), nr, nc).ravel())], names=["row", "col", "val"]
                )

    return MatrixFrame(b.df.select("bi", "bj", "nr", "nc", "cells").mapInArrow(cells, "row long, col long, val double"), b.n_rows, b.n_cols, b.semiring)
