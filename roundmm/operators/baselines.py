"""Products to compare with: relational, broadcast, outer, one machine, and MLlib's block matrices."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from roundmm.model import BLOCK_SCHEMA, BlockFrame, MatrixFrame, pack, to_blocks, to_coordinates, unpack
from roundmm.operators.dense3d import multiply_3d
from roundmm.plans.rounds import RoundStore


def _sides(a: MatrixFrame, b: MatrixFrame) -> tuple[DataFrame, DataFrame]:
    if a.n_cols != b.n_rows:
        raise ValueError(f"inner sides don't match: {a.n_cols} and {b.n_rows}")
    return a.df.select("row", F.col("col").alias("k"), F.col("val").alias("x")), b.df.select(F.col("row").alias("k"), "col", F.col("val").alias("y"))


def _summed(met: DataFrame, a: MatrixFrame, b: MatrixFrame) -> MatrixFrame:
    sr = a.semiring
    return MatrixFrame(met.groupBy("row", "col").agg(sr.plus(sr.times(F.col("x"), F.col("y"))).alias("val")), a.n_rows, b.n_cols, sr)


def multiply_join(a: MatrixFrame, b: MatrixFrame) -> MatrixFrame:
    """Join on the inner index, aggregate by cell: one shuffle of the inputs and one of partial sums."""
    left, right = _sides(a, b)
    return _summed(left.join(right, "k"), a, b)


def multiply_broadcast(a: MatrixFrame, b: MatrixFrame, max_rows: int = 2_000_000) -> MatrixFrame:
    """B goes to every task, if it has at most ``max_rows`` entries; otherwise the join shuffles."""
    left, right = _sides(a, b)
    if right.limit(max_rows + 1).count() <= max_rows:
        right = F.broadcast(right)
    return _summed(left.join(right, "k"), a, b)


def multiply_outer(a: MatrixFrame, b: MatrixFrame, block: int, rho: int | str = "max", store: RoundStore | None = None) -> MatrixFrame:
    """Columns of A times rows of B: the 3D schedule on a ``1 x q x 1`` grid."""
    return to_coordinates(multiply_3d(to_blocks(a, a.n_rows, block, full=True), to_blocks(b, block, b.n_cols, full=True), rho, store=store))


def multiply_local(a: MatrixFrame, b: MatrixFrame, max_cells: int = 4_000_000) -> MatrixFrame:
    """On the driver, for matrices of at most ``max_cells`` cells: the sequential reference."""
    if max(a.n_rows * a.n_cols, b.n_rows * b.n_cols, a.n_rows * b.n_cols) > max_cells:
        raise ValueError(f"more than {max_cells} cells")

    def dense(m: MatrixFrame) -> np.ndarray:
        out = np.full((m.n_rows, m.n_cols), a.semiring.zero)
        t = m.df.toPandas()
        out[t["row"].to_numpy(), t["col"].to_numpy()] = t["val"].to_numpy()
        return out

    c = a.semiring.product(dense(a), dense(b))
    r, k = np.divmod(np.arange(c.size), b.n_cols)
    rows = a.df.sparkSession.createDataFrame(list(zip(r.tolist(), k.tolist(), c.ravel().tolist(), strict=True)), "row long, col long, val double")
    return MatrixFrame(rows, a.n_rows, b.n_cols, a.semiring)


def multiply_cogroup(a: BlockFrame, b: BlockFrame) -> BlockFrame:
    """One round of all block products by ``cogroup``: blocks of a row of A and a column of B meet for each block of C, and are
    added there. A task holds a whole block row and column, so this is for grids whose rows fit."""
    qi, qj, sr = a.q_rows, b.q_cols, a.semiring
    left = a.df.withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(qj - 1))))
    right = b.df.withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(qi - 1))))

    def fold(key: tuple, x: pa.Table, y: pa.Table) -> pa.Table:
        rows = {r["bj"]: r for r in x.to_pylist()}
        out, shape = None, (0, 0)
        for c in y.to_pylist():
            r = rows.get(c["bi"])
            if r is not None:
                p = sr.product(unpack(r["cells"], r["nr"], r["nc"]), unpack(c["cells"], c["nr"], c["nc"]))
                out, shape = (p if out is None else sr.merge(out, p)), (r["nr"], c["nc"])
        found = [] if out is None else [(key[0].as_py(), key[1].as_py(), *shape, pack(out))]
        kinds = (pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.binary())
        return pa.Table.from_arrays([pa.array([f[k] for f in found], t) for k, t in enumerate(kinds)], names=["bi", "bj", "nr", "nc", "cells"])

    met = left.groupBy(F.col("bi").alias("gi"), F.col("j").alias("gj")).cogroup(right.groupBy(F.col("i").alias("gi"), F.col("bj").alias("gj")))
    return replace(b, df=met.applyInArrow(fold, BLOCK_SCHEMA), n_rows=a.n_rows, block_rows=a.block_rows, semiring=sr)


def multiply_mllib(a: MatrixFrame, b: MatrixFrame, block: int) -> MatrixFrame:
    """MLlib's ``BlockMatrix.multiply`` (over RDDs), a check by other code."""
    from pyspark.mllib.linalg.distributed import CoordinateMatrix, MatrixEntry

    def blocks(m: MatrixFrame):
        entries = m.df.rdd.map(lambda r: MatrixEntry(r["row"], r["col"], r["val"]))
        return CoordinateMatrix(entries, m.n_rows, m.n_cols).toBlockMatrix(block, block)

    c = blocks(a).multiply(blocks(b)).toCoordinateMatrix()
    rows = c.entries.map(lambda e: (e.i, e.j, float(e.value)))
    return MatrixFrame(a.df.sparkSession.createDataFrame(rows, "row long, col long, val double"), a.n_rows, b.n_cols, a.semiring)


def pipeline_blocks(a: MatrixFrame, b: MatrixFrame, side: int) -> tuple[BlockFrame, BlockFrame]:
    """All square blocks of both, stored once, as every round reads them."""
    return to_blocks(a, side, side, full=True).stored(), to_blocks(b, side, side, full=True).stored()
