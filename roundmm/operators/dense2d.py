"""Dense products by the 2D schedule: row strips of A times column strips of B; each product is final."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from roundmm.functions.placement import even_task, rank_2d
from roundmm.functions.schedule import Grid2D
from roundmm.model import BlockFrame, MatrixFrame, to_blocks
from roundmm.operators.dense3d import fused, tasks_of
from roundmm.plans.rounds import RoundDriver, RoundStore, fingerprint, plan_hash


def strips(a: MatrixFrame, b: MatrixFrame, m: int) -> tuple[BlockFrame, BlockFrame]:
    """Strips of at most ``m`` cells: ``m / n_cols`` rows of A, ``m / n_rows`` columns of B."""
    if m < a.n_cols or m < b.n_rows:
        raise ValueError(f"a strip needs a whole row or column: m >= {max(a.n_cols, b.n_rows)}")
    return to_blocks(a, m // a.n_cols, a.n_cols, full=True), to_blocks(b, b.n_rows, m // b.n_rows, full=True)


def multiply_2d(a: BlockFrame, b: BlockFrame, rho: int | str = "max", schedule: str = "balanced", store: RoundStore | None = None, tasks: int | None = None, resume: bool = True, stop_after: int | None = None) -> BlockFrame:
    """``A B`` of strips in ``ceil(s / rho)`` rounds. ``schedule="row_major"`` is the naive one: the next products in row
    order, so that one strip may be copied for all of them."""
    if a.q_cols != 1 or b.q_rows != 1 or a.n_cols != b.n_rows:
        raise ValueError("A must be cut into row strips and B into column strips of the same inner side")
    spark, sr = a.df.sparkSession, a.semiring
    grid = Grid2D(a.q_rows, b.q_cols, b.q_cols if rho == "max" else int(rho), schedule == "row_major")
    tasks = tasks_of(a.df, grid.si * grid.rho, tasks)
    inputs = [fingerprint(x.df) for x in (a, b)] if store is not None and store.mode == "parquet" else []
    store = store or RoundStore(spark)
    digest = plan_hash(grid=grid, semiring=sr.name, a=(a.n_rows, a.n_cols, a.block_rows), b=(b.n_cols, b.block_cols), inputs=inputs)

    def step(r: int, before: DataFrame | None) -> DataFrame:
        left = grid.copies_of_a(a.df.select(F.col("bi").alias("i"), "nr", F.col("nc").alias("nk"), F.col("cells").alias("ca")), r)
        right = grid.copies_of_b(b.df.select(F.col("bj").alias("j"), "nc", F.col("cells").alias("cb")), r)

        def placed(df: DataFrame) -> DataFrame:
            z = (F.col("i") * grid.sj + F.col("j")).cast("long") if grid.row_major else rank_2d(F.col("i"), F.col("j"), r, grid.rho, grid.sj)
            keys = grid.si * grid.sj if grid.row_major else grid.si * grid.rho
            return df.withColumn("z", z).withColumn("task", even_task(F.col("z"), keys, tasks)).repartitionById(tasks, F.col("task"))

        # on a grid with fewer strips of B than slots of A rows, z alone may name two products: i and j join too
        met = placed(left).join(placed(right).hint("merge"), ["task", "z", "i", "j"])
        out = fused(met.withColumn("slot", F.lit(0)).withColumn("cc", F.lit(None).cast("binary")), sr)
        return out.select(F.col("i").alias("bi"), F.col("j").alias("bj"), "nr", "nc", "cells")

    block = 8 * max(a.block_rows * a.n_cols, b.block_cols * b.n_rows)
    outs = RoundDriver(store, "2d", digest, block).run(grid.rounds, grid.slots, step, resume, stop_after)
    df = outs[0]
    for more in outs[1:]:
        df = df.unionAll(more)
    return replace(b, df=df, n_rows=a.n_rows, block_rows=a.block_rows, semiring=sr)
