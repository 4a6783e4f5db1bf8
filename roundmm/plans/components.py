"""Where the time of a product goes: infrastructure, computation, communication.

Three runs of the same rounds. Infrastructure: keys only, no payload, nothing computed. Computation: keys only, each reducer multiplies
blocks that it makes itself; less the infrastructure. Communication: full payloads, the reducer hands one input on; less the
infrastructure. Spark overlaps the three, so they need not add up to the whole; what is left is reported.
"""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from roundmm.functions.schedule import Grid3D
from roundmm.model import BlockFrame, pack
from roundmm.operators.dense3d import PARTIAL, fold_slots, grid_of, keyed, multiply_3d, tasks_of
from roundmm.plans.rounds import RoundStore, small_batches

SCHEMA = "method string, rho int, rounds int, t_total double, t_infr double, t_comp double, t_comm double, residual double"


def _reducers(rows: DataFrame, mode: str) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for k in range(batch.num_rows):
                if mode == "none":
                    out.append(b"")
                elif mode == "copy":
                    out.append(batch["ca"][k].as_py())
                else:
                    nr, nk, nc = (batch[c][k].as_py() for c in ("nr", "nk", "nc"))
                    pack(np.full((nr, nk), 0.5) @ np.full((nk, nc), 0.25))
                    out.append(b"")
            yield pa.RecordBatch.from_arrays([batch[c] for c in ("i", "j", "slot", "nr", "nc")] + [pa.array(out, pa.binary())], names=["i", "j", "slot", "nr", "nc", "cells"])

    # all three payloads are inputs: a column that the reducer doesn't take would be pruned below the shuffle
    return rows.select("i", "j", "slot", "nr", "nk", "nc", "ca", "cb", "cc").mapInArrow(run, PARTIAL)


def communication_round(a: DataFrame, b: DataFrame, before: DataFrame | None, grid: Grid3D, r: int, tasks: int, mode: str) -> DataFrame:
    """Round ``r`` of an ablated run: keys placed as in the product, payloads full (``copy``) or empty, and its reducer."""
    cells = F.col("cells") if mode == "copy" else F.lit(b"")
    left = grid.copies_of_a(a.select(F.col("bi").alias("i"), F.col("bj").alias("h"), "nr", F.col("nc").alias("nk"), cells.alias("ca")), r)
    right = grid.copies_of_b(b.select(F.col("bi").alias("h"), F.col("bj").alias("j"), "nc", cells.alias("cb")), r)
    left = keyed(left, grid, tasks, "even").repartitionById(tasks, F.col("task"))
    right = keyed(right, grid, tasks, "even").select("task", "z", "nc", "cb").repartitionById(tasks, F.col("task"))
    met = left.join(right.hint("merge"), ["task", "z"])
    if before is None:
        return _reducers(met.withColumn("cc", F.lit(None).cast("binary")), mode)
    held = before.where(F.col("slot") < grid.slots(r)).withColumn("h", F.lit(0))
    held = keyed(held, grid, tasks, "even").select("task", "z", F.col("cells").alias("cc")).repartitionById(tasks, F.col("task"))
    return _reducers(met.join(held.hint("merge"), ["task", "z"], "left"), mode)


def _ablated(a: BlockFrame, b: BlockFrame, grid: Grid3D, mode: str, tasks: int) -> float:
    """Seconds of all rounds with empty or full payloads and one of the reducers above."""
    spark = a.df.sparkSession
    full = mode == "copy"
    store = RoundStore(spark)
    began = time.time()
    before: DataFrame | None = None
    for r in range(grid.product_rounds):
        with small_batches(spark, 8 * a.block_rows * a.block_cols):
            before = store.commit(mode, mode, r, grid.slots(r), communication_round(a.df, b.df, before, grid, r, tasks, mode))
    if full:
        store.commit(mode, mode, grid.product_rounds, grid.rho, fold_slots(before, a.semiring, grid.qj, tasks))
    else:
        store.commit(mode, mode, grid.product_rounds, grid.rho, before.groupBy("i", "j").count())
    return time.time() - began


def components(a: BlockFrame, b: BlockFrame, rhos: list[int], repeats: int = 1) -> DataFrame:
    """One row for each replication, medians of ``repeats`` runs. Blocks should be stored first."""
    rows = []
    for rho in rhos:
        grid = grid_of(a, b, rho)
        tasks = tasks_of(a.df, grid.qi * grid.qj * grid.rho, None)
        timed: dict[str, list[float]] = {k: [] for k in ("total", "none", "local", "copy")}
        for _ in range(repeats):
            began = time.time()
            multiply_3d(a, b, rho)
            timed["total"].append(time.time() - began)
            for mode in ("none", "local", "copy"):
                timed[mode].append(_ablated(a, b, grid, mode, tasks))
        t = {k: float(np.median(v)) for k, v in timed.items()}
        infr, comp, comm = t["none"], t["local"] - t["none"], t["copy"] - t["none"]
        rows.append(("3d", rho, grid.rounds, t["total"], infr, comp, comm, t["total"] - infr - comp - comm))
    return a.df.sparkSession.createDataFrame(rows, SCHEMA)
