"""The experiment sweeps: block side, replication, components, 2D against 3D, size doubling, sparse products, partitioner,
restarts. Each gives a DataFrame of measured rows; ``python -m roundmm.workloads NAME... [--sf DIR] [--cores N]`` prints them; for speed-up over workers run
``replications`` with several ``--cores``.

Times of small matrices are nearly all fixed cost of a round, so the sweeps of times use generated matrices of some
thousand rows; the given tables are used where counts are measured.
"""

from __future__ import annotations

import sys
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from roundmm.model import BlockFrame
from roundmm.operators.baselines import pipeline_blocks
from roundmm.operators.dense2d import multiply_2d, strips
from roundmm.operators.dense3d import multiply_3d
from roundmm.operators.sparse3d import multiply_3d_sparse
from roundmm.plans import costs, density
from roundmm.plans.components import components
from roundmm.plans.rounds import RoundStore, Stopped
from roundmm.sources.generators import signed
from roundmm.sources.tables import fold_a, fold_b, scatter

ROWS = "workload string, method string, side int, block int, rho int, rounds int, seconds double, last_round double, per_extra_round double"


def _timed(run: Callable[[RoundStore], BlockFrame], spark: SparkSession) -> tuple[float, list[float]]:
    store = RoundStore(spark)
    began = time.time()
    run(store)
    took = time.time() - began
    return took, [r["seconds"] for r in sorted(store.ledger, key=lambda r: r["round"])]


def _sweep(spark: SparkSession, name: str, side: int, block: int, rhos: list[int], blocks: tuple[BlockFrame, BlockFrame] | None = None) -> list[tuple]:
    a, b = blocks or pipeline_blocks(signed(spark, side), signed(spark, side), block)
    timed = {rho: _timed(lambda s, rho=rho: multiply_3d(a, b, rho, store=s), spark) for rho in rhos}
    mono = timed[max(rhos)][0]
    return [(name, "3d", side, block, rho, len(rounds), took, rounds[-1], costs.overhead_per_round(took, len(rounds), mono)) for rho, (took, rounds) in timed.items()]


def block_sides(spark: SparkSession, sf_dir: str, side: int = 2048) -> DataFrame:
    """Time against the block side, monolithic and with one group a round."""
    rows = []
    for block in (side // 16, side // 8, side // 4):
        rows += _sweep(spark, "block side", side, block, [1, side // block])
    return spark.createDataFrame(rows, ROWS)


def replications(spark: SparkSession, sf_dir: str, sides: tuple[int, ...] = (1024, 2048), block: int = 256) -> DataFrame:
    """Time and rounds against the replication."""
    rows = []
    for side in sides:
        q = side // block
        rows += _sweep(spark, "replication", side, block, [r for r in (1, 2, 4, 8) if r <= q])
    return spark.createDataFrame(rows, ROWS)


def component_split(spark: SparkSession, sf_dir: str, side: int = 1024, block: int = 256) -> DataFrame:
    a, b = pipeline_blocks(signed(spark, side), signed(spark, side), block)
    return components(a, b, [1, 2, side // block])


def two_d_three_d(spark: SparkSession, sf_dir: str, side: int = 1024, block: int = 256) -> DataFrame:
    """3D and 2D of the same subproblem size, over the replications."""
    rows = _sweep(spark, "2d or 3d", side, block, [1, 2, side // block])
    a, b = strips(signed(spark, side), signed(spark, side), block * block)
    a, b = a.stored(), b.stored()
    for rho in (1, 4, 16):
        took, rounds = _timed(lambda s, rho=rho: multiply_2d(a, b, rho, store=s), spark)
        rows.append(("2d or 3d", "2d", side, block * block // side, rho, len(rounds), took, rounds[-1], None))
    return spark.createDataFrame(rows, ROWS)


def doubling(spark: SparkSession, sf_dir: str, sides: tuple[int, ...] = (1024, 2048, 4096), block: int = 512) -> DataFrame:
    """Time as the side doubles, one group a round and monolithic."""
    rows = []
    for side in sides:
        rows += _sweep(spark, "doubling", side, block, sorted({1, side // block}))
    return spark.createDataFrame(rows, ROWS)


def sparse_products(spark: SparkSession, sf_dir: str, side: int = 8192) -> DataFrame:
    """Random-like sparse squares over grids and replications: time, output cells, density against the law."""
    a = scatter(spark, sf_dir, side)
    nnz = a.df.count()
    law = (nnz / side**2) ** 2 * side
    rows = []
    for q in (4, 8, 16):
        for rho in (r for r in (1, 2, 4, 8, 16) if r <= q):
            began = time.time()
            cells = multiply_3d_sparse(a, a, 0, rho, side=side // q).df.count()
            rows.append((side, q, rho, -(-q // rho) + 1, time.time() - began, nnz, cells, cells / side**2, law))
    return spark.createDataFrame(rows, "side int, q int, rho int, rounds int, seconds double, entries long, cells long, density double, law double")


def density_law(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = []
    for side in (1024, 8192, 65536):
        a = scatter(spark, sf_dir, side)
        p, x = density.profile(a, a, "er"), density.profile(a, a, "exact")
        rows.append((side, p.delta_a, p.delta_out, x.delta_out, x.delta_out / p.delta_out - 1 if p.delta_out else 0.0))
    return spark.createDataFrame(rows, "side int, delta double, law double, measured double, error double")


def placements(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Keys per task of the first round, ranked and hashed."""
    out = None
    for tasks in (16, 32, 64):
        for how in ("even", "polynomial"):
            one = costs.task_loads(spark, 8, 8, tasks, how).agg(F.min("keys").alias("least"), F.max("keys").alias("most"), F.count_if(F.col("keys") == 0).alias("idle")).select(F.lit(tasks).alias("tasks"), F.lit(how).alias("placement"), "least", "most", "idle")
            out = one if out is None else out.unionAll(one)
    return out


def restarts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stop after each round and resume: seconds until the stop, seconds of the rest, against an uninterrupted run."""
    a, b = pipeline_blocks(fold_a(spark, sf_dir, 64), fold_b(spark, sf_dir, 64), 16)
    whole, _ = _timed(lambda s: multiply_3d(a, b, 1, store=s), spark)
    rows = []
    for stop in range(4):
        store = RoundStore(spark)
        began = time.time()
        try:
            multiply_3d(a, b, 1, store=store, stop_after=stop)
        except Stopped:
            pass
        half = time.time()
        multiply_3d(a, b, 1, store=store)
        rows.append((stop, half - began, time.time() - half, whole))
    return spark.createDataFrame(rows, "stopped_after int, before double, resumed double, uninterrupted double")


def store_choice(spark: SparkSession, sf_dir: str, side: int = 1024, block: int = 256) -> DataFrame:
    """Rounds kept in files, by checkpoint, in executors, or not at all."""
    a, b = pipeline_blocks(signed(spark, side), signed(spark, side), block)
    rows = []
    for mode in ("parquet", "checkpoint", "persist", "none"):
        began = time.time()
        multiply_3d(a, b, 1, store=RoundStore(spark, mode)).df.count()
        rows.append((mode, time.time() - began))
    return spark.createDataFrame(rows, "store string, seconds double")


FACTORS = "measure string, rho int, from_size int, to_size int, from_seconds double, to_seconds double, factor double"


def _factors(spark: SparkSession, name: str, times: dict[tuple[int, int], float], falls: bool = False) -> DataFrame:
    """Each time over the one before (``falls``: the other way round), of times by (rho, size)."""
    rows = []
    for rho in sorted({r for r, _ in times}):
        sizes = sorted(n for r, n in times if r == rho)
        for lo, hi in zip(sizes, sizes[1:], strict=False):
            x, y = times[rho, lo], times[rho, hi]
            rows.append((name, rho, lo, hi, x, y, x / y if falls else y / x))
    return spark.createDataFrame(rows, FACTORS)


def doubling_factors(spark: SparkSession, sf_dir: str, sides: tuple[int, ...] = (128, 256, 512), block: int = 64) -> DataFrame:
    """How much longer a product takes as the side doubles; ``rho`` 0 stands for the monolithic one."""
    times = {}
    for side in sides:
        for row in _sweep(spark, "doubling", side, block, sorted({1, side // block})):
            times[1 if row[4] == 1 else 0, side] = row[6]
    return _factors(spark, "side doubled", times)


def block_gains(spark: SparkSession, sf_dir: str, side: int = 512) -> DataFrame:
    """How much sooner the monolithic product ends as the block side doubles."""
    return _factors(spark, "block side doubled", {(0, block): _sweep(spark, "block", side, block, [side // block])[0][6] for block in (side // 16, side // 8, side // 4)}, True)


def task_speedup(spark: SparkSession, sf_dir: str, side: int = 512, block: int = 128, workers: tuple[int, ...] = (1, 2, 4)) -> DataFrame:
    """Speed-up as the reduce tasks double: a session's cores are fixed, tasks stand in for them."""
    a, b = pipeline_blocks(signed(spark, side), signed(spark, side), block)
    times = {(rho, t): _timed(lambda s, rho=rho, t=t: multiply_3d(a, b, rho, store=s, tasks=t), spark)[0] for rho in (1, 2, 4) for t in workers}
    return _factors(spark, "tasks doubled", times, True)


def two_setups(spark: SparkSession, sf_dir: str, side: int = 512, blocks: tuple[int, ...] = (64, 128)) -> DataFrame:
    """Block sides, replications and the time of each extra round under two set-ups: rounds in files, and rounds held by executors."""
    rows = []
    for setup in ("parquet", "persist"):
        for block in blocks:
            a, b = pipeline_blocks(signed(spark, side), signed(spark, side), block)
            q, times = side // block, {}
            for rho in (r for r in (1, 2, 4, 8) if r <= q):
                began = time.time()
                multiply_3d(a, b, rho, store=RoundStore(spark, setup)).df.write.format("noop").mode("overwrite").save()
                times[rho] = time.time() - began
                spark.catalog.clearCache()
            rows += [(setup, side, block, rho, -(-q // rho) + 1, t, costs.overhead_per_round(t, -(-q // rho) + 1, times[max(times)])) for rho, t in times.items()]
    return spark.createDataFrame(rows, "setup string, side int, block int, rho int, rounds int, seconds double, per_extra_round double")


WORKLOADS = {
    "doubling_factors": doubling_factors, "block_gains": block_gains, "task_speedup": task_speedup, "two_setups": two_setups,
    "block_sides": block_sides, "replications": replications, "component_split": component_split, "two_d_three_d": two_d_three_d, "doubling": doubling,
    "sparse_products": sparse_products, "density_law": density_law, "placements": placements, "restarts": restarts, "store_choice": store_choice,
}


def main(args: list[str]) -> None:
    sf_dir = args[args.index("--sf") + 1] if "--sf" in args else "/root/testdata/sf0.1"
    cores = args[args.index("--cores") + 1] if "--cores" in args else "8"
    names = [a for a in args if a in WORKLOADS] or list(WORKLOADS)
    spark = SparkSession.builder.master(f"local[{cores}]").config("spark.driver.memory", "12g").config("spark.sql.shuffle.partitions", "16").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    multiply_3d(*pipeline_blocks(signed(spark, 64), signed(spark, 64), 16), 2)  # warm-up
    for name in names:
        print(f"## {name}", flush=True)
        for row in WORKLOADS[name](spark, sf_dir).collect():
            print(" | ".join(f"{k}={v:.3f}" if isinstance(v, float) and abs(v) > 1e-2 else f"{k}={v:.3e}" if isinstance(v, float) else f"{k}={v}" for k, v in row.asDict().items()), flush=True)


if __name__ == "__main__":
    main(sys.argv[1:])
