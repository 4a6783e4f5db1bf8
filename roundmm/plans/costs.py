"""What a product costs: rounds, words shuffled by round and side, reducer sizes, copies, task loads.

Measured figures come from the schedule's own replication of block descriptions (no payload is read); bounds are closed forms.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from roundmm.functions.placement import even_task, polynomial_task, rank_2d, rank_3d
from roundmm.functions.schedule import Grid2D, Grid3D, ceil_div, schedule_3d
from roundmm.model import MatrixFrame
from roundmm.plans.rounds import small_batches
from roundmm.scratch import stored

LEDGER = "method string, rho int, round int, side string, pairs long, words long"


def block_axis(spark: SparkSession, side: int, block: int, name: str) -> DataFrame:
    """``name, n_name``: the blocks of an axis and their lengths."""
    q = ceil_div(side, block)
    return spark.range(q).select(F.col("id").cast("int").alias(name), F.least(F.lit(block), F.lit(side) - F.col("id") * block).cast("long").alias(f"n_{name}"))


def block_pairs(spark: SparkSession, rows: tuple[int, int], cols: tuple[int, int], names: tuple[str, str]) -> DataFrame:
    """Descriptions of all blocks of a dense matrix, a row a block, and their words."""
    n, b = cols
    q = ceil_div(n, b)
    each = block_axis(spark, *rows, names[0]).withColumn(names[1], F.explode(F.sequence(F.lit(0), F.lit(q - 1))))
    return each.select(*names, (F.col(f"n_{names[0]}") * F.least(F.lit(b), F.lit(n) - F.col(names[1]) * b)).cast("long").alias("words"))


def _sum(df: DataFrame, method: str, rho: int, r: int, side: str) -> DataFrame:
    return df.groupBy().agg(F.count(F.lit(1)).alias("pairs"), F.coalesce(F.sum("words"), F.lit(0)).cast("long").alias("words")).select(
        F.lit(method).alias("method"), F.lit(rho).alias("rho"), F.lit(r).alias("round"), F.lit(side).alias("side"), "pairs", "words"
    )


def ledger_3d(spark: SparkSession, sides: tuple[int, int, int], block: int, rho: int) -> DataFrame:
    """Pairs and words shuffled, by round and side, of a dense 3D product with accumulated slots."""
    n, k, m = sides
    grid = Grid3D(ceil_div(n, block), ceil_div(k, block), ceil_div(m, block), rho)
    a, b = block_pairs(spark, (n, block), (k, block), ("i", "h")), block_pairs(spark, (k, block), (m, block), ("h", "j"))
    c = block_pairs(spark, (n, block), (m, block), ("i", "j"))
    out = []
    for r in range(grid.product_rounds):
        out += [_sum(grid.copies_of_a(a, r), "3d", rho, r, "A"), _sum(grid.copies_of_b(b, r), "3d", rho, r, "B")]
        if r:
            live = c.withColumn("slot", F.explode(F.sequence(F.lit(0), F.lit(grid.slots(r) - 1))))
            out.append(_sum(live, "3d", rho, r, "C"))
    slots = min(rho, grid.qh)
    out.append(_sum(c.withColumn("slot", F.explode(F.sequence(F.lit(0), F.lit(slots - 1)))), "3d", rho, grid.product_rounds, "C"))
    return _all(out)


def ledger_2d(spark: SparkSession, side: int, m: int, rho: int, row_major: bool = False) -> DataFrame:
    """The same of a 2D product of square matrices cut into strips of ``m`` cells."""
    width = m // side
    grid = Grid2D(ceil_div(side, width), ceil_div(side, width), rho, row_major)
    a = block_axis(spark, side, width, "i").withColumn("words", F.col("n_i") * side)
    b = block_axis(spark, side, width, "j").withColumn("words", F.col("n_j") * side)
    out = []
    for r in range(grid.rounds):
        out += [_sum(grid.copies_of_a(a, r), "2d", rho, r, "A"), _sum(grid.copies_of_b(b, r), "2d", rho, r, "B")]
    return _all(out)


def reached(a: MatrixFrame, b: MatrixFrame, side: int, rhos: tuple[int, ...]) -> tuple[list[Grid3D], DataFrame, DataFrame, DataFrame]:
    """The grid of each replication; the entries of A's and B's blocks (``i, h, words`` and ``h, j, words``); and ``rho, i, j, slot, since, n``: how many cells each slot of
    a sparse product comes to hold, by the first round that reaches them. Elementary products are no rows."""
    from roundmm.operators.chunks import CHUNK, reached_counts
    from roundmm.operators.dense3d import tasks_of
    from roundmm.operators.sparse3d import chunked, sparse_grid, weight

    grids = [sparse_grid(a, b, side, rho) for rho in rhos]
    shape, left, right = chunked(a, b, side, max(weight(a, b)))
    x = stored(left.groupBy(F.col("bi").alias("i"), F.col("bj").alias("h")).agg(F.sum("n").alias("words")), "words")
    y = stored(right.groupBy(F.col("bi").alias("h"), F.col("bj").alias("j")).agg(F.sum("n").alias("words")), "words")
    once = {g.rho: g for g in grids}
    with small_batches(a.df.sparkSession, 9 * min(max(shape.area, 1), CHUNK)):
        c = stored(reached_counts(left, right, list(once.values()), shape, tasks_of(left, grids[0].qi * grids[0].qj, None)), "reached")
    return grids, x, y, c


def ledger_sparse(a: MatrixFrame, b: MatrixFrame, side: int, rho: int | tuple[int, ...], method: str = "sparse") -> DataFrame:
    """Entries shuffled in each round of a sparse product with accumulated slots, a word an entry: of A and B from block counts, of C the cells that
    the round's slots hold by then; the last round folds what all slots hold. Several replications share one pass over the products."""
    rhos = (rho,) if isinstance(rho, int) else rho
    grids, x, y, c = reached(a, b, side, rhos)
    out = []
    for rho, grid in zip(rhos, grids, strict=True):
        mine = c.where(F.col("rho") == grid.rho)
        held = lambda r, slots: mine.where((F.col("since") < r) & (F.col("slot") < slots)).groupBy("i", "j", "slot").agg(F.sum("n").alias("words"))  # noqa: B023, E731
        for r in range(grid.product_rounds):
            out += [_sum(grid.copies_of_a(x, r), method, rho, r, "A"), _sum(grid.copies_of_b(y, r), method, rho, r, "B")]
            if r:
                out.append(_sum(held(r, grid.slots(r)), method, rho, r, "C"))
        out.append(_sum(held(grid.product_rounds, grid.rho), method, rho, grid.product_rounds, "C"))
    return _all(out)


def strips_of(m: MatrixFrame, axis: str, width: int, name: str) -> DataFrame:
    """``name, words``: the strips of a matrix that hold entries, and how many."""
    from roundmm.operators.sparse3d import _index

    return m.df.groupBy(_index(axis, width).alias(name)).agg(F.count(F.lit(1)).alias("words"))


def ledger_strips(a: MatrixFrame, b: MatrixFrame, m: int, rho: int, row_major: bool = False) -> DataFrame:
    """Strips and entries shuffled in each round of a 2D product of two given square matrices, cut into strips of ``m`` cells."""
    width = m // a.n_rows
    q = ceil_div(a.n_rows, width)
    grid = Grid2D(q, q, rho, row_major)
    x, y = strips_of(a, "row", width, "i"), strips_of(b, "col", width, "j")
    out = []
    for r in range(grid.rounds):
        out += [_sum(grid.copies_of_a(x, r), "2d", rho, r, "A"), _sum(grid.copies_of_b(y, r), "2d", rho, r, "B")]
    return _all(out)


def strip_copies(a: MatrixFrame, b: MatrixFrame, m: int, rho: int, row_major: bool) -> DataFrame:
    """``round, side, least, greatest``: copies that a strip of two given matrices makes in a round of their 2D product."""
    width = m // a.n_rows
    q = ceil_div(a.n_rows, width)
    grid = Grid2D(q, q, rho, row_major)
    x, y = strips_of(a, "row", width, "i"), strips_of(b, "col", width, "j")
    out = []
    for r in range(grid.rounds):
        for side, key, copies in (("A", "i", grid.copies_of_a(x, r)), ("B", "j", grid.copies_of_b(y, r))):
            each = copies.groupBy(key).agg(F.count(F.lit(1)).alias("n"))
            out.append(each.agg(F.min("n").alias("least"), F.max("n").alias("greatest")).select(F.lit(r).alias("round"), F.lit(side).alias("side"), "least", "greatest"))
    return _all(out)


def block_loads(a: MatrixFrame, b: MatrixFrame, side: int, rho: int, tasks: int, r: int = 0) -> DataFrame:
    """``task, keys`` for every task: products of the blocks of two given matrices in a round, under the polynomial placement."""
    from roundmm.operators.sparse3d import _index, sparse_grid

    grid = sparse_grid(a, b, side, rho)
    x = a.df.select(_index("row", side).alias("i"), _index("col", side).alias("h")).distinct()
    y = b.df.select(_index("row", side).alias("h"), _index("col", side).alias("j")).distinct()
    met = grid.copies_of_a(x, r).join(grid.copies_of_b(y, r), ["i", "h", "j", "slot"])
    return _loads(a.df.sparkSession, met.select(polynomial_task(F.col("i"), F.col("h"), F.col("j"), tasks).alias("task")), tasks)


def heaviest_ratio(a: MatrixFrame, b: MatrixFrame, block: int) -> DataFrame:
    """``side, block, words, ratio``: entries in the heaviest round of the monolithic product of two given matrices, over the ``n q`` words that two rounds need of full ones."""
    side, q = a.n_rows, ceil_div(a.n_rows, block)
    most = ledger_sparse(a, b, block, q).groupBy("round").agg(F.sum("words").alias("words")).agg(F.max("words").alias("words"))
    return most.select(F.lit(side).alias("side"), F.lit(block).alias("block"), "words", (F.col("words") / F.lit(float(side * side * q))).alias("ratio"))


def sparse_bound(a: MatrixFrame, b: MatrixFrame, side: int, rhos: tuple[int, ...]) -> DataFrame:
    """``rho, greatest, bound``: words of the heaviest round of a sparse product, and the bound that random inputs of their density have in expectation:
    three times the replication times the output's expected density times the cells."""
    p = a.df.agg((F.count(F.lit(1)) / F.lit(float(a.n_rows * a.n_cols))).alias("da")).crossJoin(F.broadcast(b.df.agg((F.count(F.lit(1)) / F.lit(float(b.n_rows * b.n_cols))).alias("db"))))  # one row each
    most = ledger_sparse(a, b, side, rhos).groupBy("rho", "round").agg(F.sum("words").alias("w")).groupBy("rho").agg(F.max("w").alias("greatest"))
    return most.crossJoin(F.broadcast(p)).select("rho", "greatest", (3 * F.col("rho") * F.col("da") * F.col("db") * F.lit(float(a.n_cols) * a.n_rows * b.n_cols)).alias("bound"))


def _all(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionAll(p)
    return out


def reducer_words_3d(spark: SparkSession, side: int, block: int, rho: int) -> DataFrame:
    """``round, reducers, least, greatest``: words that one reduce call holds, by round: blocks of A, B and, later, C."""
    q = ceil_div(side, block)
    grid = Grid3D(q, q, q, rho)
    length = lambda c: F.least(F.lit(block), F.lit(side) - F.col(c) * block)
    words = length("i") * length("h") + length("h") * length("j") + F.when(F.col("round") > 0, length("i") * length("j")).otherwise(0)
    return schedule_3d(spark, grid).withColumn("words", words.cast("long")).groupBy("round").agg(F.count(F.lit(1)).alias("reducers"), F.min("words").alias("least"), F.max("words").alias("greatest"))


def reducer_entries(a: MatrixFrame, b: MatrixFrame, side: int, rho: int) -> DataFrame:
    """``round, reducers, mean, greatest``: entries of A, of B and of the slot so far that meet in one reduce call of a sparse product, by round."""
    (grid,), x, y, c = reached(a, b, side, (rho,))
    x, y = x.withColumnRenamed("words", "x"), y.withColumnRenamed("words", "y")
    c = c.select(F.col("i").alias("ci"), F.col("j").alias("cj"), F.col("slot").alias("cs"), "since", "n")
    i, h, j = F.col("i"), F.col("h"), F.col("j")
    met = x.join(y, "h").select("i", "h", "j", "x", "y", grid.round_of(i, h, j).alias("round"), grid.slot_of(i, h, j).cast("int").alias("slot"))
    held = met.join(c, (F.col("ci") == i) & (F.col("cj") == j) & (F.col("cs") == F.col("slot")) & (F.col("since") < F.col("round")), "left")
    w = held.groupBy("round", "i", "h", "j", "x", "y").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("z")).select("round", (F.col("x") + F.col("y") + F.col("z")).alias("w"))
    return w.groupBy("round").agg(F.count(F.lit(1)).alias("reducers"), F.avg("w").alias("mean"), F.max("w").alias("greatest"))


def mapper_copies(spark: SparkSession, s: int, rho: int, row_major: bool) -> DataFrame:
    """``round, side, least, greatest``: copies that one strip makes in a round of the 2D product."""
    grid = Grid2D(s, s, rho, row_major)
    out = []
    for r in range(grid.rounds):
        p = grid.products(spark, r)
        for side, key in (("A", "i"), ("B", "j")):
            each = p.groupBy(key).agg(F.count(F.lit(1)).alias("n"))
            out.append(each.agg(F.min("n").alias("least"), F.max("n").alias("greatest")).select(F.lit(r).alias("round"), F.lit(side).alias("side"), "least", "greatest"))
    return _all(out)


def task_loads(spark: SparkSession, q: int, rho: int, tasks: int, placement: str, r: int = 0) -> DataFrame:
    """``task, keys`` for every task: keys of a round of the 3D product under a placement."""
    grid = Grid3D(q, q, q, rho)
    keys = schedule_3d(spark, grid).where(F.col("round") == r)
    i, h, j = F.col("i"), F.col("h"), F.col("j")
    task = even_task(rank_3d(i, j, F.col("slot"), q, rho), q * q * rho, tasks) if placement == "even" else polynomial_task(i, h, j, tasks)
    return _loads(spark, keys.select(task.alias("task")), tasks)


def task_loads_2d(spark: SparkSession, s: int, rho: int, tasks: int, r: int = 0) -> DataFrame:
    keys = Grid2D(s, s, rho).products(spark, r)
    return _loads(spark, keys.select(even_task(rank_2d(F.col("i"), F.col("j"), r, rho, s), s * rho, tasks).alias("task")), tasks)


def _loads(spark: SparkSession, keys: DataFrame, tasks: int) -> DataFrame:
    n = keys.groupBy("task").agg(F.count(F.lit(1)).alias("n"))
    every = spark.range(tasks).select(F.col("id").cast("int").alias("task"))
    return every.join(n, "task", "left").select("task", F.coalesce("n", F.lit(0)).alias("keys"))


def two_round_ratio(spark: SparkSession, side: int, block: int) -> DataFrame:
    """``side, block, words, ratio``: the heaviest round of the monolithic product as its ledger counts it, over the ``n q`` words that two rounds need at least."""
    q = ceil_div(side, block)
    most = ledger_3d(spark, (side, side, side), block, q).groupBy("round").agg(F.sum("words").alias("words")).agg(F.max("words").alias("words"))
    return most.select(F.lit(side).alias("side"), F.lit(block).alias("block"), "words", (F.col("words") / F.lit(float(side * side * q))).alias("ratio"))


def rounds_3d(side: int, block: int, rho: int) -> int:
    return ceil_div(ceil_div(side, block), rho) + 1


def rounds_2d(side: int, m: int, rho: int) -> int:
    return ceil_div(side * side // m, rho)


def rounds_sparse(side: int, m: int, rho: int, density: float) -> int:
    """With blocks of area ``m / density``."""
    return math.ceil(math.sqrt(density) * side / (rho * math.sqrt(m))) + 1


def max_relative_error(c: MatrixFrame, exact: MatrixFrame) -> DataFrame:
    """``cells, greatest``: the greatest difference of two matrices, relative to the exact one's cell (cells that one lacks count as zeros)."""
    met = c.df.join(exact.df.select("row", "col", F.col("val").alias("_e")), ["row", "col"], "full")
    off, size = F.abs(F.coalesce("val", F.lit(0.0)) - F.coalesce("_e", F.lit(0.0))), F.abs(F.coalesce("_e", F.lit(0.0)))
    return met.agg(F.count(F.lit(1)).alias("cells"), F.max(F.when(off > 0, off / F.greatest(size, F.lit(1e-300))).otherwise(0.0)).alias("greatest"))


def overhead_per_round(seconds: float, rounds: int, monolithic: float) -> float | None:
    """Relative slow-down for each round beyond the two of the monolithic product."""
    return None if rounds <= 2 else (seconds / monolithic - 1) / (rounds - 2)


def lost_work(round_seconds: list[float]) -> float:
    """Mean work lost at an interruption at a random time: half of the round that it hits."""
    total = sum(round_seconds)
    return sum(s * s for s in round_seconds) / (2 * total) if total else 0.0
