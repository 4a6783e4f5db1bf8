"""Sparse products by the 3D schedule, on blocks whose area grows as the density falls."""

from __future__ import annotations

import math
import warnings
from dataclasses import replace

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from roundmm.functions.placement import even_task, rank_3d
from roundmm.functions.schedule import Grid3D, ceil_div
from roundmm.model import MatrixFrame, transposed
from roundmm.operators.chunks import CHUNK, WHOLE, Shape, fold_chunks, packed_chunks, product_round, product_run, saved
from roundmm.operators.coordinates import coo_product  # noqa: F401
from roundmm.operators.dense3d import tasks_of
from roundmm.operators.panels import Panels, multiply_panels
from roundmm.plans.rounds import RoundDriver, RoundStore, fingerprint, plan_hash
from roundmm.scratch import fresh_path, stored


def block_side(m: int, density: float, *sides: int) -> int:
    """Side of a square block of ``m / density`` cells, at most the longest side of the matrices."""
    return max(1, min(int(math.sqrt(m / max(density, 1e-300))), max(sides)))


def sparse_grid(a: MatrixFrame, b: MatrixFrame, side: int, rho: int | str) -> Grid3D:
    if a.n_cols != b.n_rows:
        raise ValueError(f"inner sides don't match: {a.n_cols} and {b.n_rows}")
    qh = ceil_div(a.n_cols, side)
    return Grid3D(ceil_div(a.n_rows, side), qh, ceil_div(b.n_cols, side), qh if rho == "max" else min(int(rho), qh))


def _index(c: str, side: int) -> Column:
    return F.floor(F.col(c) / side).cast("int")


def long_round(a: MatrixFrame, b: MatrixFrame, before: DataFrame | None, grid: Grid3D, side: int, r: int, tasks: int, watch: dict[str, Observation] | None = None) -> DataFrame:
    """Round ``r`` on single entries: ``i, j, slot, row, col, val``. Entries meet on (task, rank, inner index); products and
    partial sums are added where they meet, without another exchange. ``watch`` gets, by side, observations of the entries that enter the shuffle."""
    sr = a.semiring

    def seen(df: DataFrame, name: str) -> DataFrame:
        if watch is None:
            return df
        watch[name] = Observation(f"round {r} entries {name}")
        return df.observe(watch[name], F.count(F.lit(1)).alias("words"))

    left = grid.copies_of_a(a.df.select(_index("row", side).alias("i"), _index("col", side).alias("h"), "row", F.col("col").alias("k"), F.col("val").alias("x")), r)
    right = grid.copies_of_b(b.df.select(_index("row", side).alias("h"), _index("col", side).alias("j"), F.col("row").alias("k"), "col", F.col("val").alias("y")), r)

    def placed(df: DataFrame) -> DataFrame:
        z = rank_3d(F.col("i"), F.col("j"), F.col("slot"), grid.qj, grid.rho)
        return df.withColumn("z", z).withColumn("task", even_task(F.col("z"), grid.qi * grid.qj * grid.rho, tasks)).repartitionById(tasks, F.col("task"))

    met = placed(seen(left, "A")).join(placed(seen(right, "B")).select("task", "z", "k", "col", "y").hint("merge"), ["task", "z", "k"])
    new = met.groupBy("task", "z", "row", "col").agg(sr.plus(sr.times(F.col("x"), F.col("y"))).alias("val"))
    # the rank gives back row, column and slot
    new = new.select("*", F.expr(f"cast(z div {grid.qj * grid.rho} as int)").alias("i"), F.expr(f"cast((z div {grid.rho}) % {grid.qj} as int)").alias("j"), F.expr(f"cast(z % {grid.rho} as int)").alias("slot"))
    if before is None:
        return new.select("i", "j", "slot", "row", "col", "val")
    live = placed(seen(before.where(F.col("slot") < grid.slots(r)), "C")).select("task", "z", "row", "col", *[F.col(c).alias(f"_{c}") for c in ("i", "j", "slot", "val")])
    both = new.join(live.hint("merge"), ["task", "z", "row", "col"], "full")
    val = F.when(F.col("val").isNull(), F.col("_val")).when(F.col("_val").isNull(), F.col("val")).otherwise(sr.combine(F.col("val"), F.col("_val")))
    out = both.select(*[F.coalesce(c, f"_{c}").alias(c) for c in ("i", "j", "slot")], "row", "col", val.alias("val"))
    return out.unionAll(before.where(F.col("slot") >= grid.slots(r)).select("i", "j", "slot", "row", "col", "val"))


#: Elementary products an entry of the inputs, beyond which they are no rows.
MANY = 8


#: Rounds that always have a shuffle each; of more rounds, runs of them that copy at most ``LIGHT`` entries share one, if nobody looks at single rounds.
FEW, LIGHT = 8, 1 << 28


def run_length(grid: Grid3D, a: MatrixFrame, b: MatrixFrame, side: int, packs: tuple[DataFrame, DataFrame] | None = None) -> int:
    """How many rounds share a shuffle. ``packs``, the chunks of both, tell which blocks meet, and so how many copies go in truth."""
    if grid.product_rounds <= FEW or side * side > WHOLE:
        return 1
    if packs is None:
        copies = (a.df.count() * grid.qj + b.df.count() * grid.qi) * grid.rho // grid.qh
    else:
        copies = ceil_div(copied(*packs), grid.product_rounds)
    return max(1, min(grid.product_rounds, LIGHT // max(copies, 1)))


def copied(left: DataFrame, right: DataFrame) -> int:
    """Entries that all rounds copy, if a chunk goes only where the other matrix has a block."""
    x = left.groupBy(F.col("bj").alias("h")).agg(F.sum("n").alias("x"), F.countDistinct("bi").alias("p"))
    y = right.groupBy(F.col("bi").alias("h")).agg(F.sum("n").alias("y"), F.countDistinct("bj").alias("q"))
    return int(x.join(y, "h").agg(F.coalesce(F.sum(F.col("x") * F.col("q") + F.col("y") * F.col("p")), F.lit(0))).first()[0])


def stored_pair(a: MatrixFrame, b: MatrixFrame) -> tuple[MatrixFrame, MatrixFrame]:
    """Both matrices as files; once, if they are one, or one is the other transposed."""
    same, flipped = a.df is b.df, transposed(a, b)
    a = replace(a, df=stored(a.df, "entries"))
    return a, replace(b, df=a.df if same else a.T.df if flipped else stored(b.df, "entries"))


def weight(a: MatrixFrame, b: MatrixFrame) -> tuple[int, int]:
    """Elementary products, and entries of both matrices: one number each."""
    work, in_a, in_b = weights(a, b)
    return work, in_a + in_b


def weights(a: MatrixFrame, b: MatrixFrame) -> tuple[int, int, int]:
    """Elementary products, and entries of each matrix."""
    from roundmm.plans.density import products

    in_a = a.df.count()
    return int(products(a, b).first()[0]), in_a, in_a if a.df is b.df else b.df.count()


#: Cells of C, beyond which they are neither stored nor moved, if nobody looks at single rounds and panels copy no more entries of A than there are elementary products.
WIDE = 1 << 26


def cells_of(a: MatrixFrame, b: MatrixFrame, work: int) -> float:
    """Cells that so many products of random inputs reach."""
    area = a.n_rows * b.n_cols
    return -area * math.expm1(-work / area) if area else 0.0


def chunked(a: MatrixFrame, b: MatrixFrame, side: int, work: int) -> tuple[Shape, DataFrame, DataFrame]:
    """The shape of chunks for a product of blocks of ``side``, and both matrices in chunks, stored; once, if they are one."""
    spark, shape = a.df.sparkSession, Shape.of(side, min(a.n_rows, b.n_rows), ceil_div(b.n_cols, side), work)
    left = saved(packed_chunks(a, shape), fresh_path(spark, "packed"))
    return shape, left, left if a.df is b.df else saved(packed_chunks(b, shape), fresh_path(spark, "packed"))


def multiply_3d_sparse(
    a: MatrixFrame,
    b: MatrixFrame,
    m: int,
    rho: int | str = "max",
    density: str | float = "er",
    side: int | None = None,
    encoding: str = "packed",
    carry: str = "accumulate",
    permuted: bool = False,
    store: RoundStore | None = None,
    tasks: int | None = None,
    resume: bool = True,
    stop_after: int | None = None,
    watch: dict[int, dict[str, Observation]] | None = None,
) -> MatrixFrame:
    """``A B`` of sparse matrices; the result has the cells that at least one elementary product reaches.

    ``density`` sets the block area ``m / density``: a number, an estimator of :mod:`roundmm.plans.density` (the greatest of input
    densities and the estimate counts), ``er`` for random inputs (the estimate counts), or ``input_only`` where nothing is known of the
    output; that promises no bound on a reducer, and says so. ``side`` overrides the block side. ``encoding`` is ``packed`` (entries
    of a block in chunks of bounded size, NumPy kernel) or ``long`` (entries as rows, all in Catalyst; where a product has more than ``MANY`` elementary products
    an entry, which would be rows there, or large inputs fewer blocks and slots than tasks run at once, it goes by chunks too). More than ``FEW`` rounds of small blocks
    share shuffles in runs, as far as they copy few entries and no ``store``, ``stop_after`` or ``watch`` asks for single rounds. Where C is expected to have more than ``WIDE``
    cells, no more copies of A's entries go to panels of B than there are elementary products, and nobody asks for single rounds, all rounds and slots share one shuffle and C is handed on
    panel by panel, unstored, whatever ``side``, ``rho`` and ``carry`` are.

    ``carry``: ``accumulate`` reads, adds to and rewrites the slots each round; ``append`` writes fresh partial sums, which meet in the fold only, so no
    entry of C moves twice. With one slot the fold of ``accumulate`` is an identity and left out. ``permuted`` renames rows,
    inner axis and columns at random for balance, and names the result back. ``watch`` gets, by round, observations of the entries shuffled.
    """
    from roundmm.operators.elementwise import Permutation, permute
    from roundmm.plans.density import profile

    if encoding not in ("long", "packed"):
        raise ValueError("encoding must be 'long' or 'packed'")
    if carry not in ("accumulate", "append"):
        raise ValueError("carry must be 'accumulate' or 'append'")
    names = None
    if permuted:
        rows, inner, cols = (Permutation(n, "feistel", 42 + k) for k, n in enumerate((a.n_rows, a.n_cols, b.n_cols)))
        a, b, names = permute(a, rows, inner), permute(b, inner, cols), (rows, cols)
    a, b = stored_pair(a, b)
    known = None
    if side is None:
        if isinstance(density, str):
            p = profile(a, b, "er" if density == "input_only" else density)
            least = max(p.delta_a, p.delta_b)
            if density == "input_only":
                warnings.warn("block side from the input density alone: a reducer may exceed its bound", stacklevel=2)
                density = least
            else:
                known = p.delta_out * a.n_rows * b.n_cols if density == "exact" else None
                density = p.delta_out if density == "er" else max(least, p.delta_out)
        side = block_side(m, density, a.n_rows, a.n_cols, b.n_cols)
    grid, spark, sr = sparse_grid(a, b, side, rho), a.df.sparkSession, a.semiring
    tasks = tasks_of(a.df, grid.qi * grid.qj * grid.rho, tasks)
    inputs = [fingerprint(x.df) for x in (a, b)] if store is not None and store.mode == "parquet" else []
    work, in_a, in_b = weights(a, b)
    entries = in_a + in_b
    cells = cells_of(a, b, work) if known is None else known
    if store is None and stop_after is None and watch is None and cells > WIDE and Panels.of(a, b, in_a, in_b).copies_of_a(b, in_a) <= work:
        return MatrixFrame(multiply_panels(a, b, in_a, in_b, names), a.n_rows, b.n_cols, sr)
    keys, at_once = grid.qi * grid.qj * grid.rho, spark.sparkContext.defaultParallelism
    if work > MANY * entries or (entries > CHUNK and keys < at_once):
        encoding = "packed"
    shape, *packs = chunked(a, b, side, max(work, entries)) if encoding == "packed" else (Shape(side, side),)
    cuts, run = 1, 1
    if encoding == "packed" and watch is None:
        cuts = max(1, min(ceil_div(side, shape.height), 2 * at_once // keys))
        run = run_length(grid, a, b, side, tuple(packs)) if store is None and stop_after is None else 1
    passes = ceil_div(grid.product_rounds, run)
    digest = plan_hash(grid=grid, side=side, height=shape.height, encoding=encoding, carry=carry, semiring=sr.name, a=(a.n_rows, a.n_cols), b=b.n_cols, inputs=inputs)
    identity = grid.rho == 1 and carry == "accumulate"
    outs: list[DataFrame] = []

    def one_round(r: int, before: DataFrame | None) -> DataFrame:
        if encoding == "long":
            return long_round(a, b, before, grid, side, r, tasks, None if watch is None else watch.setdefault(r, {}))
        if run > 1:
            return product_run(*packs, before, grid, shape, range(r * run, (r + 1) * run), tasks, sr, identity and r == passes - 1)
        return product_round(*packs, before, grid, shape, r, min(keys * cuts, tasks * cuts), sr, identity and r == passes - 1, None if watch is None else watch.setdefault(r, {}), cuts)

    def step(r: int, before: DataFrame | None) -> DataFrame:
        if before is not None and len(outs) < r:
            outs.append(before)
        if r < passes:
            return one_round(r, None if carry == "append" else before)
        partials = before
        if carry == "append":
            partials = outs[0]
            for more in outs[1:]:
                partials = partials.unionAll(more)
        if encoding == "packed":
            return fold_chunks(partials, grid, shape, tasks_of(a.df, grid.qi * grid.qj * -(-side // shape.height), None), sr)
        block = even_task((F.col("i") * grid.qj + F.col("j")).cast("long"), grid.qi * grid.qj, tasks)
        placed = partials.select(block.alias("task"), "row", "col", "val").repartitionById(tasks, F.col("task"))
        return placed.groupBy("task", "row", "col").agg(sr.plus("val").alias("val")).select("row", "col", "val")

    last_store = store or RoundStore(spark)
    if carry == "append" and resume:
        outs += [spark.read.parquet(p) for _, p in sorted(last_store.committed(digest).items())][:passes][:-1]
    # a chunk has at most nine bytes a cell
    driver = RoundDriver(last_store, "sparse", digest, 9 * min(max(shape.area, 1), CHUNK) if encoding == "packed" else 1)
    rounds = passes if identity else passes + 1
    save = (lambda r, df, path: saved(df, path)) if encoding == "packed" else None
    last = driver.run(rounds, lambda r: grid.slots(r) if r < passes and run == 1 else grid.rho, step, resume, stop_after, save)[-1]
    if identity and encoding == "long":
        last = last.select("row", "col", "val")
    c = MatrixFrame(last, a.n_rows, b.n_cols, sr)
    return c if names is None else permute(c, *names, back=True)
