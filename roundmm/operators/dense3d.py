"""Dense products by the 3D schedule: ``rho`` groups of block products a round, then one round that adds the slots."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace

import pyarrow as pa
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from roundmm.functions.placement import even_task, polynomial_task, rank_3d
from roundmm.functions.schedule import Grid3D
from roundmm.functions.semiring import Semiring
from roundmm.model import BlockFrame, pack, unpack
from roundmm.plans.rounds import RoundDriver, RoundStore, fingerprint, plan_hash

PARTIAL = "i int, j int, slot int, nr int, nc int, cells binary"
CARRIES = ("accumulate", "append", "stationary")


def grid_of(a: BlockFrame, b: BlockFrame, rho: int | str) -> Grid3D:
    if a.n_cols != b.n_rows or a.block_cols != b.block_rows:
        raise ValueError(f"inner sides don't match: {a.n_cols}/{a.block_cols} and {b.n_rows}/{b.block_rows}")
    return Grid3D(a.q_rows, a.q_cols, b.q_cols, a.q_cols if rho == "max" else int(rho))


def tasks_of(df: DataFrame, keys: int, tasks: int | None) -> int:
    return tasks or max(1, min(keys, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))))


def fused(rows: DataFrame, semiring: Semiring) -> DataFrame:
    """``i, j, slot, nr, nk, nc, ca, cb, cc``: the partial sum ``cc`` (or none) plus the product of ``ca`` and ``cb`` (or none)."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for k in range(batch.num_rows):
                nr, nk, nc, ca, cb, cc = (batch[c][k].as_py() for c in ("nr", "nk", "nc", "ca", "cb", "cc"))
                if ca is None:
                    out.append(cc)
                    continue
                c = semiring.product(unpack(ca, nr, nk), unpack(cb, nk, nc))
                out.append(pack(c if cc is None else semiring.merge(c, unpack(cc, nr, nc))))
            yield pa.RecordBatch.from_arrays([batch[c] for c in ("i", "j", "slot", "nr", "nc")] + [pa.array(out, pa.binary())], names=["i", "j", "slot", "nr", "nc", "cells"])

    return rows.select("i", "j", "slot", "nr", "nk", "nc", "ca", "cb", "cc").mapInArrow(kernel, PARTIAL)


def keyed(df: DataFrame, grid: Grid3D, tasks: int, placement: str) -> DataFrame:
    """Add the rank ``z`` and the ``task`` of a round's rows."""
    z = rank_3d(F.col("i"), F.col("j"), F.col("slot"), grid.qj, grid.rho)
    if placement == "even":
        task = even_task(z, grid.qi * grid.qj * grid.rho, tasks)
    elif placement == "polynomial":
        task = polynomial_task(F.col("i"), F.col("h"), F.col("j"), tasks)
    else:
        raise ValueError("placement must be 'even' or 'polynomial'")
    return df.withColumn("z", z).withColumn("task", task)


def product_round(a: DataFrame, b: DataFrame, before: DataFrame | None, grid: Grid3D, r: int, tasks: int, semiring: Semiring, placement: str, by_id: bool = True, watch: dict[str, Observation] | None = None) -> DataFrame:
    """Round ``r``: copies of A and B meet by rank, each pair is one reducer; partial sums of its slot join it there.

    ``z`` names row, column and slot, and so within a round the inner index too. Both sides are placed by the same
    task ids, so joins on (task, z) need no other exchange. ``watch`` gets, by side, observations of the pairs and words that
    enter the shuffle, filled in by the round's own run.
    """

    def seen(df: DataFrame, side: str, words) -> DataFrame:
        if watch is None:
            return df
        watch[side] = Observation(f"round {r} side {side}")
        return df.observe(watch[side], F.count(F.lit(1)).alias("pairs"), F.coalesce(F.sum(words), F.lit(0)).cast("long").alias("words"))

    left = grid.copies_of_a(a.select(F.col("bi").alias("i"), F.col("bj").alias("h"), "nr", F.col("nc").alias("nk"), F.col("cells").alias("ca")), r)
    right = grid.copies_of_b(b.select(F.col("bi").alias("h"), F.col("bj").alias("j"), F.col("nc").alias("nc"), F.col("cells").alias("cb")), r)
    place = (lambda df: df.repartitionById(tasks, F.col("task"))) if by_id else (lambda df: df.repartition(tasks, "z"))
    keys = ["task", "z"] if by_id else ["z"]
    left = place(seen(keyed(left, grid, tasks, placement), "A", F.col("nr").cast("long") * F.col("nk")))
    right = place(seen(keyed(right, grid, tasks, placement).select(*keys, "nc", "cb"), "B", F.octet_length("cb") / 8))
    # merge: payloads spill, and neither side may be broadcast, however small it looks
    both = left.join(right.hint("merge"), keys).select(*keys, "i", "j", "slot", "nr", "nk", "nc", "ca", "cb")
    if before is None:
        return fused(both.withColumn("cc", F.lit(None).cast("binary")), semiring)
    live = before.where(F.col("slot") < grid.slots(r))
    h = F.pmod(F.col("i") + F.col("j") + F.col("slot") + r * grid.rho, F.lit(grid.qh)).cast("int")
    held = keyed(live.withColumn("h", h), grid, tasks, placement).select(*keys, *[F.col(c).alias(f"_{c}") for c in ("i", "j", "slot", "nr", "nc")], F.col("cells").alias("cc"))
    held = place(seen(held, "C", F.octet_length("cc") / 8)) if by_id else held
    met = both.join(held.hint("merge"), keys, "full").select(*[F.coalesce(c, f"_{c}").alias(c) for c in ("i", "j", "slot", "nr", "nc")], "nk", "ca", "cb", "cc")
    return fused(met, semiring).unionAll(before.where(F.col("slot") >= grid.slots(r)).select("i", "j", "slot", "nr", "nc", "cells"))


def fold_slots(partials: DataFrame, semiring: Semiring, q_cols: int, tasks: int) -> DataFrame:
    """Add the partial sums of each block, streamed in the order of blocks: one accumulator at a time."""

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, held = None, None

        def done() -> pa.RecordBatch:
            kinds = (pa.int32(), pa.int32(), pa.int32(), pa.int32())
            return pa.RecordBatch.from_arrays([pa.array([x], k) for x, k in zip(at, kinds, strict=True)] + [pa.array([pack(held)], pa.binary())], names=["bi", "bj", "nr", "nc", "cells"])

        for batch in batches:
            for k in range(batch.num_rows):
                i, j, nr, nc = (batch[c][k].as_py() for c in ("i", "j", "nr", "nc"))
                cells = unpack(batch["cells"][k].as_py(), nr, nc)
                if at is not None and at[:2] == (i, j):
                    held = semiring.merge(held, cells)
                else:
                    if at is not None:
                        yield done()
                    at, held = (i, j, nr, nc), cells
        if at is not None:
            yield done()

    placed = partials.repartitionById(tasks, F.pmod(F.col("i") * q_cols + F.col("j"), F.lit(tasks)).cast("int"))
    return placed.sortWithinPartitions("i", "j", "slot").mapInArrow(fold, "bi int, bj int, nr int, nc int, cells binary")


def multiply_3d(
    a: BlockFrame,
    b: BlockFrame,
    rho: int | str = "max",
    carry: str = "accumulate",
    store: RoundStore | None = None,
    tasks: int | None = None,
    placement: str = "even",
    resume: bool = True,
    stop_after: int | None = None,
    elide_identity: bool = False,
    watch: dict[int, dict[str, Observation]] | None = None,
) -> BlockFrame:
    """``A B`` in ``ceil(q / rho) + 1`` rounds; ``rho="max"`` is the monolithic product in two.

    ``carry``: ``accumulate`` reads, adds to and rewrites the slots each round; ``append`` writes fresh partial products and
    folds them all at the end; ``stationary`` keeps the slots in files bucketed by rank, so only A and B move (it needs a ``parquet`` store). All three
    go on from the last committed round; a store that holds rounds of other inputs raises, by fingerprints of A and B, taken where a ``store`` is given.
    ``elide_identity`` leaves out the last round where there is one slot, whose sum is itself.
    ``watch`` gets, by product round, the observations of :func:`product_round`.
    """
    if carry not in CARRIES:
        raise ValueError(f"carry must be one of {CARRIES}")
    grid, spark, sr = grid_of(a, b, rho), a.df.sparkSession, a.semiring
    tasks = tasks_of(a.df, grid.qi * grid.qj * grid.rho, tasks)
    inputs = [fingerprint(x.df) for x in (a, b)] if store is not None and store.mode == "parquet" else []
    store = store or RoundStore(spark)
    if carry == "stationary" and store.mode != "parquet":
        raise ValueError("carry='stationary' needs a parquet store")
    digest = plan_hash(grid=grid, carry=carry, semiring=sr.name, placement=placement, tasks=tasks if carry == "stationary" else 0, a=(a.n_rows, a.n_cols, a.block_rows, a.block_cols), b=(b.n_rows, b.n_cols, b.block_cols), inputs=inputs)
    block = 8 * max(a.block_rows * a.block_cols, b.block_rows * b.block_cols, a.block_rows * b.block_cols)
    driver = RoundDriver(store, "3d", digest, block)
    tables: list[str] = []

    def step(r: int, before: DataFrame | None) -> DataFrame:
        if r < grid.product_rounds:
            if carry == "append":
                fresh = product_round(a.df, b.df, None, grid, r, tasks, sr, placement)
                return fresh.withColumn("slot", F.col("slot") + r * grid.rho)
            if carry == "stationary":
                held = slots_table(r - 1, f"{store.path}/round={r - 1}", before) if r else None
                return product_round(a.df, b.df, held, grid, r, tasks, sr, placement, by_id=False)
            return product_round(a.df, b.df, before, grid, r, tasks, sr, placement, watch=None if watch is None else watch.setdefault(r, {}))
        partials = before
        if carry == "append":
            partials = outs[0]
            for more in outs[1:]:
                partials = partials.unionAll(more)
        return fold_slots(partials, sr, grid.qj, tasks)

    def slots_name(r: int) -> str:
        return f"roundmm_slots_{plan_hash(path=store.path)}_{r}"

    def slots_table(r: int, where: str, rows: DataFrame) -> DataFrame:
        """The committed slots of a round as a bucketed table over its files: the join with them needs no exchange of them."""
        tables.append(slots_name(r))
        spark.sql(f"DROP TABLE IF EXISTS {tables[-1]}")
        columns = ", ".join(f"{c.name} {c.dataType.simpleString()}" for c in rows.schema)
        spark.sql(f"CREATE TABLE {tables[-1]} ({columns}) USING parquet CLUSTERED BY (z) INTO {tasks} BUCKETS LOCATION '{where}'")
        return spark.table(tables[-1])

    def save_slots(r: int, rows: DataFrame, where: str) -> None:
        if r >= grid.product_rounds:
            rows.write.parquet(where)
            return
        spark.sql(f"DROP TABLE IF EXISTS {slots_name(r)}")
        rows.write.bucketBy(tasks, "z").option("path", where).saveAsTable(slots_name(r))
        tables.append(slots_name(r))

    def ranked(rows: DataFrame) -> DataFrame:
        return rows.withColumn("z", rank_3d(F.col("i"), F.col("j"), F.col("slot"), grid.qj, grid.rho))

    outs: list[DataFrame] = []

    def step_kept(r: int, before: DataFrame | None) -> DataFrame:
        if before is not None and len(outs) < r:
            outs.append(before)
        out = step(r, before)
        return ranked(out) if carry == "stationary" and r < grid.product_rounds else out

    if carry == "append" and resume:
        outs = [spark.read.parquet(p) for _, p in sorted(store.committed(digest).items())][: grid.product_rounds]
        outs = outs[:-1] if outs else outs
    rounds = grid.product_rounds if elide_identity and grid.rho == 1 and carry != "append" else grid.rounds
    last = driver.run(rounds, lambda r: grid.slots(r) if r < grid.product_rounds else grid.rho, step_kept, resume, stop_after, save_slots if carry == "stationary" else None)[-1]
    for name in tables:
        spark.sql(f"DROP TABLE IF EXISTS {name}")  # its files stay
    if "slot" in last.columns:
        last = last.select(F.col("i").alias("bi"), F.col("j").alias("bj"), "nr", "nc", "cells")
    return replace(b, df=last, n_rows=a.n_rows, block_rows=a.block_rows, semiring=sr)
