"""Blocks of sparse matrices in chunks of bounded size: runs of rows that travel as short byte strings and are multiplied where they meet."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from roundmm.functions.placement import even_task, rank_3d
from roundmm.functions.schedule import Grid3D
from roundmm.functions.semiring import OR_AND, Semiring
from roundmm.model import MatrixFrame
from roundmm.operators.coordinates import Cells, coo_product, merged

#: Cells of a chunk, where blocks fill up; entries and products that it expects, where they don't.
CHUNK = 1 << 20
#: Bytes of a Parquet row group of chunks: a reader holds one as a column.
GROUP = 16 << 20
UNSIGNED = (np.uint8, np.uint16, np.uint32)
COORDINATES = "bi int, bj int, strip long, n long, body binary"
PARTIAL = "i int, j int, slot int, strip long, n long, body binary"
ROWS = "row long, col long, val double"


def saved(df: DataFrame, path: str) -> DataFrame:
    """``df`` as Parquet in small row groups, read back."""
    df.write.option("compression", "zstd").option("parquet.block.size", str(GROUP)).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


@dataclass(frozen=True)
class Shape:
    """Blocks of ``side``, cut into strips of ``height`` rows."""

    side: int
    height: int

    @staticmethod
    def of(side: int, rows: int, q: int, work: int) -> Shape:
        """So that a strip of a block expects ``CHUNK`` of the ``work`` (entries or products) of ``rows`` rows in ``q`` blocks each, or has that many cells."""
        return Shape(side, max(1, min(side, max(CHUNK // side, CHUNK * rows * q // max(work, 1)))))

    @property
    def area(self) -> int:
        return self.height * self.side


def encoded(key: np.ndarray, val: np.ndarray) -> bytes:
    """Sorted cells ``row * side + col`` as differences, and their values, each in the fewest bytes that give them back exactly; one value, if all are the same."""
    step = np.diff(key, prepend=0)
    step = step.astype(next((t for t in UNSIGNED if step.max() <= np.iinfo(t).max), np.int64))
    if (val.view(np.int64) == val.view(np.int64)[0]).all():
        short = val[:1]
    else:
        short = val
        if val.min() >= 0 and not np.signbit(val).any():  # false with a NaN
            kind = next((t for t in UNSIGNED if val.max() <= np.iinfo(t).max), None)
            if kind is not None and (val == np.floor(val)).all():
                short = val.astype(kind)
    head = np.array([len(key), step.itemsize, short.itemsize, len(short)], np.int64)
    return head.tobytes() + step.tobytes() + short.tobytes()


def decoded(body: bytes) -> tuple[np.ndarray, np.ndarray]:
    n, wide, size, many = np.frombuffer(body, np.int64, 4)
    of = {1: np.uint8, 2: np.uint16, 4: np.uint32}
    key = np.cumsum(np.frombuffer(body, of.get(int(wide), np.int64), n, 32), dtype=np.int64)
    val = np.frombuffer(body, of.get(int(size), np.float64), many, 32 + int(n * wide)).astype(float)
    return key, np.full(n, val[0]) if many < n else val


def cells(body: bytes, shape: Shape, strip: int = 0) -> Cells:
    """Coordinates within the block, or, without ``strip``, within the strip."""
    key, val = decoded(body)
    row = key // shape.side
    return row + strip * shape.height, key - row * shape.side, val


def _batch(names: str, rows: list[tuple]) -> pa.RecordBatch:
    kinds = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary(), "double": pa.float64()}
    fields = [x.split() for x in names.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], kinds[t]) for k, (_, t) in enumerate(fields)], names=[n for n, _ in fields])


def _rows_of(r0: int, c0: int, body: bytes, shape: Shape) -> Iterator[pa.RecordBatch]:
    r, c, v = cells(body, shape)
    for lo in range(0, len(r), 1 << 16):
        x = slice(lo, lo + (1 << 16))
        yield pa.RecordBatch.from_arrays([pa.array(r[x] + r0), pa.array(c[x] + c0), pa.array(v[x])], names=["row", "col", "val"])


def packed_chunks(m: MatrixFrame, shape: Shape) -> DataFrame:
    """``bi, bj, strip, n, body``: the entries of each strip of a block; empty strips get no row."""
    side, height = shape.side, shape.height
    row, col = F.col("row").cast("long"), F.col("col").cast("long")
    inner = F.pmod(row, F.lit(side))
    place = [F.expr(f"cast(row div {side} as int)").alias("bi"), F.expr(f"cast(col div {side} as int)").alias("bj"), F.expr(f"pmod(row, {side}) div {height}").alias("strip")]
    return packed_cells(m.df.select(*place, (F.pmod(inner, F.lit(height)) * side + F.pmod(col, F.lit(side))).cast("long").alias("key"), F.col("val").cast("double").alias("v")), -(-m.n_cols // side), -(-side // height))


def packed_cells(rows: DataFrame, qj: int, strips: int) -> DataFrame:
    """``bi, bj, strip, n, body`` of rows ``bi, bj, strip, key, v``: packed from rows sorted by strip and streamed. Of ``qj`` blocks in a row of blocks and ``strips`` in a block, a strip
    has one number, by which rows sort without being compared."""
    qj, strips = max(qj, 1), max(strips, 1)
    run = ((F.col("bi").cast("long") * qj + F.col("bj")) * strips + F.col("strip")).alias("run")

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at: int | None = None
        held: list[tuple] = []

        def done() -> pa.RecordBatch:
            key, val = (np.concatenate(x) for x in zip(*held, strict=True))
            order = np.argsort(key, kind="stable")
            block = at // strips
            return _batch(COORDINATES, [(block // qj, block % qj, at % strips, len(key), encoded(key[order], val[order]))])

        for batch in batches:
            if not batch.num_rows:
                continue
            place, key, val = batch["run"].to_numpy(), batch["key"].to_numpy(), batch["v"].to_numpy(zero_copy_only=False)
            cut = [0, *(np.flatnonzero(place[1:] != place[:-1]) + 1), len(key)]
            for lo, hi in zip(cut, cut[1:], strict=False):
                here = int(place[lo])
                if at != here:
                    if held:
                        yield done()
                    at, held = here, []
                held.append((key[lo:hi], val[lo:hi]))
        if held:
            yield done()

    return rows.select(run, "key", "v").repartition("run").sortWithinPartitions("run").mapInArrow(pack, COORDINATES)


def sorted_by(df: DataFrame, task: Column, tasks: int, *keys: str) -> DataFrame:
    return df.withColumn("task", task).repartitionById(tasks, F.col("task")).sortWithinPartitions(*keys).drop("task")


def _side(df: DataFrame, kind: int, *more: Column) -> DataFrame:
    """B's chunks (0) come before those of A (1) and C (2), which come strip by strip."""
    return df.select(*more, F.lit(min(kind, 1)).alias("part"), "strip", F.lit(kind).alias("kind"), "body")


class Block:
    """B's chunks of a block, put together when a strip of A first asks for them."""

    def __init__(self, shape: Shape):
        self.shape, self.bodies, self.whole = shape, [], None

    def __bool__(self) -> bool:
        return bool(self.bodies)

    def add(self, strip: int, body: bytes) -> None:
        self.bodies.append((strip, body))

    def get(self) -> Cells:
        if self.whole is None:
            kind = np.int32 if self.shape.side < 1 << 31 else np.int64
            parts = []
            for strip, body in self.bodies:
                r, c, v = cells(body, self.shape, strip)
                parts.append((r.astype(kind), c.astype(kind), v))
            self.whole = tuple(np.concatenate(x) for x in zip(*parts, strict=True))
        return self.whole


def product_round(a: DataFrame, b: DataFrame, before: DataFrame | None, grid: Grid3D, shape: Shape, r: int, tasks: int, semiring: Semiring, last: bool, watch: dict[str, Observation] | None = None, cuts: int = 1) -> DataFrame:
    """Round ``r`` on chunks: ``i, j, slot, strip, n, body``, or, of the ``last`` one, ``row, col, val``. A task holds a block of B and a strip of A and C.
    With ``cuts`` the strips of a block of C are dealt to as many keys, and B's block goes to each."""
    side, height, qj, rho = shape.side, shape.height, grid.qj, grid.rho

    def seen(df: DataFrame, name: str) -> DataFrame:
        if watch is None:
            return df
        watch[name] = Observation(f"round {r} entries {name}")
        return df.observe(watch[name], F.coalesce(F.sum("n"), F.lit(0)).alias("words"))

    rank, cut = rank_3d(F.col("i"), F.col("j"), F.col("slot"), qj, rho) * cuts, F.pmod("strip", F.lit(cuts))
    z = (rank + cut).alias("z")
    left = grid.copies_of_a(a.select(F.col("bi").alias("i"), F.col("bj").alias("h"), "strip", "n", "body"), r)
    right = grid.copies_of_b(b.select(F.col("bi").alias("h"), F.col("bj").alias("j"), "strip", "n", "body"), r)
    right = seen(right, "B").withColumn("cut", F.explode(F.sequence(F.lit(0), F.lit(cuts - 1))))
    parts = [_side(seen(left, "A"), 1, z), _side(right, 0, (rank + F.col("cut")).alias("z"))]
    if before is not None:
        parts.append(_side(seen(before.where(F.col("slot") < grid.slots(r)), "C"), 2, z))
    met = parts[0]
    for more in parts[1:]:
        met = met.unionAll(more)
    placed = sorted_by(met, even_task(F.col("z"), grid.qi * qj * rho, tasks), tasks, "z", "part", "strip", "kind")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, block, strip, met = None, Block(shape), None, {}

        def done() -> Iterator[pa.RecordBatch]:
            if 1 in met and block:
                key, val = keyed(coo_product(cells(met[1], shape), block.get(), semiring, shape.area, cells(met[2], shape) if 2 in met else None), side)
                if not len(key):
                    return
                body = encoded(key, val)
            elif 2 in met:
                body = met[2]
            else:
                return
            node = at // cuts
            i, j, slot = node // (qj * rho), node // rho % qj, node % rho
            if last:
                yield from _rows_of(i * side + strip * height, j * side, body, shape)
            else:
                yield _batch(PARTIAL, [(i, j, slot, strip, int(np.frombuffer(body, np.int64, 1)[0]), body)])

        for batch in batches:
            for node, run, kind, body in zip(*(batch[c] for c in ("z", "strip", "kind", "body")), strict=True):
                node, run, kind = node.as_py(), run.as_py(), kind.as_py()
                if node != at or (kind and run != strip):
                    yield from done()
                    met, strip = {}, run if kind else None
                if node != at:
                    at, block = node, Block(shape)
                if kind:
                    met[kind] = body.as_py()
                else:
                    block.add(run, body.as_py())
        yield from done()

    out = placed.select("z", "strip", "kind", "body").mapInArrow(kernel, ROWS if last else PARTIAL)
    return out if last or before is None else out.unionAll(before.where(F.col("slot") >= grid.slots(r)))


#: Cells of a block of C that a task holds as arrays through all rounds of a run, and entries of A and B that it multiplies at once.
WHOLE, MET = 1 << 22, 1 << 19


class Sums:
    """A block of C while the products of several rounds are added to it."""

    def __init__(self, shape: Shape, semiring: Semiring):
        self.shape, self.semiring = shape, semiring
        self.val, self.hit = np.full(shape.side**2, semiring.zero), np.zeros(shape.side**2, bool)
        self.clear()

    def clear(self) -> None:
        self.left, self.right, self.met, self.blocks = [], [], 0, 0

    def next_group(self) -> None:
        if self.met > MET:
            self.multiply()
            self.clear()
        self.blocks += 1

    def add(self, kind: int, strip: int, body: bytes) -> None:
        """A chunk of B (0), of A (1), or of the block itself (2). Inner coordinates go on from block to block."""
        r, c, v = cells(body, self.shape, strip)
        if kind == 2:
            key = r * self.shape.side + c
            self.val[key], self.hit[key] = v, True
            return
        shift = (self.blocks - 1) * self.shape.side
        if kind:
            self.left.append((r, c + shift, v))
        else:
            self.right.append((r + shift, c, v))
        self.met += len(v)
        if kind and sum(len(x[0]) for x in self.left) > 2 * MET:  # more of A may come for the last block of B
            self.multiply()

    def multiply(self) -> None:
        if self.left and self.right:
            a, b = (tuple(np.concatenate(x) for x in zip(*y, strict=True)) for y in (self.left, self.right))
            key, v = keyed(coo_product(a, b, self.semiring, self.shape.side**2), self.shape.side)
            self.val[key] = self.semiring.merge(self.val[key], v)
            self.hit[key] = True
        self.left = []

    def strips(self) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        self.multiply()
        area = self.shape.area
        for lo in range(0, len(self.hit), area):
            key = np.flatnonzero(self.hit[lo : lo + area])
            if len(key):
                yield lo // area, key, self.val[lo : lo + area][key]


def product_run(a: DataFrame, b: DataFrame, before: DataFrame | None, grid: Grid3D, shape: Shape, rounds: range, tasks: int, semiring: Semiring, last: bool) -> DataFrame:
    """The same for a run of rounds by one shuffle: the blocks of a slot meet group by group, a task holds the block of C meanwhile. A copy goes only where the other matrix has a block."""
    side, height, qj, rho = shape.side, shape.height, grid.qj, grid.rho
    groups = rounds.start * rho, min(rounds.stop * rho, grid.qh)
    i, h, j, g = (F.col(c) for c in "ihjg")
    left = a.select(F.col("bi").alias("i"), F.col("bj").alias("h"), "strip", "body").join(b.select(F.col("bi").alias("h"), F.col("bj").alias("j")).distinct(), "h")
    right = b.select(F.col("bi").alias("h"), F.col("bj").alias("j"), "strip", "body").join(a.select(F.col("bi").alias("i"), F.col("bj").alias("h")).distinct(), "h")
    parts = []
    for df, kind in ((left, 1), (right, 0)):
        df = df.withColumn("g", grid.group(i, h, j).cast("int")).where((g >= groups[0]) & (g < groups[1]))
        parts.append(_side(df, kind, rank_3d(i, j, F.pmod(g, F.lit(rho)), qj, rho).alias("z"), "g"))
    if before is not None:
        parts.append(_side(before, 2, rank_3d(i, j, F.col("slot"), qj, rho).alias("z"), F.lit(-1).alias("g")))
    met = parts[0]
    for more in parts[1:]:
        met = met.unionAll(more)
    placed = sorted_by(met, even_task(F.col("z"), grid.qi * qj * rho, tasks), tasks, "z", "g", "part", "strip")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, group, held = None, None, None

        def done() -> Iterator[pa.RecordBatch]:
            i, j, slot = at // (qj * rho), at // rho % qj, at % rho
            for strip, key, val in held.strips():
                body = encoded(key, val)
                if last:
                    yield from _rows_of(i * side + strip * height, j * side, body, shape)
                else:
                    yield _batch(PARTIAL, [(i, j, slot, strip, len(key), body)])

        for batch in batches:
            for node, g, run, kind, body in zip(*(batch[c] for c in ("z", "g", "strip", "kind", "body")), strict=True):
                node, g, kind = node.as_py(), g.as_py(), kind.as_py()
                if node != at:
                    if held is not None:
                        yield from done()
                    at, group, held = node, None, Sums(shape, semiring)
                if kind < 2 and g != group:
                    group = g
                    held.next_group()
                held.add(kind, run.as_py(), body.as_py())
        if held is not None:
            yield from done()

    return placed.select("z", "g", "strip", "kind", "body").mapInArrow(kernel, ROWS if last else PARTIAL)


def keyed(x: Cells, side: int) -> tuple[np.ndarray, np.ndarray]:
    return x[0].astype(np.int64) * side + x[1], x[2]


def fold_chunks(partials: DataFrame, grid: Grid3D, shape: Shape, tasks: int, semiring: Semiring) -> DataFrame:
    """The slots of each strip added where they meet, one at a time: ``row, col, val``."""
    side, height = shape.side, shape.height

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, held = None, None

        def done() -> Iterator[pa.RecordBatch]:
            yield from _rows_of(at[0] * side + at[2] * height, at[1] * side, held, shape)

        for batch in batches:
            for i, j, strip, body in zip(*(batch[c] for c in ("i", "j", "strip", "body")), strict=True):
                here, body = (i.as_py(), j.as_py(), strip.as_py()), body.as_py()
                if here == at:
                    both = (np.concatenate(x) for x in zip(cells(held, shape), cells(body, shape), strict=True))
                    held = encoded(*keyed(merged(*both, semiring, shape.area), side))
                    continue
                if held is not None:
                    yield from done()
                at, held = here, body
        if held is not None:
            yield from done()

    strips = -(-side // height)
    run = ((F.col("i") * grid.qj + F.col("j")).cast("long") * strips + F.col("strip")).cast("long")
    placed = sorted_by(partials, even_task(run, grid.qi * grid.qj * strips, tasks), tasks, "i", "j", "strip", "slot")
    return placed.select("i", "j", "strip", "body").mapInArrow(fold, ROWS)


def reached_counts(a: DataFrame, b: DataFrame, grids: list[Grid3D], shape: Shape, tasks: int) -> DataFrame:
    """``rho, i, j, slot, since, n``: how many cells each slot of a product comes to hold, by the first round that reaches them, for grids of the same blocks and each of their
    replications. A task holds a block of B, a strip of A and the cells reached so far of a block of C."""
    one = grids[0]
    single = Grid3D(one.qi, one.qh, one.qj, 1)  # a group a round
    parts = []
    for g in range(one.qh):
        z = [(F.col("i") * one.qj + F.col("j")).cast("long").alias("z"), F.lit(g).alias("g")]
        parts.append(_side(single.copies_of_a(a.select(F.col("bi").alias("i"), F.col("bj").alias("h"), "strip", "body"), g), 1, *z))
        parts.append(_side(single.copies_of_b(b.select(F.col("bi").alias("h"), F.col("bj").alias("j"), "strip", "body"), g), 0, *z))
    met = parts[0]
    for more in parts[1:]:
        met = met.unionAll(more)
    placed = sorted_by(met, even_task(F.col("z"), one.qi * one.qj, tasks), tasks, "z", "g", "part", "strip")
    rhos = [g.rho for g in grids]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, group, block, held, counts = None, None, Block(shape), {}, {}

        def done() -> Iterator[pa.RecordBatch]:
            if counts:
                yield _batch(REACHED, [(rho, at // one.qj, at % one.qj, slot, since, n) for (rho, slot, since), n in counts.items()])

        for batch in batches:
            for node, g, run, kind, body in zip(*(batch[c] for c in ("z", "g", "strip", "kind", "body")), strict=True):
                node, g, run, body = node.as_py(), g.as_py(), run.as_py(), body.as_py()
                if node != at:
                    yield from done()
                    held, counts = {}, {}
                if (node, g) != (at, group):
                    at, group, block = node, g, Block(shape)
                if not kind.as_py():
                    block.add(run, body)
                    continue
                if not block:
                    continue
                x, y = ((r, c, np.ones(len(v))) for r, c, v in (cells(body, shape), block.get()))
                key, _ = keyed(coo_product(x, y, OR_AND, shape.area), shape.side)
                if not len(key):
                    continue
                for rho in rhos:
                    slot, since = g % rho, g // rho
                    place = rho, slot, run
                    new, now = united(held.get(place), key, shape.area)
                    if since + 1 < -(-one.qh // rho):
                        held[place] = now
                    counts[rho, slot, since] = counts.get((rho, slot, since), 0) + new
        yield from done()

    return placed.select("z", "g", "strip", "kind", "body").mapInArrow(kernel, REACHED)


def united(held: bytes | np.ndarray | None, key: np.ndarray, area: int) -> tuple[int, bytes | np.ndarray]:
    """How many of the sorted cells are new, and all of them: as bits, or, where a strip's area is large, as differences."""
    if area <= 16 * CHUNK:
        hit = np.zeros(area, bool)
        hit[key] = True
        old = 0
        if held is not None:
            before = np.unpackbits(held, count=area).view(bool)
            old = int(np.count_nonzero(hit & before))
            hit |= before
        return len(key) - old, np.packbits(hit)
    if held is not None:
        before = decoded(held)[0]
        key = np.union1d(before, key)
        return len(key) - len(before), encoded(key, np.ones(len(key)))
    return len(key), encoded(key, np.ones(len(key)))


REACHED = "rho int, i int, j int, slot int, since int, n long"
