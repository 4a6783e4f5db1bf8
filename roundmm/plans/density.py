"""Densities of inputs, and estimates of the output's density."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from roundmm.functions.semiring import PLUS_TIMES
from roundmm.model import MatrixFrame, transposed


@dataclass(frozen=True)
class DensityProfile:
    nnz_a: int
    nnz_b: int
    delta_a: float
    delta_b: float
    products: int | None
    delta_out: float
    method: str
    #: Elementary products that a cell of a product of random inputs expects. Of inputs that are dense enough it exceeds 1, a density doesn't.
    expected: float

    @property
    def greatest(self) -> float:
        return max(self.delta_a, self.delta_b, self.delta_out)


def products(a: MatrixFrame, b: MatrixFrame) -> DataFrame:
    """One row ``products``: elementary products, the sum over the inner index of column count times row count."""
    x = a.df.groupBy(F.col("col").alias("k")).agg(F.count(F.lit(1)).alias("x"))
    if transposed(a, b):
        return x.agg(F.coalesce(F.sum(F.col("x") * F.col("x")), F.lit(0)).alias("products"))
    y = b.df.groupBy(F.col("row").alias("k")).agg(F.count(F.lit(1)).alias("y"))
    return x.join(y, "k").agg(F.coalesce(F.sum(F.col("x") * F.col("y")), F.lit(0)).alias("products"))


def pattern(a: MatrixFrame, b: MatrixFrame) -> DataFrame:
    return a.df.select("row", F.col("col").alias("k")).join(b.df.select(F.col("row").alias("k"), "col"), "k").select("row", "col").distinct()


#: Bits of B's rows that a task holds at once, over all inner coordinates; entries of A that all panels get as lists, beyond which panels go by what B holds.
PANEL_BITS, LISTED = 1 << 28, 1 << 30


def exact_cells(a: MatrixFrame, b: MatrixFrame) -> DataFrame:
    """One row ``cells``: by the join of the entries, or, where cells are reached by many products, by uniting B's rows as bits.
    Where the inner axis is so long that A would go to very many panels of bits, they are counted where panels of B's entries meet strips of A."""
    from roundmm.operators.panels import multiply_panels

    width = PANEL_BITS // max(a.n_cols, 1) // 64 * 64
    if int(products(a, b).first()[0]) * 8 <= a.n_rows * b.n_cols:
        return joined_cells(a, b)
    in_a = a.df.count()
    if width and in_a * -(-b.n_cols // width) <= LISTED:
        return united_rows(a, b, width)
    a, b = (replace(m, df=m.df.withColumn("val", F.lit(1.0)), semiring=PLUS_TIMES) for m in (a, b))
    return multiply_panels(a, b, in_a, b.df.count(), count=True).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("cells"))


def runs(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, np.ndarray]]:
    """Each key of rows ``key, member`` sorted by key, with its members."""
    at, held = None, []
    for batch in batches:
        if not batch.num_rows:
            continue
        key, member = batch["key"].to_numpy(), batch["member"].to_numpy()
        cut = [0, *(np.flatnonzero(key[1:] != key[:-1]) + 1), len(key)]
        for lo, hi in zip(cut, cut[1:], strict=False):
            if key[lo] != at:
                if held:
                    yield at, np.concatenate(held)
                at, held = int(key[lo]), []
            held.append(member[lo:hi])
    if held:
        yield at, np.concatenate(held)


def united_rows(a: MatrixFrame, b: MatrixFrame, width: int) -> DataFrame:
    """The cells of ``A B`` by panels of ``width`` columns and runs of rows. B's rows are packed as bits, a panel each, A's as lists of inner coordinates; a task holds the bits
    of a panel and unites them along A's rows, which are streamed. Elementary products are no rows."""
    spark, n_inner, n_cols = a.df.sparkSession, b.n_rows, b.n_cols
    width = min(width, -(-n_cols // 64) * 64)
    panels = -(-n_cols // width)
    blocks = max(1, -(-2 * spark.sparkContext.defaultParallelism // panels))

    def bits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for k, cols in runs(batches):
            row = np.zeros(panels * width, bool)
            row[cols] = True
            packed = np.packbits(row).reshape(panels, width // 8)
            some = np.flatnonzero(packed.any(axis=1))
            yield pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), pa.array(np.full(len(some), k, np.int64)), pa.array([packed[x].tobytes() for x in some], pa.binary())], names=["panel", "id", "body"])

    def lists(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row, ks in runs(batches):
            yield pa.RecordBatch.from_arrays([pa.array([row], pa.int64()), pa.array([ks.astype("<i8").tobytes() if n_inner > 1 << 31 else ks.astype("<i4").tobytes()], pa.binary())], names=["id", "body"])

    def unite(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, table, cells = None, None, 0
        for batch in batches:
            for node, first, k, body in zip(*(batch[c].to_pylist() for c in ("node", "first", "id", "body")), strict=True):
                if node != at:
                    at, table = node, np.zeros((n_inner, width // 64), np.uint64)
                if first:
                    table[k] = np.frombuffer(body, np.uint64)
                else:
                    ks, row = np.frombuffer(body, "<i8" if n_inner > 1 << 31 else "<i4"), np.zeros(width // 64, np.uint64)
                    for lo in range(0, len(ks), 1024):
                        row |= np.bitwise_or.reduce(table[ks[lo : lo + 1024]], axis=0)
                    cells += int(np.bitwise_count(row).sum())
        yield pa.RecordBatch.from_arrays([pa.array([cells], pa.int64())], names=["cells"])

    def grouped(df: DataFrame, key: str, member: str) -> DataFrame:
        return df.select(F.col(key).alias("key"), F.col(member).alias("member")).repartition("key").sortWithinPartitions("key")

    right = grouped(b.df, "row", "col").mapInArrow(bits, "panel int, id long, body binary")
    right = right.select(F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("block"), "panel", F.lit(True).alias("first"), "id", "body")
    left = grouped(a.df, "row", "col").mapInArrow(lists, "id long, body binary")
    left = left.select(F.pmod("id", F.lit(blocks)).cast("int").alias("block"), F.explode(F.sequence(F.lit(0), F.lit(panels - 1))).alias("panel"), F.lit(False).alias("first"), "id", "body")
    both = right.unionByName(left).select((F.col("block") * panels + F.col("panel")).alias("node"), "first", "id", "body")
    placed = both.repartitionById(blocks * panels, F.col("node")).sortWithinPartitions("node", F.desc("first"))
    return placed.mapInArrow(unite, "cells long").agg(F.coalesce(F.sum("cells"), F.lit(0)).alias("cells"))


def joined_cells(a: MatrixFrame, b: MatrixFrame) -> DataFrame:
    return pattern(a, b).agg(F.count(F.lit(1)).alias("cells"))


def row_sample(a: MatrixFrame, b: MatrixFrame, percent: int = 10) -> DataFrame:
    """Cells of the product's rows that an arithmetic draw takes, scaled by the rows drawn."""
    drawn = a.where(F.expr(f"pmod(row * 48271 + 11, 100) < {percent}"))
    rows = a.df.sparkSession.range(a.n_rows).where(F.expr(f"pmod(id * 48271 + 11, 100) < {percent}")).agg(F.count(F.lit(1)).alias("rows"))
    return exact_cells(drawn, b).crossJoin(F.broadcast(rows)).select(  # one row each
        F.when(F.col("rows") > 0, F.col("cells") * F.lit(float(a.n_rows)) / F.col("rows")).otherwise(0.0).alias("cells")
    )


#: Registers of a sketch, a byte each; bits of a hash that its ranks are taken from; inner coordinates whose sketches a task holds.
REGISTERS, RANKED, HELD = 1 << 12, 52, 1 << 14


def sketch(hashes: np.ndarray) -> np.ndarray:
    """The greatest rank of the leading one bit, by register."""
    h = hashes.astype(np.int64).view(np.uint64)
    rank = RANKED + 1 - np.frexp((h >> np.uint64(12)).astype(float))[1]
    out = np.zeros(REGISTERS, np.uint8)
    np.maximum.at(out, (h & np.uint64(REGISTERS - 1)).astype(np.int64), rank.astype(np.uint8))
    return out


def sketch_estimate(registers: np.ndarray) -> float:
    """Distinct hashes behind a sketch, from how often each rank occurs; small and large counts need no other formula."""
    m = float(REGISTERS)
    n = np.bincount(registers, minlength=RANKED + 2).astype(float)
    if n[0] == m:
        return 0.0
    z, x, y = 0.0, 1 - n[-1] / m, 1.0
    if 0 < x < 1:
        z, last = 1 - x, -1.0
        while z != last:
            x, last, y = math.sqrt(x), z, y / 2
            z -= (1 - x) ** 2 * y
        z *= m / 3
    for k in range(RANKED, 0, -1):
        z = (z + n[k]) / 2
    x, y = n[0] / m, 1.0
    low, last = x, -1.0
    while low != last:
        x, last = x * x, low
        low, y = low + x * y, y * 2
    return m * m / (2 * math.log(2) * (z + m * low))


def sketched(a: MatrixFrame, b: MatrixFrame) -> DataFrame:
    """Column sets of B's rows as sketches, united along A's rows, counted. A task holds the sketches of a panel of inner coordinates and unites them along
    A's rows, which are streamed as lists; a sketch travels once a run of rows of A, not once an entry."""
    n_inner = b.n_rows
    panels = -(-n_inner // HELD)
    blocks = max(1, -(-2 * a.df.sparkSession.sparkContext.defaultParallelism // panels))

    def sketches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for k, hashes in runs(batches):
            yield pa.RecordBatch.from_arrays([pa.array([k], pa.int64()), pa.array([sketch(hashes).tobytes()], pa.binary())], names=["id", "body"])

    def lists(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for key, ks in runs(batches):
            yield pa.RecordBatch.from_arrays([pa.array([key], pa.int64()), pa.array([(ks % HELD).astype("<i4").tobytes()], pa.binary())], names=["id", "body"])

    def unite(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, table = None, None
        for batch in batches:
            ids, bodies = [], []
            for node, first, k, body in zip(*(batch[c].to_pylist() for c in ("node", "first", "id", "body")), strict=True):
                if node != at:
                    at, table = node, np.zeros((min(HELD, n_inner), REGISTERS), np.uint8)
                if first:
                    table[k % HELD] = np.frombuffer(body, np.uint8)
                    continue
                ks, row = np.frombuffer(body, "<i4"), np.zeros(REGISTERS, np.uint8)
                for lo in range(0, len(ks), 256):
                    np.maximum(row, table[ks[lo : lo + 256]].max(axis=0), out=row)
                ids.append(k // panels)
                bodies.append(row.tobytes())
                if len(ids) == 1024:
                    yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(bodies, pa.binary())], names=["row", "body"])
                    ids, bodies = [], []
            if ids:
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(bodies, pa.binary())], names=["row", "body"])

    def estimates(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, held, cells = None, None, 0
        for batch in batches:
            for row, body in zip(batch["row"].to_pylist(), batch["body"].to_pylist(), strict=True):
                x = np.frombuffer(body, np.uint8)
                if row == at:
                    held = np.maximum(held, x)
                    continue
                cells += round(sketch_estimate(held)) if held is not None else 0
                at, held = row, x
        cells += round(sketch_estimate(held)) if held is not None else 0
        yield pa.RecordBatch.from_arrays([pa.array([cells], pa.int64())], names=["cells"])

    def grouped(key: Column, member: Column, df: DataFrame) -> DataFrame:
        return df.select(key.alias("key"), member.alias("member")).repartition("key").sortWithinPartitions("key")

    right = grouped(F.col("row").cast("long"), F.xxhash64(F.col("col").cast("long")), b.df).mapInArrow(sketches, "id long, body binary")
    panel = F.expr(f"col div {HELD}")
    left = grouped(F.col("row").cast("long") * panels + panel, F.col("col").cast("long"), a.df).mapInArrow(lists, "id long, body binary")
    right = right.select(F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("block"), F.expr(f"id div {HELD}").alias("panel"), F.lit(True).alias("first"), "id", "body")
    left = left.select(F.pmod(F.expr(f"id div {panels}"), F.lit(blocks)).cast("int").alias("block"), F.pmod("id", F.lit(panels)).alias("panel"), F.lit(False).alias("first"), "id", "body")
    both = right.unionByName(left).select((F.col("block") * panels + F.col("panel")).cast("int").alias("node"), "first", "id", "body")
    united = both.repartitionById(blocks * panels, F.col("node")).sortWithinPartitions("node", F.desc("first")).mapInArrow(unite, "row long, body binary")
    if panels > 1:
        united = united.repartition("row").sortWithinPartitions("row")
    return united.mapInArrow(estimates, "cells long").agg(F.coalesce(F.sum("cells"), F.lit(0)).alias("cells"))


def exponential_minima(a: MatrixFrame, b: MatrixFrame, ranks: int = 32) -> DataFrame:
    """Each column gets ``ranks`` exponential draws; their minima over B's rows, then over A's, estimate set sizes."""
    draws = [(-F.log((F.pmod(F.xxhash64("col", F.lit(t)), F.lit(1 << 40)) + 1) / F.lit(float((1 << 40) + 1)))).alias(f"e{t}") for t in range(ranks)]
    least = [F.min(f"e{t}").alias(f"e{t}") for t in range(ranks)]
    rows = b.df.select(F.col("row").alias("k"), *draws).groupBy("k").agg(*least)
    out = a.df.select("row", F.col("col").alias("k")).join(rows, "k").groupBy("row").agg(*least)
    total = sum((F.col(f"e{t}") for t in range(1, ranks)), F.col("e0"))
    return out.agg(F.coalesce(F.sum(F.lit(ranks - 1) / total), F.lit(0.0)).alias("cells"))


METHODS = ("flops_upper", "er", "er_exact", "hll", "kmin", "row_sample", "exact")


def profile(a: MatrixFrame, b: MatrixFrame, method: str = "flops_upper") -> DensityProfile:
    """Counts of the inputs and an estimate of the output: single rows reach the driver."""
    if method not in METHODS:
        raise ValueError(f"method must be one of {METHODS}")
    nnz_a, nnz_b = a.df.count(), b.df.count()
    da, db = nnz_a / (a.n_rows * a.n_cols), nnz_b / (b.n_rows * b.n_cols)
    cells, work, expected = a.n_rows * b.n_cols, None, da * db * a.n_cols
    if method == "flops_upper":
        work = int(products(a, b).first()[0])
        out = min(1.0, work / cells)
    elif method == "er":
        out = min(1.0, expected)
    elif method == "er_exact":
        out = -math.expm1(a.n_cols * math.log1p(-da * db)) if da * db < 1 else 1.0
    else:
        of = {"hll": sketched, "kmin": exponential_minima, "row_sample": row_sample, "exact": exact_cells}[method]
        out = min(1.0, float(of(a, b).first()[0]) / cells)
    return DensityProfile(nnz_a, nnz_b, da, db, work, out, method, expected)
