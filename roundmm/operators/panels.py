"""Products with more cells than can be kept: by one shuffle, panel by panel and strip by strip, each cell handed on when it is whole."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from typing import TYPE_CHECKING

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from roundmm.functions.placement import even_task
from roundmm.functions.schedule import ceil_div
from roundmm.functions.semiring import Semiring
from roundmm.model import MatrixFrame
from roundmm.operators.chunks import CHUNK, ROWS, decoded, packed_cells, saved, sorted_by
from roundmm.scratch import fresh_path

if TYPE_CHECKING:
    from roundmm.operators.elementwise import Permutation

#: Entries of B that a task expects to hold, cells of C that it holds, cells of a dense factor, and elementary products made at once.
HELD, AREA, DENSE, AT_ONCE = 1 << 22, 1 << 20, 1 << 23, 1 << 18
#: Columns of a panel, where B is thin enough for them; elementary products to multiplications of a dense product that cost as much.
LEAST, WORTH = 8192, 256


@dataclass(frozen=True)
class Panels:
    """B in panels of ``width`` columns, in chunks of ``piece`` of ``inner`` coordinates; A in strips of ``height`` rows."""

    inner: int
    height: int
    width: int
    piece: int

    @staticmethod
    def of(a: MatrixFrame, b: MatrixFrame, in_a: int, in_b: int) -> Panels:
        """For matrices of so many entries."""
        inner = max(a.n_cols, 1)
        width = max(1, min(b.n_cols, HELD * b.n_cols // max(in_b, 1), max(LEAST, DENSE // inner)))
        width = ceil_div(b.n_cols, ceil_div(b.n_cols, width))
        height = max(1, min(a.n_rows, AREA // width, CHUNK * a.n_rows // max(in_a, 1)))
        return Panels(inner, height, width, max(1, min(inner, CHUNK * inner * b.n_cols // max(in_b * width, 1))))

    def copies_of_a(self, b: MatrixFrame, in_a: int) -> int:
        """Entries of A that the shuffle gets: each strip goes to every panel."""
        return in_a * ceil_div(b.n_cols, self.width)


class Panel:
    """A panel of B, by inner coordinates, and strips of A multiplied by it."""

    def __init__(self, shape: Panels, semiring: Semiring):
        self.shape, self.semiring, self.parts, self.ready, self.full = shape, semiring, [], False, None

    def add(self, piece: int, body: bytes) -> None:
        """Chunks come in the order of inner coordinates."""
        key, val = decoded(body)
        k = key // self.shape.width
        self.parts.append(((k + piece * self.shape.piece).astype(np.int32 if self.shape.inner < 1 << 31 else np.int64), (key - k * self.shape.width).astype(np.int32), val))

    def _join(self) -> None:
        self.k, self.col, self.val = (np.concatenate(x) for x in zip(*self.parts, strict=True))
        self.parts, self.ready = [], True
        self.ones, self.finite = bool((self.val == 1).all()), bool(np.isfinite(self.val).all())
        self.first = None
        if self.shape.inner <= 4 * len(self.k):
            self.first = np.concatenate(([0], np.cumsum(np.bincount(self.k, minlength=self.shape.inner))))

    def _spans(self, k: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if self.first is None:
            return np.searchsorted(self.k, k, "left"), np.searchsorted(self.k, k, "right")
        return self.first[k], self.first[k + 1]

    def times(self, r: np.ndarray, k: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The product's cells and whether a product reaches them, as arrays of ``height * width``, for entries sorted by row."""
        if not self.ready:
            self._join()
        sr, w = self.semiring, self.shape.width
        lo, hi = self._spans(k)
        many = hi - lo
        total = int(many.sum())
        ring = sr.merge is np.add and sr.pair is np.multiply
        h = int(r[-1]) + 1
        if ring and self.finite and self.shape.inner * max(h, w) <= DENSE and h * w * self.shape.inner <= WORTH * total and np.isfinite(v).all():
            return self._dense(r, k, v, h)
        val, hit = np.full(h * w, sr.zero), np.zeros(h * w, bool)
        some = np.flatnonzero(many)
        r, v, lo, many = r[some], v[some], lo[some], many[some]
        ones = ring and self.ones and bool((v == 1).all())
        done = np.cumsum(many)
        cut = [0, *(np.flatnonzero(np.diff((done - many) // AT_ONCE)) + 1), len(r)]
        for at, to in zip(cut, cut[1:], strict=False):
            if at == to:
                continue
            n, top = many[at:to], int(r[at])
            end = np.cumsum(n)
            which = np.repeat(lo[at:to] - end + n, n)
            which += np.arange(len(which))
            key = np.repeat((r[at:to] - top) * w, n)
            key += self.col[which]
            here = slice(top * w, (int(r[to - 1]) + 1) * w)
            if ones:
                sums = np.bincount(key, minlength=here.stop - here.start)
                val[here] += sums
                hit[here] |= sums > 0
                continue
            x = sr.pair(np.repeat(v[at:to], n), self.val[which])
            if ring:
                val[here] += np.bincount(key, x, here.stop - here.start)
            else:
                sr.merge.at(val[here], key, x)
            hit[here][key] = True
        return val, hit

    def _dense(self, r: np.ndarray, k: np.ndarray, v: np.ndarray, h: int) -> tuple[np.ndarray, np.ndarray]:
        w, inner = self.shape.width, self.shape.inner
        if self.full is None:
            y, met = np.zeros((inner, w)), np.zeros((inner, w), bool)
            y[self.k, self.col], met[self.k, self.col] = self.val, True
            self.full, self.bits = y, np.ascontiguousarray(np.packbits(met, axis=0).T)
        x, met = np.zeros((h, inner)), np.zeros((h, inner), bool)
        x[r, k], met[r, k] = v, True
        bits = np.packbits(met, axis=1)
        val = (x @ self.full).ravel()
        hit = val != 0
        doubt = np.flatnonzero(~hit)  # products may be zeros, vanish or cancel: the patterns tell
        for lo in range(0, len(doubt), 1 << 16):
            cell = doubt[lo : lo + (1 << 16)]
            hit[cell] = (bits[cell // w] & self.bits[cell % w]).any(axis=1)
        return val, hit


def names_of(spark: SparkSession, n: int, p: Permutation, cut: int) -> DataFrame:
    """``at, body``: for runs of ``cut`` permuted numbers the numbers that they stand for."""
    now = p.apply(F.col("id"))
    rows = spark.range(n).select(F.expr("cast(0 as int)").alias("bi"), F.expr("cast(0 as int)").alias("bj"), F.floor(now / cut).cast("long").alias("strip"), F.pmod(now, F.lit(cut)).cast("long").alias("key"), F.col("id").cast("double").alias("v"))
    return packed_cells(rows, 1, ceil_div(n, cut)).select(F.col("strip").alias("at"), "body")


def multiply_panels(a: MatrixFrame, b: MatrixFrame, in_a: int, in_b: int, names: tuple[Permutation, Permutation] | None = None, count: bool = False) -> DataFrame:
    """``row, col, val`` of ``A B``. A panel of B goes to as many tasks as keep the cores busy, each strip of A to one of them for each panel; a task holds the panel, a strip of A and a strip of
    C, and no cell of C is stored or moved. The frame is lazy: what reads it twice multiplies twice. ``names`` are permutations of rows and columns to undo.
    With ``count``: ``n``, the cells of each strip."""
    spark, sr, shape = a.df.sparkSession, a.semiring, Panels.of(a, b, in_a, in_b)
    height, width, piece, inner = shape.height, shape.width, shape.piece, shape.inner
    strips, panels = ceil_div(a.n_rows, height), ceil_div(b.n_cols, width)
    busy = 8 * spark.sparkContext.defaultParallelism
    cuts = max(1, min(strips, ceil_div(busy, panels)))

    def chunks(m: MatrixFrame, place: str, div: str, strip: str, cut: int) -> DataFrame:
        rows = m.df.select(F.expr(div).cast("int").alias("bi"), F.lit(0).alias("bj"), F.expr(strip).cast("long").alias("strip"), F.expr(place).cast("long").alias("key"), F.col("val").cast("double").alias("v"))
        return saved(packed_cells(rows, 1, ceil_div(m.n_rows, cut)), fresh_path(spark, "packed"))

    left = chunks(a, f"(row % {height}) * {inner} + col", "0", f"row div {height}", height)
    right = chunks(b, f"(row % {piece}) * {width} + col % {width}", f"col div {width}", f"row div {piece}", piece)

    def every(n: int) -> Column:
        return F.explode(F.sequence(F.lit(0), F.lit(n - 1)))

    def to(panel: Column, cut: Column) -> Column:
        return (panel.cast("long") * cuts + cut).alias("z")

    def part(df: DataFrame, kind: int) -> DataFrame:
        return df.select("z", F.lit(kind // 2).alias("part"), "strip", F.lit(kind).alias("kind"), "body")

    left = left.withColumn("panel", every(panels)).select(to(F.col("panel"), F.pmod("strip", F.lit(cuts))), "strip", "body")
    right = right.withColumn("cut", every(cuts)).select(to(F.col("bi"), F.col("cut")), "strip", "body")
    parts = [part(left, 3), part(right, 1)]
    if names is not None:
        rows, cols = names_of(spark, a.n_rows, names[0], height), names_of(spark, b.n_cols, names[1], width)
        rows = rows.withColumn("panel", every(panels)).select(to(F.col("panel"), F.pmod("at", F.lit(cuts))), F.col("at").alias("strip"), "body")
        cols = cols.withColumn("cut", every(cuts)).select(to(F.col("at"), F.col("cut")), F.lit(0).cast("long").alias("strip"), "body")
        parts += [part(rows, 2), part(cols, 0)]
    met = parts[0]
    for more in parts[1:]:
        met = met.unionAll(more)
    keys = panels * cuts
    tasks = min(keys, max(busy, int(spark.conf.get("spark.sql.shuffle.partitions"))))
    placed = sorted_by(met, even_task(F.col("z"), keys, tasks), tasks, "z", "part", "strip", "kind")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, panel, row_names, col_names = None, Panel(shape, sr), None, None
        for batch in batches:
            for node, run, kind, body in zip(*(batch[c] for c in ("z", "strip", "kind", "body")), strict=True):
                node, run, kind, body = node.as_py(), run.as_py(), kind.as_py(), body.as_py()
                if node != at:
                    at, panel, row_names, col_names = node, Panel(shape, sr), None, None
                if kind == 0:
                    col_names = decoded(body)[1].astype(np.int64)
                elif kind == 1:
                    panel.add(run, body)
                elif kind == 2:
                    row_names = decoded(body)[1].astype(np.int64)
                elif panel.parts or panel.ready:
                    key, v = decoded(body)
                    r = key // inner
                    val, hit = panel.times(r, key - r * inner, v)
                    if count:
                        yield pa.RecordBatch.from_arrays([pa.array([np.count_nonzero(hit)], pa.int64())], names=["n"])
                        continue
                    cell = np.flatnonzero(hit)
                    for lo in range(0, len(cell), 1 << 16):
                        x = cell[lo : lo + (1 << 16)]
                        r = x // width
                        c = x - r * width
                        r = r + run * height if row_names is None else row_names[r]
                        c = c + at // cuts * width if col_names is None else col_names[c]
                        yield pa.RecordBatch.from_arrays([pa.array(r), pa.array(c), pa.array(val[x])], names=["row", "col", "val"])

    return placed.select("z", "strip", "kind", "body").mapInArrow(kernel, "n long" if count else ROWS)
