"""Sums, masks, permutations and summaries of matrices."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from roundmm.model import MatrixFrame
from roundmm.scratch import stored


def add(a: MatrixFrame, b: MatrixFrame, sign: float = 1.0) -> MatrixFrame:
    """Cell by cell; a cell of either pattern stays, even if it sums to zero."""
    if (a.n_rows, a.n_cols) != (b.n_rows, b.n_cols):
        raise ValueError("shapes differ")
    other = b.df.select("row", "col", (F.col("val") * sign if sign != 1.0 else F.col("val")).alias("_v"))
    met = a.df.join(other, ["row", "col"], "full")
    return replace(a, df=met.select("row", "col", a.semiring.combine(F.col("val"), F.col("_v")).alias("val")))


def subtract(a: MatrixFrame, b: MatrixFrame) -> MatrixFrame:
    if a.semiring.sql_plus != "sum":
        raise ValueError("this semiring has no subtraction")
    return add(a, b, -1.0)


def elementwise(m: MatrixFrame, f) -> MatrixFrame:
    return replace(m, df=m.df.select("row", "col", f(F.col("val")).alias("val")))


def scale(m: MatrixFrame, factor: float) -> MatrixFrame:
    """Times ``factor`` in the semiring."""
    return elementwise(m, lambda v: m.semiring.times(v, F.lit(float(factor))))


def shift(m: MatrixFrame, by: float) -> MatrixFrame:
    return elementwise(m, lambda v: v + by)


def clip(m: MatrixFrame, lo: float, hi: float) -> MatrixFrame:
    return elementwise(m, lambda v: F.greatest(F.least(v, F.lit(hi)), F.lit(lo)))


def prune(m: MatrixFrame, keep: Column | str | None = None) -> MatrixFrame:
    """Without cells that fail ``keep``; by default without zeros of the semiring."""
    return m.where(F.col("val") != m.semiring.zero if keep is None else keep)


def mask(m: MatrixFrame, pattern: MatrixFrame, negate: bool = False) -> MatrixFrame:
    return replace(m, df=m.df.join(pattern.df.select("row", "col"), ["row", "col"], "left_anti" if negate else "left_semi"))


def clean(m: MatrixFrame, policy: str = "zero") -> MatrixFrame:
    """Nulls and NaNs become the semiring's zero, or their cells go (``policy="drop"``)."""
    bad = F.col("val").isNull() | F.isnan("val")
    if policy == "drop":
        return m.where(~bad)
    return replace(m, df=m.df.withColumn("val", F.when(bad, F.lit(m.semiring.zero)).otherwise(F.col("val"))))


def masked_product(a: MatrixFrame, b: MatrixFrame, pattern: MatrixFrame) -> MatrixFrame:
    """Only the cells of ``pattern`` of ``A B``: the pattern joins the products, below their aggregation; or, where cells are reached by many products, it joins
    the product, which is made in chunks."""
    from roundmm.operators.sparse3d import MANY, multiply_3d_sparse, stored_pair, weight

    sr = a.semiring
    a, b = stored_pair(a, b)
    work, entries = weight(a, b)
    if work > MANY * entries and work * 8 > a.n_rows * b.n_cols:
        side = max(a.n_rows, a.n_cols, b.n_cols)
        c = multiply_3d_sparse(a, b, 0, 2, side=-(-side // -(-side // 2048)))
        return replace(c, df=c.df.join(pattern.df.select("row", "col"), ["row", "col"], "left_semi"))
    met = a.df.select("row", F.col("col").alias("k"), F.col("val").alias("x")).join(b.df.select(F.col("row").alias("k"), "col", F.col("val").alias("y")), "k")
    met = met.join(pattern.df.select("row", "col"), ["row", "col"], "left_semi")
    return MatrixFrame(met.groupBy("row", "col").agg(sr.plus(sr.times(F.col("x"), F.col("y"))).alias("val")), a.n_rows, b.n_cols, sr)


def band_product(a: MatrixFrame, b: MatrixFrame, width: int) -> MatrixFrame:
    """Products of the cells of A and B whose inner coordinates differ by at most ``width``, summed by cell: each cell of A
    goes to the coordinates of its band, which makes it an equi-join."""
    sr = a.semiring
    left = a.df.select("row", F.explode(F.sequence(F.col("col") - width, F.col("col") + width)).alias("k"), F.col("val").alias("x"))
    met = left.join(b.df.select(F.col("row").alias("k"), "col", F.col("val").alias("y")), "k")
    return MatrixFrame(met.groupBy("row", "col").agg(sr.plus(sr.times(F.col("x"), F.col("y"))).alias("val")), a.n_rows, b.n_cols, sr)


def top_per_row(m: MatrixFrame, k: int) -> DataFrame:
    w = Window.partitionBy("row").orderBy(F.desc("val"), "col")
    return m.df.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def norms(m: MatrixFrame) -> DataFrame:
    """One row: trace, squared Frobenius norm, sum, greatest value, cells."""
    v = F.col("val")
    return m.df.agg(
        F.sum(F.when(F.col("row") == F.col("col"), v).otherwise(0.0)).alias("trace"), F.sum(v * v).alias("frobenius2"), F.sum(v).alias("total"), F.max(v).alias("greatest"), F.count(F.lit(1)).alias("cells")
    )


def axis_index(df: DataFrame, name: str) -> DataFrame:
    """``name, idx``: ranks of the distinct values of a column, from 0."""
    return global_rank(df.select(name).where(F.col(name).isNotNull()).distinct(), [F.col(name)], "idx")


def global_rank(df: DataFrame, order: list[Column], out: str) -> DataFrame:
    """``df`` with ``out``: the rank of each row in ``order``, from 0. Rows are cut into key ranges, ranked within them, and moved on by the rows of the ranges
    before: no task sorts all of them."""
    held = stored(df.repartitionByRange(*order).withColumn("_part", F.spark_partition_id()), "ranked")
    sizes = held.groupBy("_part").agg(F.count(F.lit(1)).alias("_n"))
    upto = Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)  # a row a range
    before = sizes.select(F.col("_part").alias("_p"), "_n").select("_p", F.coalesce(F.sum("_n").over(upto), F.lit(0)).alias("_before"))
    rows = held.withColumn("_row", F.row_number().over(Window.partitionBy("_part").orderBy(*order)))
    return rows.join(F.broadcast(before), F.col("_part") == F.col("_p")).select(*df.columns, (F.col("_before") + F.col("_row") - 1).cast("long").alias(out))


@dataclass(frozen=True)
class Permutation:
    """A permutation of ``0 .. n-1`` as column expressions.

    ``affine``: ``a x + b mod n`` with ``a`` prime to ``n``. ``feistel``: four rounds on a grid of two near-equal sides,
    walked on until the number is below ``n``. Neither needs a table or a sort.
    """

    n: int
    kind: str = "affine"
    seed: int = 42

    def _affine(self) -> tuple[int, int]:
        a = (self.seed * 2654435761 + 12345) % self.n or 1
        while math.gcd(a, self.n) != 1:
            a += 1
        return a % self.n or 1, (self.seed * 40503 + 17) % self.n

    def _walk(self, x: Column, back: bool) -> Column:
        b = math.isqrt(self.n - 1) + 1 if self.n > 1 else 1
        a = -(-self.n // b)

        def once(v: Column) -> Column:
            left, right = F.floor(v / b).cast("long"), F.pmod(v, F.lit(b)).cast("long")
            for k in (range(4) if not back else reversed(range(4))):
                sign = -1 if back else 1
                if k % 2 == 0:
                    left = F.pmod(left + sign * F.pmod(F.xxhash64(right, F.lit(self.seed + k)), F.lit(a)), F.lit(a))
                else:
                    right = F.pmod(right + sign * F.pmod(F.xxhash64(left, F.lit(self.seed + k)), F.lit(b)), F.lit(b))
            return left * b + right

        first = once(x.cast("long"))
        walked = F.aggregate(F.sequence(F.lit(1), F.lit(64)), first, lambda v, _: F.when(v < self.n, v).otherwise(once(v)))
        return F.when(walked < self.n, walked).otherwise(F.raise_error(F.lit("the permutation's walk is too long")).cast("long"))

    def apply(self, x: Column) -> Column:
        if self.kind == "affine":
            a, b = self._affine()
            return F.pmod(x * a + b, F.lit(self.n)).cast("long")
        if self.kind == "feistel":
            return self._walk(x, False)
        raise ValueError("kind must be 'affine' or 'feistel'")

    def invert(self, x: Column) -> Column:
        if self.kind == "affine":
            a, b = self._affine()
            return F.pmod((x - b) * pow(a, -1, self.n), F.lit(self.n)).cast("long")
        return self._walk(x, True)


def table_permutation(n: DataFrame, seed: int) -> DataFrame:
    """``x, y``: the axis ``n(x)`` in the order of a hash."""
    return global_rank(n.select("x"), [F.xxhash64("x", F.lit(seed)), F.col("x")], "y")


def permute(m: MatrixFrame, rows: Permutation | None, cols: Permutation | None, back: bool = False) -> MatrixFrame:
    """Rows and columns renamed; ``back`` undoes it."""

    def to(p: Permutation | None, c: str) -> Column:
        return F.col(c) if p is None else (p.invert(F.col(c)) if back else p.apply(F.col(c))).alias(c)

    return replace(m, df=m.df.select(to(rows, "row"), to(cols, "col"), "val"))
