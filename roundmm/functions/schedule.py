"""Which products happen in which round and slot, as arithmetic on columns.

3D: product ``(i, h, j)`` of a ``qi x qh x qj`` grid belongs to group ``g = (h - i - j) mod qh``. Groups are dealt to rounds,
``rho`` a round: slot ``g mod rho`` of round ``g div rho``. Each group uses a block of A for the columns ``j = h - i - g (mod qh)``,
a block of B for the rows ``i = h - j - g (mod qh)``: once each on a square grid.
2D: product ``(i, j)`` of ``s`` row strips and ``s`` column strips belongs to group ``(j - i) mod s``.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def ceil_div(a: int, b: int) -> int:
    return -(-a // b)


@dataclass(frozen=True)
class Grid3D:
    qi: int
    qh: int
    qj: int
    rho: int

    def __post_init__(self):
        if min(self.qi, self.qh, self.qj) < 1 or not 1 <= self.rho <= self.qh:
            raise ValueError(f"need grid sides of at least 1 and 1 <= rho <= {self.qh}: {self}")

    @property
    def product_rounds(self) -> int:
        return ceil_div(self.qh, self.rho)

    @property
    def rounds(self) -> int:
        """With the round that folds the slots."""
        return self.product_rounds + 1

    def slots(self, r: int) -> int:
        return min(self.rho, self.qh - r * self.rho)

    def group(self, i: Column, h: Column, j: Column) -> Column:
        return F.pmod(h - i - j, F.lit(self.qh))

    def slot_of(self, i: Column, h: Column, j: Column) -> Column:
        return F.pmod(self.group(i, h, j), F.lit(self.rho))

    def round_of(self, i: Column, h: Column, j: Column) -> Column:
        return F.floor(self.group(i, h, j) / F.lit(self.rho)).cast("int")

    def _copies(self, df: DataFrame, r: int, free: str, fixed: Column, side: int) -> DataFrame:
        slot = F.explode(F.sequence(F.lit(0), F.lit(self.slots(r) - 1)))
        df = df.select("*", slot.alias("slot"))
        first = F.pmod(F.col("h") - fixed - F.col("slot") - F.lit(r * self.rho), F.lit(self.qh))
        if side <= self.qh:
            return df.withColumn(free, first.cast("int")).where(F.col(free) < side)
        every = F.sequence(first.cast("int"), F.lit(side - 1), F.lit(self.qh))
        return df.withColumn(free, F.explode(every))

    def copies_of_a(self, df: DataFrame, r: int) -> DataFrame:
        """Rows ``i, h, ...`` of A, once for each slot and column ``j`` of round ``r`` that needs them."""
        return self._copies(df, r, "j", F.col("i"), self.qj)

    def copies_of_b(self, df: DataFrame, r: int) -> DataFrame:
        """Rows ``h, j, ...`` of B, once for each slot and row ``i``."""
        return self._copies(df, r, "i", F.col("j"), self.qi)


@dataclass(frozen=True)
class Grid2D:
    si: int
    sj: int
    rho: int
    row_major: bool = False

    def __post_init__(self):
        if min(self.si, self.sj) < 1 or not 1 <= self.rho <= self.sj:
            raise ValueError(f"need at least one strip and 1 <= rho <= {self.sj}: {self}")

    @property
    def rounds(self) -> int:
        return ceil_div(self.sj, self.rho)

    def slots(self, r: int) -> int:
        return min(self.rho, self.sj - r * self.rho)

    def products(self, spark: SparkSession, r: int) -> DataFrame:
        """``i, j`` of round ``r``; balanced by groups, or the naive next run of products in row order."""
        if self.row_major:
            lo, hi = r * self.rho * self.si, min((r * self.rho + self.slots(r)) * self.si, self.si * self.sj)
            n = spark.range(lo, hi)
            return n.select((F.col("id") / self.sj).cast("int").alias("i"), F.pmod("id", F.lit(self.sj)).cast("int").alias("j"))
        at = spark.range(self.si).select(F.col("id").cast("int").alias("i"), F.explode(F.sequence(F.lit(0), F.lit(self.slots(r) - 1))).alias("slot"))
        return at.select("i", F.pmod(F.col("i") + F.col("slot") + r * self.rho, F.lit(self.sj)).cast("int").alias("j"))

    def copies_of_a(self, df: DataFrame, r: int) -> DataFrame:
        """Strips ``i, ...`` of A for every product of the round; arithmetic, no table of products."""
        if self.row_major:
            lo, hi = r * self.rho * self.si, min((r * self.rho + self.slots(r)) * self.si, self.si * self.sj)
            first = F.greatest(F.lit(lo) - F.col("i") * self.sj, F.lit(0))
            last = F.least(F.lit(hi) - F.col("i") * self.sj, F.lit(self.sj)) - 1
            return df.where(first <= last).withColumn("j", F.explode(F.sequence(first.cast("int"), last.cast("int"))))
        slot = F.explode(F.sequence(F.lit(0), F.lit(self.slots(r) - 1)))
        df = df.select("*", slot.alias("_slot"))
        return df.withColumn("j", F.pmod(F.col("i") + F.col("_slot") + r * self.rho, F.lit(self.sj)).cast("int")).drop("_slot")

    def copies_of_b(self, df: DataFrame, r: int) -> DataFrame:
        if self.row_major:
            lo, hi = r * self.rho * self.si, min((r * self.rho + self.slots(r)) * self.si, self.si * self.sj)
            first = F.greatest(F.ceil((F.lit(lo) - F.col("j")) / F.lit(self.sj)), F.lit(0)).cast("int")
            last = (F.floor((F.lit(hi - 1) - F.col("j")) / F.lit(self.sj))).cast("int")
            return df.where(first <= last).withColumn("i", F.explode(F.sequence(first, last)))
        slot = F.explode(F.sequence(F.lit(0), F.lit(self.slots(r) - 1)))
        df = df.select("*", slot.alias("_slot"))
        first = F.pmod(F.col("j") - F.col("_slot") - r * self.rho, F.lit(self.sj)).cast("int")
        if self.si <= self.sj:
            return df.withColumn("i", first).where(F.col("i") < self.si).drop("_slot")
        return df.withColumn("i", F.explode(F.sequence(first, F.lit(self.si - 1), F.lit(self.sj)))).drop("_slot")


def schedule_3d(spark: SparkSession, grid: Grid3D) -> DataFrame:
    """Every product with its round and slot: ``i, h, j, round, slot``. For reports and tests; methods use the arithmetic."""
    at = spark.range(grid.qi).select(F.col("id").cast("int").alias("i"))
    at = at.withColumn("h", F.explode(F.sequence(F.lit(0), F.lit(grid.qh - 1)))).withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(grid.qj - 1))))
    i, h, j = F.col("i"), F.col("h"), F.col("j")
    return at.select("i", "h", "j", grid.round_of(i, h, j).alias("round"), grid.slot_of(i, h, j).cast("int").alias("slot"))


def schedule_2d(spark: SparkSession, grid: Grid2D) -> DataFrame:
    out = None
    for r in range(grid.rounds):
        one = grid.products(spark, r).select("i", "j", F.lit(r).alias("round"))
        out = one if out is None else out.unionAll(one)
    return out
