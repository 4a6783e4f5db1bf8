"""The given tables, and matrices made of them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from roundmm.functions.semiring import COUNT, PLUS_TIMES, Semiring
from roundmm.model import MatrixFrame, matrix_from

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name not in TABLES:
        raise ValueError(f"no table {name}")
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def side(df: DataFrame, column: str) -> int:
    """Length of an axis whose keys run from 0: the greatest key and one. From the files' statistics or one small scan."""
    top = df.agg(F.max(column)).first()[0]
    return 0 if top is None else int(top) + 1


def _mod(c: str, n: int) -> Column:
    return F.pmod(F.col(c), F.lit(n))


def fold_a(spark: SparkSession, sf_dir: str, n: int, semiring: Semiring = PLUS_TIMES) -> MatrixFrame:
    return matrix_from(load(spark, sf_dir, "lineitem"), _mod("l_orderkey", n), _mod("l_partkey", n), F.col("l_quantity"), n, n, semiring)


def fold_b(spark: SparkSession, sf_dir: str, n: int, semiring: Semiring = PLUS_TIMES) -> MatrixFrame:
    return matrix_from(load(spark, sf_dir, "lineitem"), _mod("l_partkey", n), _mod("l_suppkey", n), F.col("l_quantity"), n, n, semiring)


def scatter(spark: SparkSession, sf_dir: str, n: int) -> MatrixFrame:
    """Keys of line items spread as good as at random; a cell is 1."""
    li = load(spark, sf_dir, "lineitem")
    row = F.pmod(7 * F.col("l_orderkey") + 131 * F.col("l_linenumber"), F.lit(n))
    col = F.pmod(31 * F.col("l_partkey") + 17 * F.col("l_orderkey") + 7 * F.col("l_suppkey"), F.lit(n))
    m = matrix_from(li, row, col, F.lit(1.0), n, n)
    return MatrixFrame(m.df.withColumn("val", F.lit(1.0)), n, n)


def incidence(df: DataFrame, row: str, col: str, n_rows: int, n_cols: int) -> MatrixFrame:
    """Ones where a pair of keys occurs."""
    cells = df.select(F.col(row).cast("long").alias("row"), F.col(col).cast("long").alias("col")).dropna().distinct()
    return MatrixFrame(cells.withColumn("val", F.lit(1.0)), n_rows, n_cols, COUNT)


def counts(df: DataFrame, row: str, col: str, n_rows: int, n_cols: int) -> MatrixFrame:
    return matrix_from(df, F.col(row), F.col(col), F.lit(1.0), n_rows, n_cols, COUNT)


def user_hour(spark: SparkSession, sf_dir: str) -> MatrixFrame:
    """Users by hours since the first of January 2024, cents."""
    ev = load(spark, sf_dir, "events")
    hour = F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")) * 24 + F.hour("ts")
    cells = ev.select(F.col("user_id").alias("u"), hour.alias("h"), F.round(F.col("value") * 100).alias("v"))
    return matrix_from(cells, F.col("u"), F.col("h"), F.col("v"), side(cells, "u"), side(cells, "h"))


def gram(spark: SparkSession, sf_dir: str) -> MatrixFrame:
    """Embeddings in steps of 1/1024, whole numbers."""
    e = load(spark, sf_dir, "embeddings").select("vec_id", F.posexplode("embedding").alias("p", "x"))
    cells = e.select("vec_id", "p", F.floor(F.col("x").cast("double") * 1024).alias("v"))
    return matrix_from(cells, F.col("vec_id"), F.col("p"), F.col("v"), side(cells, "vec_id"), side(cells, "p"))
