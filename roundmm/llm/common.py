"""Shared plumbing: table access, size-checked broadcasts, components. Intermediates are stored by :mod:`roundmm.scratch`."""

from __future__ import annotations

import gc
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BinaryType, MapType, StringType, StructType

from roundmm.scratch import remove, stored

#: Rows and bytes up to which a side of a join may be broadcast; beyond it the join shuffles.
BROADCAST_ROWS = 200_000
BROADCAST_BYTES = 64 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def drop_stored(*frames: DataFrame) -> None:
    """Delete the files behind frames made by :func:`stored`; they must not be read again."""
    for df in frames:
        for parent in {f.rpartition("/")[0] for f in df.inputFiles()}:
            remove(df.sparkSession, parent)


def free_shuffles(spark: SparkSession) -> None:
    """Let Spark's cleaner drop shuffle files of frames that nothing refers to any more."""
    gc.collect()
    spark._jvm.System.gc()


def row_bytes(df: DataFrame) -> Column:
    """About what a row holds in memory: texts and binaries by their length, nested values by that of their JSON."""
    total = F.lit(16)
    for f in df.schema:
        c = F.col(f"`{f.name}`")
        if isinstance(f.dataType, (StringType, BinaryType)):
            total = total + F.coalesce(F.octet_length(c), F.lit(0)) + 16
        elif isinstance(f.dataType, (ArrayType, MapType, StructType)):
            total = total + F.coalesce(F.octet_length(F.to_json(F.struct(c))), F.lit(0))
        else:
            total = total + 16
    return total.cast("long")


def small(df: DataFrame, max_rows: int = BROADCAST_ROWS, max_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """``df``, which should be a stored frame, with a broadcast hint if it has at most ``max_rows`` rows and ``max_bytes`` bytes, else
    unchanged (the join then shuffles)."""
    seen = df.limit(max_rows + 1).agg(F.count(F.lit(1)), F.coalesce(F.sum(row_bytes(df)), F.lit(0))).first()
    return F.broadcast(df) if seen[0] <= max_rows and seen[1] <= max_bytes else df


def sliced(batches: Iterator[pa.RecordBatch], rows: int = 512) -> Iterator[pa.RecordBatch]:
    """The batches in slices, so that what a Python worker makes of one at a time stays small."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def empty_text(col: str = "text") -> Column:
    return F.coalesce(F.col(col), F.lit(""))


def ascii_lower(col: Column) -> Column:
    """Lower-case A-Z and leave every other character alone."""
    return F.translate(col, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def remainder(modulus: int, col: str = "doc_id") -> Column:
    """crc32 of the id as text, modulo ``modulus``; a null id counts as the empty text."""
    return F.pmod(F.crc32(F.coalesce(F.col(col).cast("string"), F.lit("")).cast("binary")), F.lit(modulus))


def unit_hash(*cols: Column, seed: int) -> Column:
    """A number in [0, 1) from md5 of the columns as text: 12 hex digits, the same in any SQL engine."""
    return F.conv(F.substring(md5_key(*cols, seed=seed), 1, 12), 16, 10).cast("double") / F.lit(float(16**12))


def md5_key(*cols: Column, seed: int) -> Column:
    parts = [F.coalesce(c.cast("string"), F.lit("")) for c in cols]
    return F.md5(F.concat_ws(":", F.lit(str(seed)), *parts).cast("binary"))


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Connected components of ``edges(a, b)``: one row ``(node, component)`` per node, the smallest reachable id.

    Hash-to-min with pointer jumping: every round each node takes the smallest label among its neighbours, and
    then the label of its label. Rows per round are the edges and the nodes; nothing is collected. Labels
    are written to the shared folder each round, so a lost executor costs one round.
    """
    both = stored(
        edges.select("a", "b").where("a <> b").unionAll(edges.select(F.col("b").alias("a"), F.col("a").alias("b")).where("a <> b")).distinct(),
        "cc-edges",
    )
    labels = stored(both.groupBy(F.col("a").alias("node")).agg(F.least(F.first("a"), F.min("b")).alias("component")), "cc-labels")
    for _ in range(max_rounds):
        heard = both.join(labels, both.b == labels.node).groupBy(F.col("a").alias("node")).agg(F.min("component").alias("heard"))
        took = labels.join(heard, "node").select("node", F.least("component", "heard").alias("near"), F.col("component").alias("was"))
        jump = labels.select(F.col("node").alias("near"), F.col("component").alias("far"))
        after = stored(
            took.join(jump, "near", "left").select("node", F.least("near", F.coalesce("far", "near")).alias("component"), "was"),
            "cc-labels",
        )
        changed = after.where("component <> was").limit(1).count()
        drop_stored(labels)
        labels = after.select("node", "component")
        if not changed:
            break
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    drop_stored(both)
    return labels
