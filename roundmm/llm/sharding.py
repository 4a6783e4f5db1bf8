"""Proportional stratified interleaving: every shard holds the sources in the corpus's proportions.

Within each source rows are put in a seeded random order; row ``r`` of ``n`` gets the fraction ``(r - 1/2) / n``;
all rows sorted by that fraction are cut into equal runs. Two distributed rankings do it: each splits its order into
fine key ranges, counts them, adds up the counts before each range, and numbers rows only inside a range.
No task ever sorts a whole source, and only ids, sizes and checksums move; texts are read once.

The order's key hashes id, checksum, size and, of rows equal in these, a number: copies of a document are spread as other rows are, and an id that
has many rows has as many keys.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F

from roundmm.llm.common import drop_stored, empty_text, md5_key, stored

#: Rows that one key range holds on average, up to MOST_RANGES ranges; beyond that ranges grow with the table.
RANGE_ROWS = 2_000
MOST_RANGES = 1_000_000
ROW_BYTES = 16


#: Equal rows are counted, and made again in lots of so many, so that one task never makes all copies of a row.
LOT = 100_000


def ranked(df: DataFrame, group: str, order: list[Column], place: Column, out: str, ranges: int) -> DataFrame:
    """Add ``out``: the 0-based rank in ``order`` within ``group`` (not null), and ``_of``: the group's rows. ``place`` in [0, 1) must rise with ``order``.

    Rows and counts of a range use the same exchange, so ``df`` is read once: the counts' hash of all columns keeps the optimizer from making a narrower one."""
    held = df.withColumn("_range", F.least(F.floor(place * F.lit(ranges)), F.lit(ranges - 1)).cast("int")).repartition(F.col(group), F.col("_range"))
    counts = held.groupBy(group, "_range").agg(F.count(F.lit(1)).alias("_n"), F.bit_xor(F.xxhash64(*held.columns)).alias("_seen")).where("_seen is not null")
    over = Window.partitionBy(group).orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)  # a row a range
    before = counts.select(F.col(group).alias("_b_group"), F.col("_range").alias("_b_range"), F.coalesce(F.sum("_n").over(over), F.lit(0)).alias("_before"), F.sum("_n").over(Window.partitionBy(group)).alias("_of"))
    rows = held.withColumn("_row", F.row_number().over(Window.partitionBy(group, "_range").orderBy(*order)))
    met = rows.join(before, (F.col(group) == F.col("_b_group")) & (F.col("_range") == F.col("_b_range")))
    return met.withColumn(out, F.col("_before") + F.col("_row") - 1).drop("_range", "_row", "_before", "_b_group", "_b_range")


def numbered(rows: DataFrame) -> DataFrame:
    """``rows`` with ``_copy``: 0, 1, ... for rows equal in all columns. Equal rows are counted before they are shuffled, and made again from the count."""
    n = rows.groupBy(*rows.columns).agg(F.count(F.lit(1)).alias("_n"))
    lots = n.withColumn("_lot", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("_n") - 1) / LOT))))
    last = F.least(F.col("_n") - 1, F.col("_lot") * LOT + LOT - 1)
    return lots.withColumn("_copy", F.explode(F.sequence(F.col("_lot") * LOT, last))).drop("_n", "_lot")


def stratified_shards(docs: DataFrame, shards: int, seed: int = 11, range_rows: int = RANGE_ROWS, source: str = "source") -> DataFrame:
    """``doc_id, source, size, text_crc32, shard, slot`` for every row of ``docs``.

    Law ``rows``: counts differ by at most one. Null texts count as empty, a null source is a source of its own, null ids and rows that share an id
    are ordered by checksum and size as well; repeated rows each take a place, in the order of a number given to them. An empty table gives no rows;
    other columns are ignored.
    """
    raw = empty_text().cast("binary")
    rows = docs.select("doc_id", F.col(source).cast("string").alias("source"), (F.octet_length(raw) + ROW_BYTES).cast("long").alias("size"), F.crc32(raw).alias("text_crc32"))
    rows = numbered(rows).withColumn("_key", md5_key(F.col("doc_id"), F.col("text_crc32"), F.col("size"), F.col("_copy"), seed=seed))
    seen = Observation("shard rows")
    rows = stored(rows.observe(seen, F.count(F.lit(1)).alias("n")).withColumn("_stratum", F.when(F.col("source").isNull(), F.lit("")).otherwise(F.concat(F.lit(":"), F.col("source")))), "shard-rows")
    total = seen.get["n"]
    ranges = min(MOST_RANGES, max(1, -(-total // range_rows)))
    place = F.conv(F.substring("_key", 1, 12), 16, 10).cast("double") / F.lit(float(16**12))
    order = [F.col("_key"), F.col("doc_id"), F.col("text_crc32"), F.col("size"), F.col("_copy")]
    inner = ranked(rows, "_stratum", order, place, "_rank", ranges)
    inner = inner.withColumn("_part", (F.col("_rank") + 0.5) / F.col("_of"))
    inner = stored(inner.select("doc_id", "source", "size", "text_crc32", "_copy", "_key", "_part", F.lit(0).alias("_all")), "shard-ranks")
    drop_stored(rows)
    whole = ranked(inner, "_all", [F.col("_part"), *order], F.col("_part"), "_at", ranges)
    shard = F.expr(f"cast((_at * {shards}L) div {max(total, 1)}L as int)")
    begin = F.expr(f"(cast(shard as bigint) * {max(total, 1)}L + {shards - 1}L) div {shards}L")
    return whole.withColumn("shard", shard).withColumn("slot", (F.col("_at") - begin).cast("long")).select("doc_id", "source", "size", "text_crc32", "shard", "slot")
