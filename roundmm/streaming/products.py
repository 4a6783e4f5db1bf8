"""Matrices and products over a stream of events."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from roundmm.plans.rounds import RoundStore, fingerprint, plan_hash
from roundmm.scratch import fresh_path
from roundmm.sources.tables import load


def split_events(spark: SparkSession, sf_dir: str, files: int = 4) -> str:
    """The events as ``files`` files of a fresh folder, to be replayed."""
    path = fresh_path(spark, "stream-events")
    load(spark, sf_dir, "events").repartitionByRange(files, "ts").write.parquet(path)
    return path


def event_stream(spark: SparkSession, path: str, per_trigger: int = 2) -> DataFrame:
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path)


def run_to_table(result: DataFrame, mode: str = "complete", late: list[int] | None = None) -> DataFrame:
    """Run what is available, to Parquet: the last batch's result for ``complete``, all batches' for ``append``. ``late`` gets, for each batch,
    the rows that the watermark dropped."""
    spark = result.sparkSession
    out = fresh_path(spark, "stream-out")

    def write(batch: DataFrame, number: int) -> None:
        # a batch that is run again writes the same folder: the number is its identity
        batch.write.mode("overwrite").parquet(f"{out}/batch={number}")

    q = result.writeStream.outputMode(mode).foreachBatch(write).trigger(availableNow=True).option("checkpointLocation", fresh_path(spark, "stream-state")).queryName(f"roundmm_{uuid.uuid4().hex[:8]}").start()
    q.awaitTermination()
    if late is not None:
        late += [sum(s["numRowsDroppedByWatermark"] for s in p["stateOperators"]) for p in q.recentProgress]
    found = spark.read.parquet(out)
    if mode == "complete":
        last = found.agg(F.max("batch")).first()[0]
        found = found.where(F.col("batch") == last)
    return found.drop("batch")


def user_type_counts(events: DataFrame) -> DataFrame:
    """``user_id, event_type, n`` so far. Replayed events count once."""
    return events.dropDuplicates(["event_id"]).groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))


def windowed_counts(events: DataFrame, width: str = "1 day", late: str = "2 days") -> DataFrame:
    """User by type matrices of tumbling windows; rows later than ``late`` are dropped, windows come once they close."""
    ev = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    return ev.groupBy(F.window("ts", width).alias("w"), "user_id", "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "user_id", "event_type", "n")


def session_counts(events: DataFrame, gap: str = "2 hours", late: str = "1 day") -> DataFrame:
    ev = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    return ev.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "user_id", "n")


def incremental_product(events: DataFrame, b: DataFrame) -> DataFrame:
    """``C += dA B`` for a static ``b(event_type, col, weight)``: times distributes over plus, so each batch adds its share."""
    return events.join(b, "event_type").groupBy(F.col("user_id").alias("row"), "col").agg(F.sum("weight").cast("double").alias("val"))


def close_pairs(events: DataFrame, seconds: int = 3600) -> DataFrame:
    """Pairs of one user's events, the second within ``seconds`` after the first, by a stream-stream join in time bounds."""
    ev = events.withColumn("ts", F.col("ts").cast("timestamp"))
    a = ev.select(F.col("user_id").alias("u"), F.col("ts").alias("t1"), F.col("event_id").alias("e1")).withWatermark("t1", "2 days")
    b = ev.select("user_id", F.col("ts").alias("t2"), F.col("event_id").alias("e2")).withWatermark("t2", "2 days")
    near = (F.col("t2") >= F.col("t1")) & (F.col("t2") <= F.col("t1") + F.expr(f"interval {seconds} seconds")) & (F.col("e1") != F.col("e2"))
    return a.join(b, (F.col("u") == F.col("user_id")) & near).select("u", "e1", "e2")


def product_by_batches(events: DataFrame, b: DataFrame, store: RoundStore) -> DataFrame:
    """The same product, each micro-batch a committed round of ``store``: its own share ``dA B`` under its number. A batch that
    was committed before a crash is not run again; the store raises if it holds another stream's batch, or another B. The result folds the committed shares."""
    out = events.sparkSession
    digest = plan_hash(kind="stream product", columns=b.columns, b=fingerprint(b))

    def commit(batch: DataFrame, number: int) -> None:
        job = f"stream batch {fingerprint(batch)}"
        if number not in store.committed(digest):
            store.commit(job, digest, number, 1, incremental_product(batch, b))
        elif {r["job"] for r in store.manifest().where(F.col("round") == number).collect()} != {job}:  # one manifest row
            raise ValueError(f"the store holds batch {number} of another stream")

    q = events.writeStream.foreachBatch(commit).trigger(availableNow=True).option("checkpointLocation", fresh_path(out, "stream-state")).start()
    q.awaitTermination()
    shares = [out.read.parquet(p) for p in store.committed(digest).values()]
    total = shares[0]
    for s in shares[1:]:
        total = total.unionAll(s)
    return total.groupBy("row", "col").agg(F.sum("val").alias("val"))


def once(events: DataFrame, late: str = "2 days") -> DataFrame:
    """Events without replays, their ids remembered as long as the watermark allows."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
