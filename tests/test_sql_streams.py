import numpy as np
from pyspark.sql import functions as F
from tests.test_core import array, ints, of_array

from roundmm import sqlext
from roundmm.functions.placement import even_task, rank_3d
from roundmm.functions.schedule import Grid3D, schedule_3d
from roundmm.model import MatrixFrame, to_blocks
from roundmm.scratch import fresh_path
from roundmm.streaming import products as stream


def test_table_functions(spark):
    sqlext.register(spark)
    got = {tuple(r) for r in spark.sql("SELECT * FROM schedule_3d(3, 2)").collect()}
    assert got == {tuple(r) for r in schedule_3d(spark, Grid3D(3, 3, 3, 2)).collect()}
    assert spark.sql("SELECT * FROM schedule_2d(4, 3)").where("round = 1").count() == 4
    assert [r["rounds"] for r in spark.sql("SELECT * FROM cost_3d(64, 16) ORDER BY rho").collect()] == [5, 3, 3, 2]
    bad = spark.sql("SELECT count(*) AS n FROM schedule_3d(4, 2) WHERE slot3d(i, h, j, 4, 2) <> slot OR round3d(i, h, j, 4, 2) <> round").first()
    assert bad["n"] == 0
    keys = schedule_3d(spark, Grid3D(5, 5, 5, 3)).withColumn("e", even_task(rank_3d(F.col("i"), F.col("j"), F.col("slot"), 5, 3), 75, 7))
    keys.createOrReplaceTempView("keys")
    assert spark.sql("SELECT count(*) AS n FROM keys WHERE task3d(i, j, slot, 5, 3, 7) <> e").first()["n"] == 0


def test_products_of_views(spark):
    x, y = ints(1, 4, 5), ints(2, 5, 3)
    sqlext.register_matrix(spark, "x_view", of_array(spark, x))
    sqlext.register_matrix(spark, "y_view", of_array(spark, y))
    assert np.array_equal(array(MatrixFrame(sqlext.sql_product(spark, "x_view", "y_view"), 4, 3)), x @ y)
    assert sqlext.sql_product(spark, "x_view", "y_view", "min_plus").count() == 12


def test_block_functions(spark):
    x = ints(3, 6, 4)
    b = to_blocks(of_array(spark, x), 3, 4).df.cache()
    t = {r["bi"]: np.frombuffer(r["t"], "<f8").reshape(4, 3) for r in b.select("bi", sqlext.block_transpose("cells", "nr", "nc").alias("t")).collect()}
    assert np.array_equal(np.hstack([t[0], t[1]]), x.T)
    s = np.frombuffer(b.groupBy("bj").agg(sqlext.block_sum()(F.col("cells")).alias("s")).first()["s"], "<f8").reshape(3, 4)
    assert np.array_equal(s, x[:3] + x[3:])
    f = b.where("bi = 0").select(sqlext.block_fma()(F.col("cells"), sqlext.block_transpose("cells", "nr", "nc"), F.lit(None).cast("binary"), "nr", "nc", "nr").alias("p")).first()["p"]
    assert np.array_equal(np.frombuffer(f, "<f8").reshape(3, 3), x[:3] @ x[:3].T)
    d = sqlext.scaled_blocks(b, 2.0).where("bi = 1").first()
    assert np.array_equal(np.frombuffer(d["cells"], "<f8").reshape(3, 4), 2 * x[3:])


def test_replayed_events_count_once(spark, sf_dir):
    path = stream.split_events(spark, sf_dir)
    spark.read.parquet(path).limit(50).write.mode("append").parquet(path)
    got = stream.run_to_table(stream.user_type_counts(stream.event_stream(spark, path))).agg(F.sum("n")).first()[0]
    assert got == spark.read.parquet(f"{sf_dir}/events.parquet").count()


def test_late_rows_are_dropped(spark):
    path = fresh_path(spark, "late")
    make = lambda rs: spark.createDataFrame(rs, "event_id long, ts string, user_id long, event_type string").withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1)
    # one file a batch, in the order of writing; a batch drops what is behind the watermark that stood one batch before it
    for rows in ([(1, "2024-01-01 00:00:00", 1, "a"), (2, "2024-01-10 00:00:00", 1, "a")], [(3, "2024-01-11 00:00:00", 1, "a")], [(4, "2024-01-02 00:00:00", 1, "a"), (5, "2024-01-20 00:00:00", 1, "a")]):
        make(rows).write.mode("append").parquet(path)
    out = stream.run_to_table(stream.windowed_counts(stream.event_stream(spark, path, 1)), "append").collect()
    assert {str(r["start"])[:10] for r in out} == {"2024-01-01", "2024-01-10", "2024-01-11"} and sum(r["n"] for r in out) == 3


def test_sessions(spark, sf_dir):
    path = stream.split_events(spark, sf_dir)
    out = stream.run_to_table(stream.session_counts(stream.event_stream(spark, path)), "append")
    assert 0 < out.agg(F.sum("n")).first()[0] <= spark.read.parquet(f"{sf_dir}/events.parquet").count()


def test_late_rows_are_counted(spark, sf_dir, tmp_path):
    """A file of old events after newer ones: the watermark drops its rows, and the report says how many."""
    from roundmm.sources.tables import load
    from roundmm.streaming import products as stream

    ev = load(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    path = str(tmp_path / "ev")
    ev.coalesce(1).write.parquet(path)
    ev.orderBy(F.desc("ts")).limit(1).coalesce(1).write.mode("append").parquet(path)  # rows are late by the watermark of the batch before the last
    ev.limit(7).withColumn("ts", F.lit("2001-01-01 00:00:00").cast("timestamp")).coalesce(1).write.mode("append").parquet(path)
    late: list[int] = []
    stream.run_to_table(stream.windowed_counts(stream.event_stream(spark, path, 1)), "append", late)
    assert 0 < sum(late) <= 7 and len(late) >= 3
