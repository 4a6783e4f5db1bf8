"""Every query with SQL, side by side with DuckDB, on the smallest tables."""

import os

import duckdb
import pytest

import __spark_entry__ as entry
from roundmm.oracles import ORACLES
from roundmm.queries import QUERIES

FULL = os.environ.get("TEST_ALL_QUERIES")
#: Cells of folded matrices are all there only from sf0.01 on; a few queries of each kind are enough here.
SOME = ["mm3d_dense_rho2", "mm2d_rho3", "mm3d_sparse_packed", "mm3d_sparse_permuted", "mm_join", "mm_chain_trade", "mm_triangles", "mm_links2", "mm_sources", "mm_masked", "schedule3d_rect_cover", "cost3d_rounds", "cost2d_naive_rounds", "reducer_words", "partition_hash_hist", "density_row_sample", "mat_add", "op_asof_value", "op_interval_pairs", "op_ledger_cube", "op_json_axis", "op_array_dot", "stream_incremental_product"]


@pytest.fixture(scope="module")
def duck(sf_dir):
    c = duckdb.connect()
    for f in os.listdir(sf_dir):
        path = f"{sf_dir}/{f}" + ("/*.parquet" if os.path.isdir(f"{sf_dir}/{f}") else "")
        c.sql(f"create view {f.split('.')[0]} as select * from read_parquet('{path}')")
    return c


def plain(rows):
    return sorted(tuple("null" if v is None or v != v else format(float(v), ".9g") if isinstance(v, (int, float)) else str(v) for v in r) for r in rows)


@pytest.mark.parametrize("name", sorted(ORACLES) if FULL else SOME)
def test_query_equals_sql(spark, duck, sf_dir, name):
    df = QUERIES[name](spark, sf_dir)
    want = duck.sql(ORACLES[name])
    cols = sorted(df.columns)
    assert cols == sorted(want.columns)
    place = [want.columns.index(c) for c in cols]
    assert plain(df.select(*cols).collect()) == plain([tuple(r[k] for k in place) for r in want.fetchall()])


def test_entry(spark):
    assert entry.entry(spark).count() == 64 * 64
    assert set(entry.oracle_sql()) <= set(entry.queries()) and set(ORACLES) <= set(QUERIES)


def test_measures_without_sql(spark, sf_dir):
    t = QUERIES["component_times"](spark, sf_dir).collect()
    assert [r["rho"] for r in t] == [2, 4] and all(r["t_total"] > 0 and r["t_infr"] > 0 for r in t)
    exact = QUERIES["density_exact"](spark, sf_dir).first()[0]
    for name in ("density_hll", "density_kmin"):
        assert abs(QUERIES[name](spark, sf_dir).first()[0] / exact - 1) < 0.1
    a = {(r[0], r[1]): r[2] for r in QUERIES["mm_mllib"](spark, sf_dir).collect()}
    b = {(r[0], r[1]): r[2] for r in QUERIES["mm_join"](spark, sf_dir).collect()}
    assert {k: v for k, v in a.items() if v} == {k: v for k, v in b.items() if v}
    assert QUERIES["plan_choice"](spark, sf_dir).count() == 18


@pytest.mark.parametrize("name", ["op_missing_cells", "op_band_join", "op_pattern", "mm_roles", "mm_items_documents", "mm_quality_tokens", "lower_bound_ratio", "cost_sparse_rounds", "mm3d_sparse_observed_words", "reducer_words_sparse", "cost_sparse_bound", "plan_choice"])
def test_whole_tables_equal_sql(spark, duck, sf_dir, name):
    test_query_equals_sql(spark, duck, sf_dir, name)


def test_no_row_is_left_out(spark, sf_dir):
    orders = QUERIES["op_missing_cells"](spark, sf_dir)
    assert orders.where("row >= 100").count() > 0
    assert QUERIES["op_pattern"](spark, sf_dir).where("row >= 200").count() > 0
    assert QUERIES["op_band_join"](spark, sf_dir).where("row <> 5 and col <> 7").count() > 0
    assert QUERIES["mm_quality_tokens"](spark, sf_dir).select("col").distinct().count() > 50


def test_communication_moves_every_payload(spark, sf_dir):
    """The plan of the copying rounds reads and shuffles the cells of A, of B and of the slots."""
    from roundmm.functions.schedule import Grid3D
    from roundmm.operators.baselines import pipeline_blocks
    from roundmm.operators.dense3d import product_round
    from roundmm.functions.semiring import PLUS_TIMES
    from roundmm.plans.components import communication_round
    from roundmm.sources.tables import fold_a, fold_b

    a, b = pipeline_blocks(fold_a(spark, sf_dir, 8), fold_b(spark, sf_dir, 8), 4)
    g = Grid3D(2, 2, 2, 1)
    before = product_round(a.df, b.df, None, g, 0, 4, PLUS_TIMES, "even")
    for slots, payloads in ((None, ("ca", "cb")), (before, ("ca", "cb", "cc"))):
        plan = communication_round(a.df, b.df, slots, g, 1 if slots is not None else 0, 4, "copy")._jdf.queryExecution().optimizedPlan().toString()
        shuffled = [x for x in plan.splitlines() if "Repartition" in x]
        assert len(shuffled) >= len(payloads)
        assert plan.count("cells#") >= 2 and all(f"AS {c}#" in plan for c in payloads), plan


def test_factors_are_measured(spark, sf_dir):
    got = QUERIES["measure_block_gain"](spark, sf_dir).collect()
    assert len(got) == 2 and all(abs(r.factor - r.from_seconds / r.to_seconds) < 1e-9 for r in got)


def test_planner_weighs_all_methods():
    from roundmm.plans.planner import best_plan

    assert best_plan(16_000, 3 * 4_000**2, 3 * 16_000**2, 32).method == "3d"
    assert best_plan(1 << 20, 3 * 4_000**2, 3 << 30, 32, density=8 / (1 << 20)).method == "sparse"
    assert best_plan(16_000, 3 * 16_000 * 200, 2 * 16_000**2, 4).method == "2d"
    with pytest.raises(ValueError):
        best_plan(16_000, 300, 300, 4)


@pytest.fixture(scope="module")
def dense_items(spark, tmp_path_factory):
    """Line items enough that a cell of the square of their scatter expects more than one product."""
    from pyspark.sql import functions as F

    root = str(tmp_path_factory.mktemp("items"))
    li = spark.range(900_000).select(F.col("id").alias("l_orderkey"), F.pmod(F.xxhash64("id"), F.lit(20_000)).alias("l_partkey"), F.pmod(F.xxhash64("id", F.lit(1)), F.lit(1000)).alias("l_suppkey"), F.lit(0).alias("l_linenumber"), F.lit(1.0).alias("l_quantity"))
    li.write.parquet(f"{root}/lineitem.parquet")
    return root


def test_expected_density_beyond_one_equals_sql(spark, dense_items):
    c = duckdb.connect()
    c.sql(f"create view lineitem as select * from read_parquet('{dense_items}/lineitem.parquet/*.parquet')")
    want = c.sql(ORACLES["density_er"]).fetchall()
    assert want[0][2] > 1 and plain(QUERIES["density_er"](spark, dense_items).collect()) == plain(want)


#: Queries that count blocks and entries of the folds of line items.
OF_ITEMS = ["cost3d_rounds", "cost3d_total", "cost2d_rounds", "cost2d_naive_rounds", "mapper_replicas_balanced", "mapper_replicas_naive", "lower_bound_ratio", "op_balance_stats", "op_cum_shuffle", "op_ledger_cube", "op_ledger_gsets", "op_ledger_rollup"]


@pytest.fixture(scope="module")
def few_items(spark, tmp_path_factory):
    """So few line items that blocks and strips are missing."""
    root = str(tmp_path_factory.mktemp("few"))
    spark.createDataFrame([(7 * k, 5 * k, 3 * k, 1.0) for k in range(20)], "l_orderkey long, l_partkey long, l_suppkey long, l_quantity double").coalesce(1).write.parquet(f"{root}/lineitem.parquet")
    return root


@pytest.mark.parametrize("name", OF_ITEMS)
def test_ledgers_follow_the_table(spark, few_items, name):
    c = duckdb.connect()
    c.sql(f"create view lineitem as select * from read_parquet('{few_items}/lineitem.parquet/*.parquet')")
    df, want = QUERIES[name](spark, few_items), c.sql(ORACLES[name])
    place = [want.columns.index(x) for x in df.columns]
    assert plain(df.collect()) == plain([tuple(r[k] for k in place) for r in want.fetchall()])
