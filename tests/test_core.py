import itertools

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from roundmm.functions.placement import even_task, polynomial_task, rank_3d
from roundmm.functions.schedule import Grid2D, Grid3D, schedule_2d, schedule_3d
from roundmm.functions.semiring import COUNT, MAX_MIN, MAX_PLUS, MAX_TIMES, MIN_PLUS, OR_AND, PLUS_TIMES, SEMIRINGS
from roundmm.model import MatrixFrame, matrix_from, to_blocks, to_coordinates
from roundmm.operators import baselines as base
from roundmm.operators import elementwise as ew
from roundmm.operators.dense2d import multiply_2d, strips
from roundmm.operators.dense3d import multiply_3d, product_round, grid_of
from roundmm.operators.sparse3d import coo_product, long_round, multiply_3d_sparse, sparse_grid
from roundmm.plans import costs, density
from roundmm.plans.planner import plan, plan_3d
from roundmm.plans.rewrite import describe, leaf, optimize
from roundmm.plans.rounds import RoundStore, Stopped
from roundmm.scratch import stored
from roundmm.sources import generators as gen


def frame(spark, cells, rows, cols, semiring=PLUS_TIMES):
    return MatrixFrame(spark.createDataFrame([(int(r), int(c), float(v)) for r, c, v in cells], "row long, col long, val double"), rows, cols, semiring)


def of_array(spark, x, semiring=PLUS_TIMES, sparse=False):
    return frame(spark, [(r, c, v) for (r, c), v in np.ndenumerate(x) if not sparse or v != semiring.zero], *x.shape, semiring)


def array(m):
    out = np.full((m.n_rows, m.n_cols), m.semiring.zero)
    rows = m.df.collect()
    assert len({(r["row"], r["col"]) for r in rows}) == len(rows)
    for r in rows:
        out[r["row"], r["col"]] = r["val"]
    return out


def ints(seed, rows, cols, share=1.0):
    rng = np.random.default_rng(seed)
    x = rng.integers(-5, 6, (rows, cols)).astype(float)
    return np.where(rng.random((rows, cols)) < share, x, 0.0)


# ---- schedules


@pytest.mark.parametrize("sides", [(1, 1, 1), (4, 4, 4), (2, 3, 5), (5, 2, 3), (4, 1, 4), (1, 8, 1), (3, 4, 2)])
def test_every_product_once(sides):
    qi, qh, qj = sides
    for rho in range(1, qh + 1):
        g = Grid3D(qi, qh, qj, rho)
        seen = set()
        for r in range(g.product_rounds):
            for i, h, j in itertools.product(range(qi), range(qh), range(qj)):
                group = (h - i - j) % qh
                if group // rho == r:
                    assert group % rho < g.slots(r)
                    seen.add((i, h, j))
        assert len(seen) == qi * qh * qj and g.rounds == -(-qh // rho) + 1


def test_worked_example(spark):
    g = Grid3D(4, 4, 4, 2)
    got = {(r["round"], r["slot"]): r["h"] for r in schedule_3d(spark, g).where("i = 1 and j = 3").collect()}
    assert got == {(0, 0): 0, (0, 1): 1, (1, 0): 2, (1, 1): 3}
    a = spark.createDataFrame([(1, 0)], "i int, h int")
    assert {(r["slot"], r["j"]) for r in g.copies_of_a(a, 0).collect()} == {(0, 3), (1, 2)}
    b = spark.createDataFrame([(0, 3)], "h int, j int")
    assert {(r["slot"], r["i"]) for r in g.copies_of_b(b, 0).collect()} == {(0, 1), (1, 0)}
    z = spark.range(1).select(*[rank_3d(F.lit(1), F.lit(3), F.lit(s), 4, 2).alias(f"z{s}") for s in (0, 1)]).first()
    assert tuple(z) == (14, 15)
    h = Grid2D(4, 4, 2)
    assert {r["j"] for r in h.copies_of_a(spark.createDataFrame([(1,)], "i int"), 1).collect()} == {3, 0}
    assert {r["i"] for r in h.copies_of_b(spark.createDataFrame([(0,)], "j int"), 1).collect()} == {2, 1}
    assert {r["round"] for r in schedule_2d(spark, h).where("i = 1 and j = 0").collect()} == {1}


def test_copies_of_2d_meet_as_planned(spark):
    for si, sj, rho, naive in ((4, 4, 3, False), (3, 5, 2, False), (5, 3, 2, False), (3, 5, 2, True), (4, 4, 1, True)):
        g = Grid2D(si, sj, rho, naive)
        a, b = spark.range(si).select(F.col("id").cast("int").alias("i")), spark.range(sj).select(F.col("id").cast("int").alias("j"))
        seen = []
        for r in range(g.rounds):
            met = {tuple(x) for x in g.copies_of_a(a, r).join(g.copies_of_b(b, r), ["i", "j"]).select("i", "j").collect()}
            assert met == {tuple(x) for x in g.products(spark, r).collect()}
            seen += met
        assert sorted(seen) == sorted(itertools.product(range(si), range(sj)))


def test_invalid_parameters(spark):
    for make in (lambda: Grid3D(2, 2, 2, 3), lambda: Grid3D(2, 2, 2, 0), lambda: Grid2D(2, 2, 3), lambda: RoundStore(spark, "tape"), lambda: strips(of_array(spark, ints(1, 4, 4)), of_array(spark, ints(1, 4, 4)), 3)):
        with pytest.raises(ValueError):
            make()
    a = to_blocks(of_array(spark, ints(1, 4, 4)), 2, 2)
    with pytest.raises(ValueError):
        multiply_3d(a, to_blocks(of_array(spark, ints(1, 6, 4)), 2, 2))
    with pytest.raises(ValueError):
        multiply_3d(a, a, 1, carry="none")


# ---- dense products


X, Y = ints(1, 10, 10), ints(2, 10, 10)


@pytest.fixture(scope="module")
def blocks(spark):
    return base.pipeline_blocks(of_array(spark, X), of_array(spark, Y), 3)


@pytest.mark.parametrize("options", [{"rho": 1}, {"rho": 3}, {"rho": "max"}, {"rho": 2, "carry": "append"}, {"rho": 2, "carry": "stationary"}, {"rho": 2, "placement": "polynomial"}, {"rho": 1, "elide_identity": True}, {"rho": 2, "tasks": 3}, {"rho": 2, "tasks": 50}])
def test_dense_3d_does_not_depend_on_the_plan(spark, blocks, options):
    assert np.array_equal(array(to_coordinates(multiply_3d(*blocks, **options))), X @ Y)


@pytest.mark.parametrize("mode", ["checkpoint", "persist", "none"])
def test_stores(spark, blocks, mode):
    assert np.array_equal(array(to_coordinates(multiply_3d(*blocks, 3, store=RoundStore(spark, mode)))), X @ Y)


@pytest.mark.parametrize("shape", [(5, 7, 3), (1, 4, 1), (1, 1, 1), (6, 1, 6), (2, 9, 4)])
@pytest.mark.parametrize("rho", [1, "max"])
def test_rectangles(spark, shape, rho):
    n, k, m = shape
    x, y = ints(3, n, k), ints(4, k, m)
    got = multiply_3d(to_blocks(of_array(spark, x), 2, 3), to_blocks(of_array(spark, y), 3, 2), rho)
    assert np.array_equal(array(to_coordinates(got)), x @ y)


@pytest.mark.parametrize("options", [{"rho": 1}, {"rho": 3}, {"rho": "max"}, {"rho": 2, "schedule": "row_major"}])
def test_dense_2d(spark, options):
    a, b = strips(of_array(spark, X), of_array(spark, Y), 20)
    assert np.array_equal(array(to_coordinates(multiply_2d(a, b, **options))), X @ Y)


def test_rectangular_2d(spark):
    x, y = ints(5, 4, 9), ints(6, 9, 13)
    for rho in (1, 4, "max"):
        a, b = to_blocks(of_array(spark, x), 1, 9), to_blocks(of_array(spark, y), 9, 2)
        assert np.array_equal(array(to_coordinates(multiply_2d(a, b, rho))), x @ y)


def test_restart_after_every_round(spark, blocks):
    for stop in range(4):
        store = RoundStore(spark)
        with pytest.raises(Stopped):
            multiply_3d(*blocks, 1, store=store, stop_after=stop)
        before = {r["round"]: r["seconds"] for r in store.manifest().collect()}
        assert set(before) == set(range(stop + 1))
        assert np.array_equal(array(to_coordinates(multiply_3d(*blocks, 1, store=store))), X @ Y)
        after = {r["round"]: r["seconds"] for r in store.manifest().collect()}
        assert set(after) == set(range(5)) and all(after[r] == before[r] for r in before)


def test_restart_of_appended_partials(spark, blocks):
    store = RoundStore(spark)
    with pytest.raises(Stopped):
        multiply_3d(*blocks, 1, "append", store=store, stop_after=1)
    assert np.array_equal(array(to_coordinates(multiply_3d(*blocks, 1, "append", store=store))), X @ Y)


def test_another_plan_is_not_mixed_in(spark, blocks):
    store = RoundStore(spark)
    with pytest.raises(Stopped):
        multiply_3d(*blocks, 1, store=store, stop_after=0)
    with pytest.raises(ValueError):
        multiply_3d(*blocks, 2, store=store)


def test_placed_join_adds_no_exchange(spark, blocks):
    a, b = blocks
    plan = product_round(a.df, b.df, None, grid_of(a, b, 2), 0, 4, PLUS_TIMES, "even")._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange shufflepartitionidpassthrough") == 2 and "hashpartitioning" not in plan and "Broadcast" not in plan


@pytest.mark.parametrize("sr", [MIN_PLUS, MAX_PLUS, MAX_MIN, MAX_TIMES, COUNT])
def test_semirings(spark, sr):
    x, y = abs(ints(7, 5, 6)), abs(ints(8, 6, 4))
    want = np.array([[sr.merge.reduce(sr.pair(x[i], y[:, j])) for j in range(4)] for i in range(5)])
    a, b = of_array(spark, x, sr), of_array(spark, y, sr)
    assert np.array_equal(array(to_coordinates(multiply_3d(to_blocks(a, 2, 2), to_blocks(b, 2, 2), 2))), want)
    assert np.array_equal(array(base.multiply_join(a, b)), want)
    assert np.array_equal(array(multiply_3d_sparse(a, b, 0, 2, side=2)), want)
    assert np.array_equal(array(multiply_3d_sparse(a, b, 0, 2, side=2, encoding="packed")), want)


def test_min_plus_with_infinities(spark):
    inf = float("inf")
    x = np.array([[0.0, 3.0, inf], [inf, 0.0, 1.0], [2.0, inf, 0.0]])
    m = of_array(spark, x, MIN_PLUS, sparse=True)
    want = np.min(x[:, :, None] + x[None], axis=1)
    assert np.array_equal(array(to_coordinates(multiply_3d(to_blocks(m, 2, 2), to_blocks(m, 2, 2), 1))), want)


# ---- sparse products


@pytest.mark.parametrize("encoding", ["long", "packed"])
@pytest.mark.parametrize("rho", [1, 3, "max"])
def test_sparse_3d(spark, encoding, rho):
    x, y = ints(9, 23, 17, 0.15), ints(10, 17, 19, 0.15)
    a, b = of_array(spark, x, sparse=True), of_array(spark, y, sparse=True)
    got = multiply_3d_sparse(a, b, 0, rho, side=5, encoding=encoding)
    reached = {(i, j) for i, j in itertools.product(range(23), range(19)) if ((x[i] != 0) & (y[:, j] != 0)).any()}
    assert {(r["row"], r["col"]) for r in got.df.collect()} == reached  # cells that cancel stay
    assert np.array_equal(array(got), x @ y)


def test_sparse_rounds_reuse_the_placement(spark):
    a = of_array(spark, ints(12, 20, 20, 0.2), sparse=True)
    g = sparse_grid(a, a, 5, 2)
    first = long_round(a, a, None, g, 5, 0, 4)
    held = stored(first, "held")
    for df, exchanges in ((first, 2), (long_round(a, a, held, g, 5, 1, 4), 3)):
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert plan.count("Exchange shufflepartitionidpassthrough") == exchanges and "hashpartitioning" not in plan


def test_sparse_sizes(spark):
    a = gen.er_random(spark, 300, 0.02, 3)
    assert abs(a.df.count() / 90_000 - 0.02) < 0.003
    want = array(a) @ array(a)
    for how in ("er", "er_exact", "flops_upper", "exact", "row_sample", "hll", "kmin", 0.1):
        assert np.array_equal(array(multiply_3d_sparse(a, a, 500, 2, density=how)), want)
    with pytest.warns(UserWarning):
        multiply_3d_sparse(a, a, 500, 2, density="input_only")


def test_empty_matrices(spark):
    e = frame(spark, [], 6, 6)
    assert multiply_3d_sparse(e, e, 0, 2, side=2).df.count() == 0
    assert to_coordinates(multiply_3d(to_blocks(e, 2, 2), to_blocks(e, 2, 2), 2)).df.count() == 0
    assert base.multiply_join(e, e).df.count() == 0
    assert array(e.dense()).shape == (6, 6)


@given(st.lists(st.tuples(st.integers(0, 4), st.integers(0, 4), st.integers(-3, 3)), max_size=25), st.lists(st.tuples(st.integers(0, 4), st.integers(0, 4), st.integers(-3, 3)), max_size=25))
@settings(max_examples=60, deadline=None)
def test_coordinate_kernel(a, b):
    def parts(cells):
        d = {(r, c): float(v) for r, c, v in cells}
        return tuple(np.array(x) for x in ([k[0] for k in d], [k[1] for k in d], list(d.values()))) if d else (np.empty(0, int), np.empty(0, int), np.empty(0))

    def full(p):
        out = np.zeros((5, 5))
        out[p[0].astype(int), p[1].astype(int)] = p[2]
        return out

    x, y = parts(a), parts(b)
    assert np.array_equal(full(coo_product(x, y, PLUS_TIMES, 10**6)), full(x) @ full(y))


def test_or_and_reaches(spark):
    x = (ints(11, 8, 8, 0.3) != 0).astype(float)
    m = of_array(spark, x, OR_AND, sparse=True)
    assert np.array_equal(array(multiply_3d_sparse(m, m, 0, 2, side=3)), ((x @ x) > 0).astype(float))


# ---- estimates


def test_density_estimates(spark):
    a = gen.er_random(spark, 400, 0.01, 5)
    exact = density.profile(a, a, "exact").delta_out
    for how, slack in (("er", 0.1), ("er_exact", 0.1), ("hll", 0.08), ("kmin", 0.12), ("row_sample", 0.25)):
        assert abs(density.profile(a, a, how).delta_out / exact - 1) < slack, how
    assert density.profile(a, a, "flops_upper").delta_out >= exact
    with pytest.raises(ValueError):
        density.profile(a, a, "guess")


# ---- placement and costs


def test_even_placement(spark):
    for q, rho, tasks in ((8, 8, 32), (5, 3, 7), (2, 1, 16)):
        loads = [r["keys"] for r in costs.task_loads(spark, q, rho, tasks, "even").collect()]
        keys = q * q * rho
        assert len(loads) == tasks and sum(loads) == keys and max(loads) <= keys // tasks + keys % tasks + (keys < tasks)
    uneven = [r["keys"] for r in costs.task_loads(spark, 8, 8, 32, "polynomial").collect()]
    assert (min(uneven), max(uneven), uneven.count(0)) == (0, 48, 10)
    row = spark.range(1).select(even_task(F.lit(5).cast("long"), 12, 4).alias("e"), polynomial_task(F.lit(1), F.lit(2), F.lit(3), 7).alias("p")).first()
    assert tuple(row) == (1, (961 + 62 + 3) % 7)


def test_ledger_matches_the_worked_table(spark):
    want = {1: [32, 48, 48, 48, 16], 2: [64, 96, 32], 3: [96, 48, 48], 4: [128, 64]}
    for rho, pairs in want.items():
        got = costs.ledger_3d(spark, (64, 64, 64), 16, rho).groupBy("round").agg(F.sum("pairs").alias("n"), F.sum("words").alias("w")).orderBy("round").collect()
        assert [r["n"] for r in got] == pairs and sum(r["w"] for r in got) == 3 * 64 * 64 * 4
    assert sum(r["pairs"] for r in costs.ledger_2d(spark, 64, 256, 4).collect()) == 512


def test_reducers_hold_three_blocks(spark):
    for rho in (1, 2, 4):
        assert max(r["greatest"] for r in costs.reducer_words_3d(spark, 64, 16, rho).collect()) <= 3 * 16 * 16


def test_naive_schedule_loads_mappers(spark):
    even = {(r["side"], r["least"], r["greatest"]) for r in costs.mapper_copies(spark, 16, 4, False).collect()}
    naive = [r["greatest"] for r in costs.mapper_copies(spark, 16, 4, True).where("side = 'A'").collect()]
    assert even == {("A", 4, 4), ("B", 4, 4)} and max(naive) == 16


def test_permutations(spark):
    for n in (1, 2, 7, 64, 100, 1000):
        for kind in ("affine", "feistel"):
            p = ew.Permutation(n, kind, 42)
            got = spark.range(n).select("id", p.apply(F.col("id")).alias("y")).select("id", "y", p.invert(F.col("y")).alias("back")).collect()
            assert sorted(r["y"] for r in got) == list(range(n)) and all(r["back"] == r["id"] for r in got)
    skew = frame(spark, [(r, c, 1) for r in range(4) for c in range(64)], 64, 64)
    p = ew.Permutation(64, "feistel", 1)
    load = lambda m: max(r["n"] for r in m.df.groupBy(F.floor(F.col("row") / 16)).agg(F.count(F.lit(1)).alias("n")).collect())
    assert load(ew.permute(skew, p, p)) < load(skew)
    assert np.array_equal(array(ew.permute(ew.permute(skew, p, None), p, None, back=True)), array(skew))


def test_formulas():
    assert costs.rounds_3d(64, 16, 2) == 3 and costs.rounds_2d(64, 256, 4) == 4
    assert costs.overhead_per_round(1.14, 4, 1.0) == pytest.approx(0.07) and costs.overhead_per_round(1.0, 2, 1.0) is None
    assert costs.lost_work([2.0, 2.0]) == pytest.approx(1.0)
    assert plan_3d(32_000, 4_000, 8).rounds == 2


def test_planner():
    p = plan(32_000, 3 * 4_000**2, 3 * 4 * 32_000**2, 32)
    assert p.block == 4_000 and p.rho == 4 and p.rounds == 3 and p.reducer_words <= 3 * 4_000**2
    with pytest.raises(ValueError):
        plan(3_540_000, 10**9, 10**12, 1000)
    assert plan(100, 10**9, 10**12, 4).method == "local"
    risky = plan(32_000, 3 * 4_000**2, 3 * 8 * 32_000**2, 32, revocations_per_second=1e-2)
    assert risky.rounds >= plan(32_000, 3 * 4_000**2, 3 * 8 * 32_000**2, 32).rounds


# ---- algebra and rewriting


def test_algebra(spark):
    a, b = of_array(spark, X), of_array(spark, Y)
    x, y = leaf(a), leaf(b)
    assert np.array_equal(array((x @ y).T.lower()), (X @ Y).T)
    assert np.array_equal(array((x.scaled(2) @ y.scaled(3)).lower()), 6 * X @ Y)
    assert np.array_equal(array((x + x).lower()), 2 * X)
    assert np.array_equal(array(x.power(5).lower()), np.linalg.matrix_power(X, 5))
    assert np.array_equal(array((x @ y @ x).rows(2, 5).cols(1, 4).lower())[2:5, 1:4], (X @ Y @ X)[2:5, 1:4])
    assert np.array_equal(array(base.multiply_join(a, gen.identity(spark, 10))), X)
    pattern = of_array(spark, np.eye(10), sparse=True)
    assert np.array_equal(array((x @ y).mask(pattern).lower()), np.diag(np.diag(X @ Y)))
    assert np.array_equal(array((x @ y).lower("3d", block=4, rho=1)), X @ Y)
    assert np.array_equal(array((x @ y).lower("sparse", m=20, rho=2)), X @ Y)
    assert np.array_equal(array(ew.subtract(a, b)), X - Y)
    assert describe(optimize((x.T @ y.T).T)) == "(10x10 @ 10x10)" and (a @ b).lower().df.count() == 100


def test_observed_words_and_round_texts(spark, blocks):
    watch = {}
    multiply_3d(*blocks, 2, watch=watch)
    assert {r: {k: o.get["words"] for k, o in sides.items()} for r, sides in watch.items()} == {0: {"A": 200, "B": 200}, 1: {"A": 200, "B": 200, "C": 200}}
    x = leaf(of_array(spark, X))
    assert (x @ x).explain_rounds(4, 1) == "(10x10 @ 10x10): grid 3x3x3, 4 rounds, at most 388 words a round"
    assert np.array_equal(array(to_coordinates(base.multiply_cogroup(*blocks))), X @ Y)


def test_chain_order(spark):
    wide, tall = of_array(spark, ints(1, 2, 40)), of_array(spark, ints(2, 40, 2))
    e = leaf(tall) @ leaf(wide) @ leaf(tall)
    assert describe(optimize(e)) == "(40x2 @ (2x40 @ 40x2))"


def test_slices_reach_the_scan(spark, tmp_path):
    gen.write_matrix(of_array(spark, X), str(tmp_path / "x"))
    m = gen.read_matrix(spark, str(tmp_path / "x"), "parquet", 10, 10)
    text = (leaf(m) @ leaf(m)).rows(0, 3).cols(2, 4).lower().df._jdf.queryExecution().executedPlan().toString()
    assert "LessThan(row,3)" in text and "GreaterThanOrEqual(col,2)" in text


def test_cleaning_and_elements(spark):
    m = frame(spark, [(0, 0, 1), (0, 1, 5), (1, 1, 0)], 2, 2)
    dirty = MatrixFrame(m.df.unionAll(spark.createDataFrame([(1, 0, None)], "row long, col long, val double")), 2, 2)
    assert ew.clean(dirty).df.where("val = 0").count() == 2 and ew.clean(dirty, "drop").df.count() == 3
    assert ew.prune(m).df.count() == 2
    assert [r["val"] for r in ew.top_per_row(m, 1).orderBy("row").collect()] == [5.0, 0.0]
    t = ew.table_permutation(spark.range(9).select(F.col("id").alias("x")), 3).collect()
    assert sorted(r["y"] for r in t) == list(range(9))
    twice = matrix_from(spark.createDataFrame([(0, 0, 2.0), (0, 0, 3.0), (None, 0, 1.0)], "r long, c long, v double"), F.col("r"), F.col("c"), F.col("v"), 1, 1)
    assert array(twice).tolist() == [[5.0]]


# ---- sources


def test_sources(spark, tmp_path):
    gen.register_sources(spark)
    got = spark.read.format("signed_matrix").option("n", 9).option("parts", 4).load()
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, gen.signed(spark, 9).df.collect()))
    m = of_array(spark, X)
    for fmt in ("parquet", "orc", "json", "csv"):
        gen.write_matrix(m, str(tmp_path / fmt), fmt)
        assert np.array_equal(array(gen.read_matrix(spark, str(tmp_path / fmt), fmt, 10, 10)), X)
    (tmp_path / "m.mtx").write_text("%%MatrixMarket matrix coordinate real general\n% note\n3 3 2\n1 1 2.5\n3 2 -1\n")
    assert array(gen.read_matrix(spark, str(tmp_path / "m.mtx"), "mtx", 3, 3)).tolist() == [[2.5, 0, 0], [0, 0, 0], [0, -1.0, 0]]
    (tmp_path / "n.mtx").write_text("% a cell that reads as the size line does\n3 3 1\n3 3 1\n")
    assert array(gen.read_matrix(spark, str(tmp_path / "n.mtx"), "mtx", 3, 3)).tolist() == [[0, 0, 0], [0, 0, 0], [0, 0, 1.0]]
    assert set(SEMIRINGS) >= {"plus_times", "min_plus"} and sparse_grid(m, m, 3, 9).rho == 4
    assert gen.dense_random(spark, 3, 4).df.count() == 12 and gen.diagonal(spark.createDataFrame([(0, 2.0)], "idx long, val double"), 2).df.count() == 1


# ---- stores and inputs


@pytest.mark.parametrize("kind", ["3d", "stationary", "2d", "long", "packed", "append"])
def test_a_store_with_other_data_raises(spark, kind):
    """Same shapes, same options, other numbers: the rounds of one product must not be read as those of another."""
    x, y = ints(21, 6, 6), ints(22, 6, 6)
    run = {
        "3d": lambda a, b, **o: multiply_3d(to_blocks(a, 2, 2, full=True), to_blocks(b, 2, 2, full=True), 1, **o),
        "stationary": lambda a, b, **o: multiply_3d(to_blocks(a, 2, 2, full=True), to_blocks(b, 2, 2, full=True), 1, "stationary", **o),
        "2d": lambda a, b, **o: multiply_2d(*strips(a, b, 12), 1, **o),
        "long": lambda a, b, **o: multiply_3d_sparse(a, b, 0, 1, side=2, encoding="long", **o),
        "packed": lambda a, b, **o: multiply_3d_sparse(a, b, 0, 1, side=2, **o),
        "append": lambda a, b, **o: multiply_3d_sparse(a, b, 0, 1, side=2, carry="append", **o),
    }[kind]
    cells = lambda c: array(c if isinstance(c, MatrixFrame) else to_coordinates(c))
    store = RoundStore(spark)
    with pytest.raises(Stopped):
        run(of_array(spark, x), of_array(spark, y), store=store, stop_after=0)
    assert np.array_equal(cells(run(of_array(spark, x), of_array(spark, y), store=RoundStore(spark, path=store.path))), x @ y)
    with pytest.raises(ValueError, match="other data"):
        run(of_array(spark, x), of_array(spark, 2 * y), store=RoundStore(spark, path=store.path))


def test_random_matrices_have_their_density(spark):
    m = gen.er_random(spark, 500, 0.02, 3)
    n = m.df.count()
    assert n == m.df.distinct().count() and abs(n - 5000) < 4 * (5000 * 0.98) ** 0.5
    assert {r.row for r in m.df.select("row").distinct().collect()} <= set(range(500)) and m.df.agg(F.max("col")).first()[0] < 500
    again = gen.er_random(spark, 500, 0.02, 3).df.repartition(3)
    assert again.exceptAll(m.df).count() == 0


def test_ranks_without_one_task(spark):
    df = spark.range(1000).select((F.col("id") * 7919 % 1000).alias("x"), F.lit("a").alias("idx"))
    got = ew.global_rank(df.repartition(7), [F.desc("x")], "at").collect()
    assert all(r["at"] == 999 - r["x"] for r in got) and len(got) == 1000
    plan = ew.global_rank(df, [F.col("x")], "at")._jdf.queryExecution().executedPlan().toString()
    assert "_part" in plan and ew.global_rank(df.limit(0), [F.col("x")], "at").count() == 0


def test_full_blocks_are_multiplied_in_bounded_memory():
    """Many products a cell: no array of all elementary products is made, whatever the values."""
    import tracemalloc

    from roundmm.functions.semiring import MIN_PLUS, OR_AND

    rng = np.random.default_rng(3)

    def block(share: float, values: np.ndarray) -> tuple:
        r, c = np.nonzero(rng.random((300, 300)) < share)
        return r + 600, c + 600, rng.choice(values, len(r))

    def full(x: tuple, zero: float) -> np.ndarray:
        out = np.full((300, 300), zero)
        out[x[0] - 600, x[1] - 600] = x[2]
        return out

    for semiring, values in ((PLUS_TIMES, np.array([1.0, -1.0])), (PLUS_TIMES, np.array([1.0, 2.0])), (OR_AND, np.array([1.0])), (MIN_PLUS, np.array([3.0, 5.0]))):
        x, y, more = block(0.5, values), block(0.5, values), block(0.01, values)
        tracemalloc.start()
        got = coo_product(x, y, semiring, 300 * 300, more)
        assert tracemalloc.get_traced_memory()[1] < 150 << 20
        tracemalloc.stop()
        want = semiring.merge(semiring.product(full(x, semiring.zero), full(y, semiring.zero)), full(more, semiring.zero))
        assert len(got[0]) == 300 * 300 and np.array_equal(full(got, semiring.zero), want)


def test_cells_by_bits_equal_cells_by_join(spark):
    """Also with several panels of columns, empty rows, and no entries at all."""
    a = gen.er_random(spark, 300, 0.05, 3)
    for width in (64, 128, 320):
        assert density.united_rows(a, a.T, width).first()[0] == density.joined_cells(a, a.T).first()[0] > 0
    assert density.united_rows(a.where("false"), a, 64).first()[0] == 0
    plan = density.exact_cells(a, a)._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and "MapInArrow" in plan


def test_chunks_give_back_their_cells():
    """Whatever the values and distances; few bytes where the cells are close and the values are small counts."""
    from roundmm.operators.chunks import decoded, encoded

    rng = np.random.default_rng(5)
    for top in (300, 10**5, 10**12):
        key = np.unique(rng.integers(0, top, 200))
        for v in (np.ones(len(key)), rng.integers(0, 1000, len(key)) * 1.0, rng.integers(-3, 3, len(key)) * 1.0, rng.random(len(key)), np.where(key % 2, np.inf, 7.0), np.where(key % 2, np.nan, 0.0), np.where(key % 2, -0.0, 0.0)):
            k, w = decoded(encoded(key, v))
            assert np.array_equal(k, key) and np.array_equal(v.view(np.int64), w.view(np.int64))
    assert len(encoded(np.arange(10**5), np.arange(10**5) % 200 * 1.0)) < 250_000


@pytest.mark.parametrize("encoding", ["long", "packed"])
def test_partial_sums_travel_in_bounded_rows(spark, monkeypatch, encoding):
    """A block of C is many rows, also where entries as rows were asked for and elementary products are many."""
    from roundmm.operators import chunks

    monkeypatch.setattr(chunks, "CHUNK", 256)
    rng = np.random.default_rng(6)
    x = (rng.random((64, 64)) < 0.6) * rng.integers(1, 9, (64, 64)) * 1.0
    a, store, watch = of_array(spark, x, sparse=True), RoundStore(spark), {}
    got = multiply_3d_sparse(a, a, 0, 2, side=32, encoding=encoding, store=store, watch=watch)
    assert np.array_equal(array(got), x @ x)
    held = spark.read.parquet(f"{store.path}/round=0")
    assert held.agg(F.max("n")).first()[0] <= 256 and held.agg(F.sum("n")).first()[0] >= 64 * 64
    assert watch[0]["A"].get["words"] == 2 * a.df.count()


def test_sketches_are_united_where_they_are_held(spark, monkeypatch):
    """Also with several panels of inner coordinates: no join makes an entry carry a sketch, and the estimate is near the cells."""
    a = gen.er_random(spark, 300, 0.05, 3)
    exact = density.joined_cells(a, a).first()[0]
    for held in (64, 1 << 14):
        monkeypatch.setattr(density, "HELD", held)
        df = density.sketched(a, a)
        assert abs(df.first()[0] / exact - 1) < 0.05
        assert "Join" not in df._jdf.queryExecution().optimizedPlan().toString()
    assert density.sketched(a.where("false"), a).first()[0] == 0
    rng = np.random.default_rng(8)
    for n in (1, 10, 1000, 100_000):
        assert abs(density.sketch_estimate(density.sketch(rng.integers(-(1 << 63), 1 << 63, n))) / n - 1) < 0.06


def test_a_mask_on_many_products_joins_no_entries(spark, monkeypatch):
    rng = np.random.default_rng(9)
    x, p = (rng.random((80, 80)) < 0.7) * 1.0, (rng.random((80, 80)) < 0.2) * 1.0
    a = of_array(spark, x, sparse=True)
    got = ew.masked_product(a, a, of_array(spark, p, sparse=True))
    assert np.array_equal(array(got), (x @ x) * p)
    plan = got.df._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Join") == 1 and "Aggregate" not in plan.split("Join")[0]


@pytest.mark.parametrize("q", [3, 4])
def test_several_ledgers_share_a_pass_over_the_products(spark, q):
    """Cells by slot and the first round that reaches them, of blocks in several strips, without rows for elementary products."""
    from roundmm.operators.chunks import Shape, packed_chunks, reached_counts

    rng = np.random.default_rng(10)
    n, side = 40, -(-40 // q)
    x = rng.random((n, n)) < 0.08
    a = of_array(spark, x * 1.0, sparse=True)
    packs = packed_chunks(a, Shape(side, 4))
    got = {tuple(r)[:5]: r.n for r in reached_counts(packs, packs, [sparse_grid(a, a, side, rho) for rho in (1, 2, q)], Shape(side, 4), 3).collect()}
    want: dict = {}
    for rho in (1, 2, q):
        first: dict = {}
        for r, k, c in itertools.product(range(n), repeat=3):
            if x[r, k] and x[k, c]:
                g = (k // side - r // side - c // side) % q
                at = (rho, r // side, c // side, g % rho, r, c)
                first[at] = min(first.get(at, q), g // rho)
        for at, since in first.items():
            want[(*at[:4], since)] = want.get((*at[:4], since), 0) + 1
    assert {k: v for k, v in got.items() if v} == want


@pytest.mark.parametrize("carry, rho, sr", [("accumulate", 3, PLUS_TIMES), ("append", 1, MIN_PLUS)])
def test_light_rounds_share_a_shuffle(spark, monkeypatch, carry, rho, sr):
    """Many rounds of small blocks go in few passes; a store, which shows single rounds, keeps them."""
    from roundmm.operators import sparse3d

    x, y = ints(13, 23, 70, 0.1), ints(14, 70, 19, 0.1)
    x[:10, 35:], y[:35, 9:] = 0, 0  # blocks that meet none
    a, b = of_array(spark, np.where(x != 0, x, sr.zero), sr, sparse=True), of_array(spark, np.where(y != 0, y, sr.zero), sr, sparse=True)
    want = {(r["row"], r["col"]): r["val"] for r in base.multiply_join(a, b).df.collect()}
    grid = sparse_grid(a, b, 2, rho)
    for light, most in ((1 << 28, 1), (2 * (a.df.count() * grid.qj + b.df.count() * grid.qi) // 5, 4)):
        monkeypatch.setattr(sparse3d, "LIGHT", light)
        run = sparse3d.run_length(grid, a, b, 2)
        assert 1 < run and -(-grid.product_rounds // run) <= most
        got = multiply_3d_sparse(a, b, 0, rho, side=2, encoding="packed", carry=carry).df.collect()
        assert len(got) == len(want) and {(r["row"], r["col"]): r["val"] for r in got} == want
    store = RoundStore(spark)
    multiply_3d_sparse(a, b, 0, rho, side=7, encoding="packed", carry=carry, store=store)
    assert len(store.ledger) == sparse_grid(a, b, 7, rho).product_rounds + (rho > 1 or carry == "append")


def test_sums_multiply_in_parts(monkeypatch):
    from roundmm.operators import chunks

    rng, n = np.random.default_rng(3), 8
    shape = chunks.Shape(n, 3)
    for met in (1, 40, 1 << 19):
        monkeypatch.setattr(chunks, "MET", met)
        total, sums = np.zeros((n, n)), chunks.Sums(shape, PLUS_TIMES)
        for _ in range(6):
            x, y = ((rng.random((n, n)) < 0.5) * rng.integers(1, 9, (n, n)) * 1.0 for _ in range(2))
            total += x @ y
            sums.next_group()
            for kind, m in ((0, y), (1, x)):
                for strip in range(3):
                    r, c = np.nonzero(m[strip * 3 : strip * 3 + 3])
                    if len(r):
                        sums.add(kind, strip, chunks.encoded(r * n + c, m[strip * 3 + r, c]))
        got = np.zeros((n, n))
        for strip, key, val in sums.strips():
            got[strip * 3 + key // n, key % n] = val
        assert np.array_equal(got, total)


def test_strips_of_few_blocks_are_dealt_to_many_tasks(spark, monkeypatch):
    """Where blocks and slots are fewer than tasks, also of entries as rows; results are the same."""
    from roundmm.operators import chunks, sparse3d

    monkeypatch.setattr(sparse3d, "CHUNK", 4)
    monkeypatch.setattr(chunks, "CHUNK", 4)
    monkeypatch.setattr(type(spark.sparkContext), "defaultParallelism", 6)
    seen, before = [], sparse3d.product_round
    monkeypatch.setattr(sparse3d, "product_round", lambda *a: seen.append(a[-1]) or before(*a))
    x, y = ints(15, 40, 30, 0.1), ints(16, 30, 20, 0.1)
    got = multiply_3d_sparse(of_array(spark, x, sparse=True), of_array(spark, y, sparse=True), 0, 2, side=20, encoding="long")
    assert np.array_equal(array(got), x @ y) and set(seen) == {3}
    seen.clear()
    got = multiply_3d_sparse(of_array(spark, x, sparse=True), of_array(spark, y, sparse=True), 0, 1, side=40, encoding="long")
    assert np.array_equal(array(got), x @ y) and set(seen) == {12}


@pytest.mark.parametrize("sr, permuted", [(PLUS_TIMES, False), (PLUS_TIMES, True), (MIN_PLUS, False), (OR_AND, True)])
def test_wide_products_are_not_stored(spark, monkeypatch, sr, permuted):
    """Where C has more cells than are kept, no round is stored; results are the same, by dense arrays or not, and with products that cancel."""
    from roundmm.operators import panels, sparse3d

    monkeypatch.setattr(sparse3d, "WIDE", 0)
    x, y = ints(17, 33, 26, 0.3), ints(18, 26, 47, 0.3)
    x[0, :2], y[:2, 0] = (1, 1), (3, -3)
    if sr is OR_AND:
        x, y = (x != 0) * 1, (y != 0) * 1
    a, b = of_array(spark, np.where(x != 0, x, sr.zero), sr, sparse=True), of_array(spark, np.where(y != 0, y, sr.zero), sr, sparse=True)
    want = {(r["row"], r["col"]): r["val"] for r in base.multiply_join(a, b).df.collect()}
    monkeypatch.setattr(sparse3d, "fold_chunks", None)
    monkeypatch.setattr(sparse3d, "product_round", None)
    for held, area, worth in ((1 << 22, 1 << 20, 256), (100, 40, 0), (60, 90, 1 << 20)):
        for k, v in (("HELD", held), ("AREA", area), ("WORTH", worth), ("AT_ONCE", 7), ("CHUNK", 50)):
            monkeypatch.setattr(panels, k, v)
        got = multiply_3d_sparse(a, b, 0, 2, side=5, permuted=permuted).df.collect()
        assert len(got) == len(want) and {(r["row"], r["col"]): r["val"] for r in got} == want


@pytest.mark.parametrize("sr", [PLUS_TIMES, MIN_PLUS, OR_AND])
def test_panels_multiply_by_lists_and_by_arrays(monkeypatch, sr):
    from roundmm.operators import panels
    from roundmm.operators.chunks import encoded

    x, y = ints(19, 9, 14, 0.4) * 1.0, ints(20, 14, 11, 0.4) * 1.0
    x[0, :3], y[:3, 0] = (1, 1, 0), (3, -3, 5)  # a cell whose products cancel
    if sr is OR_AND:
        x, y = (x != 0) * 1.0, (y != 0) * 1.0
    (r, k), (i, j) = np.nonzero(x), np.nonzero(y)
    want = {}
    for p, q in ((p, q) for p in range(len(r)) for q in range(len(i)) if k[p] == i[q]):
        now = sr.pair(x[r[p], k[p]], y[i[q], j[q]])
        want[r[p], j[q]] = sr.merge(want[r[p], j[q]], now) if (r[p], j[q]) in want else now
    for at_once, worth, inner in ((1 << 18, 0, 14), (5, 0, 14), (5, 0, 1 << 20), (5, 1 << 20, 14)):
        monkeypatch.setattr(panels, "AT_ONCE", at_once)
        monkeypatch.setattr(panels, "WORTH", worth)
        panel = panels.Panel(panels.Panels(inner, 9, 11, 6), sr)
        for piece in range(3):
            here = i // 6 == piece
            panel.add(piece, encoded(i[here] % 6 * 11 + j[here], y[i[here], j[here]]))
        val, hit = panel.times(r, k, x[r, k])
        assert {(c // 11, c % 11): val[c] for c in np.flatnonzero(hit)} == want
        assert (panel.full is not None) == (worth > 0 and sr is PLUS_TIMES)


def test_runs_of_rounds_follow_the_copies_that_go(spark, monkeypatch):
    """Blocks on a diagonal meet few others: their rounds share one shuffle, where the count of all copies would allow few."""
    from roundmm.operators import sparse3d

    x = np.kron(np.eye(20, dtype=int), ints(21, 2, 2, 1.0) + 10)
    a = of_array(spark, x, sparse=True)
    grid = sparse_grid(a, a, 2, 1)
    _, left, right = sparse3d.chunked(a, a, 2, 80)
    assert sparse3d.copied(left, right) == 2 * a.df.count()
    monkeypatch.setattr(sparse3d, "LIGHT", 160)
    assert sparse3d.run_length(grid, a, a, 2) == 1 and sparse3d.run_length(grid, a, a, 2, (left, right)) == 20
    assert np.array_equal(array(multiply_3d_sparse(a, a, 0, 1, side=2)), x @ x)


def test_exact_cells_over_a_long_inner_axis(spark, monkeypatch):
    """Neither bits of all inner coordinates nor lists for very many panels."""
    from roundmm.operators import panels

    x, y = ints(22, 30, 50, 0.2), ints(23, 50, 40, 0.2)
    a, b = of_array(spark, x, sparse=True), of_array(spark, y, sparse=True)
    seen, before = [], panels.multiply_panels
    monkeypatch.setattr(panels, "multiply_panels", lambda *x, **o: seen.append(o) or before(*x, **o))
    for listed, bits, times in ((1 << 30, 1 << 28, 0), (10, 1 << 28, 1), (1 << 30, 50, 2)):
        monkeypatch.setattr(density, "LISTED", listed)
        monkeypatch.setattr(density, "PANEL_BITS", bits)
        assert density.exact_cells(a, b).first()[0] == np.count_nonzero((x != 0) @ (y != 0).astype(int))
        assert len(seen) == times


def test_wide_products_of_few_entries_a_panel_go_by_rounds(spark, monkeypatch):
    """Where strips of A would go to more panels than they have products, as of orders' parts, the rounds and slots asked for are kept; a matrix and its transpose are stored once."""
    from roundmm.operators import panels, sparse3d

    x = of_array(spark, np.kron(np.eye(30, dtype=int), ints(22, 2, 3, 1.0) + 10), COUNT, sparse=True)
    x = MatrixFrame(x.df.groupBy("row", "col").agg(F.sum("val").alias("val")), x.n_rows, x.n_cols, COUNT)
    for k, v in (("WIDE", 0), ("multiply_panels", None)):
        monkeypatch.setattr(sparse3d, k, v)
    monkeypatch.setattr(panels, "HELD", 9)
    names, before = [], sparse3d.stored
    monkeypatch.setattr(sparse3d, "stored", lambda df, name: names.append(name) or before(df, name))
    want = array(x).T @ array(x)
    for a, b, c in ((x.T, x, want), (x, x.T, array(x) @ array(x).T)):
        names.clear()
        assert (array(multiply_3d_sparse(a, b, 0, 2, side=23, encoding="packed")) == c).all()
        assert names == ["entries"]
        assert density.products(a, b).first()[0] == density.products(a, MatrixFrame(stored(b.df, "b"), b.n_rows, b.n_cols, COUNT)).first()[0]
