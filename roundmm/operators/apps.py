"""Products on the given tables: graphs, chains, similarities."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from roundmm.functions.semiring import COUNT, MIN_PLUS, OR_AND
from roundmm.model import MatrixFrame, matrix_from
from roundmm.operators import elementwise as ew
from roundmm.operators.baselines import multiply_join
from roundmm.operators.sparse3d import multiply_3d_sparse
from roundmm.plans.rewrite import leaf
from roundmm.scratch import stored
from roundmm.sources.tables import counts, incidence, load, side


def order_part(spark: SparkSession, d: str) -> MatrixFrame:
    li = load(spark, d, "lineitem")
    return incidence(li, "l_orderkey", "l_partkey", side(li, "l_orderkey"), side(li, "l_partkey"))


def rows_without_top(cells: DataFrame) -> DataFrame:
    """``row, col``: the rows of ``cells(row, col)`` without the column that most cells have (ties: the smallest)."""
    top = cells.groupBy("col").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "col").limit(1).select("col")
    rows = cells.select("row").distinct()
    return rows.crossJoin(F.broadcast(top)).join(cells.select("row", "col"), ["row", "col"], "left_anti").select("row", "col")  # one column


def copurchase(spark: SparkSession, d: str, q: int = 4, rho: int = 2) -> MatrixFrame:
    """Parts by parts: orders that hold both."""
    x = order_part(spark, d)
    return multiply_3d_sparse(x.T, x, 0, rho, side=-(-max(x.n_rows, x.n_cols) // q))


def copurchase_edges(spark: SparkSession, d: str) -> MatrixFrame:
    """An edge from the smaller to the larger part where an order holds both."""
    x = order_part(spark, d)
    pairs = x.df.select(F.col("row").alias("o"), F.col("col").alias("row")).join(x.df.select(F.col("row").alias("o"), "col"), "o").where("row < col")
    return MatrixFrame(stored(pairs.select("row", "col").distinct().withColumn("val", F.lit(1.0)), "edges"), x.n_cols, x.n_cols, COUNT)


def triangles(spark: SparkSession, d: str) -> DataFrame:
    """Triangles by their smallest part: the masked square of the oriented graph, summed by row."""
    u = copurchase_edges(spark, d)
    return ew.masked_product(u, u, u).df.groupBy("row").agg(F.sum("val").cast("long").alias("triangles"))


def nation_customer(spark: SparkSession, d: str) -> MatrixFrame:
    c = load(spark, d, "customer")
    return incidence(c, "c_nationkey", "c_custkey", 25, side(c, "c_custkey"))


def customer_order(spark: SparkSession, d: str) -> MatrixFrame:
    o = load(spark, d, "orders")
    return incidence(o, "o_custkey", "o_orderkey", side(o, "o_custkey"), side(o, "o_orderkey"))


def trade_chain(spark: SparkSession, d: str) -> MatrixFrame:
    """Customer nations by supplier nations: line items, as a chain of four matrices in the order that costs least."""
    li, s = load(spark, d, "lineitem"), load(spark, d, "supplier")
    n_order, n_supp, n_cust = side(load(spark, d, "orders"), "o_orderkey"), side(s, "s_suppkey"), side(load(spark, d, "customer"), "c_custkey")
    a, b = nation_customer(spark, d), customer_order(spark, d)
    a, b = MatrixFrame(a.df, 25, n_cust, COUNT), MatrixFrame(b.df, n_cust, n_order, COUNT)
    c = counts(li, "l_orderkey", "l_suppkey", n_order, n_supp)
    e = incidence(s, "s_suppkey", "s_nationkey", n_supp, 25)
    return (leaf(a) @ leaf(b) @ leaf(c) @ leaf(e)).lower()


def region_brand(spark: SparkSession, d: str) -> DataFrame:
    """Regions by brands: line items. ``row`` is the region key, ``col`` the rank of the brand."""
    li, p, n = load(spark, d, "lineitem"), load(spark, d, "part"), load(spark, d, "nation")
    n_order, n_part, n_cust = side(load(spark, d, "orders"), "o_orderkey"), side(p, "p_partkey"), side(load(spark, d, "customer"), "c_custkey")
    brands = ew.axis_index(p, "p_brand")
    n_brand = brands.count()
    rn = incidence(n, "n_regionkey", "n_nationkey", 5, 25)
    nc = MatrixFrame(nation_customer(spark, d).df, 25, n_cust, COUNT)
    co = MatrixFrame(customer_order(spark, d).df, n_cust, n_order, COUNT)
    op = counts(li, "l_orderkey", "l_partkey", n_order, n_part)
    pb = incidence(p.join(F.broadcast(brands), "p_brand"), "p_partkey", "idx", n_part, n_brand)  # an axis of few names
    return (leaf(rn) @ leaf(nc) @ leaf(co) @ leaf(op) @ leaf(pb)).lower().df


def transitions(spark: SparkSession, d: str) -> MatrixFrame:
    """Event types by the user's next event type."""
    ev = load(spark, d, "events")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    pairs = ev.select("event_type", F.lead("event_type").over(w).alias("next")).where(F.col("next").isNotNull()).groupBy("event_type", "next").agg(F.count(F.lit(1)).alias("n"))
    axis = ew.axis_index(ev, "event_type")
    n = axis.count()
    cells = pairs.join(F.broadcast(axis.select("event_type", F.col("idx").alias("row"))), "event_type").join(F.broadcast(axis.select(F.col("event_type").alias("next"), F.col("idx").alias("col"))), "next")
    return matrix_from(cells, F.col("row"), F.col("col"), F.col("n"), n, n, COUNT)


def host_targets(spark: SparkSession, d: str) -> MatrixFrame:
    """Hosts of pages by the targets of their links, ones; both axes are ranks of names."""
    p = load(spark, d, "pages").select(F.regexp_extract("url", "://([^/?#]+)", 1).alias("host"), F.explode(F.expr("regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)")).alias("target"))
    p = stored(p.distinct(), "links")
    hosts, targets = ew.axis_index(p, "host"), ew.axis_index(p, "target")
    cells = p.join(hosts.select("host", F.col("idx").alias("row")), "host").join(targets.select("target", F.col("idx").alias("col")), "target")
    return MatrixFrame(cells.select("row", "col", F.lit(1.0).alias("val")), hosts.count(), targets.count(), OR_AND)


def two_steps(spark: SparkSession, d: str) -> MatrixFrame:
    """Hosts that reach hosts by a shared target."""
    a = host_targets(spark, d)
    return multiply_join(a, a.T)


def cheapest_two_hops(spark: SparkSession, d: str) -> MatrixFrame:
    """Nations by nations: least price in cents of a sale from the one to the other, over one stop."""
    li, o, c, s = (load(spark, d, t) for t in ("lineitem", "orders", "customer", "supplier"))
    sold = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(c, F.col("o_custkey") == F.col("c_custkey")).join(s, F.col("l_suppkey") == F.col("s_suppkey"))
    m = matrix_from(sold, F.col("c_nationkey"), F.col("s_nationkey"), F.round(F.col("l_extendedprice") * 100), 25, 25, MIN_PLUS)
    m = MatrixFrame(stored(m.df, "prices"), 25, 25, MIN_PLUS)
    return multiply_join(m, m)


def tokens(df: DataFrame, key: str, text: str = "text") -> DataFrame:
    return df.select(key, F.explode(F.expr(f"regexp_extract_all(lower({text}), '[a-z]+', 0)")).alias("token"))


def token_overlap(df: DataFrame, row: str, other: DataFrame, col: str) -> DataFrame:
    """``row, col, val``: products of the token counts of ``df(row, token)`` and ``other(col, token)``, over every token.
    The inner index is the token itself, so it needs no dictionary."""
    a = df.groupBy(F.col(row).alias("row"), "token").agg(F.count(F.lit(1)).cast("double").alias("x"))
    b = other.groupBy(F.col(col).alias("col"), "token").agg(F.count(F.lit(1)).cast("double").alias("y"))
    return a.join(b, "token").groupBy("row", "col").agg(F.sum(F.col("x") * F.col("y")).alias("val"))


def source_overlap(spark: SparkSession, d: str) -> DataFrame:
    t = tokens(load(spark, d, "documents"), "source")
    return token_overlap(t, "source", t, "source")


def role_item_overlap(spark: SparkSession, d: str) -> DataFrame:
    return token_overlap(tokens(load(spark, d, "conversations"), "role"), "role", tokens(load(spark, d, "benchmark"), "item_id"), "item_id")


def item_document_overlap(spark: SparkSession, d: str) -> DataFrame:
    """Benchmark items by documents."""
    return token_overlap(tokens(load(spark, d, "benchmark"), "item_id"), "item_id", tokens(load(spark, d, "documents"), "doc_id"), "doc_id")


def quality_by_token(spark: SparkSession, d: str) -> DataFrame:
    """Quality class by every token: ``row, col, val``, ``col`` the token."""
    held = tokens(load(spark, d, "documents"), "doc_id").groupBy("doc_id", "token").agg(F.count(F.lit(1)).cast("double").alias("n"))
    return held.join(load(spark, d, "labels").select("doc_id", F.col("quality").cast("long").alias("row")), "doc_id").groupBy("row", F.col("token").alias("col")).agg(F.sum("n").alias("val"))
