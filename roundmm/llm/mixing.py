"""Poisson replication: repeat each document a Poisson number of times whose mean brings its source to its weight."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from roundmm.llm.common import md5_key, small, unit_hash

#: Exponent of the default target: a source of n rows weighs n**TEMPER.
TEMPER = 0.7


def repetition_rates(docs: DataFrame, weights: dict[str | None, float] | None = None, temper: float = TEMPER, epochs: float = 1.0) -> DataFrame:
    """``source, n_rows, rate``: mean repetitions per row, so that source shares become the target weights.

    ``weights`` names target shares (scaled to sum 1; unnamed sources get 0); without it shares follow
    ``n_rows ** temper``. ``epochs`` is the expected output size over the input size. A null source is one source.
    """
    n = docs.groupBy(F.col("source").cast("string").alias("source")).agg(F.count(F.lit(1)).alias("n_rows"))
    if weights is None:
        share = F.pow(F.col("n_rows"), F.lit(temper))
    else:
        share = F.lit(0.0)
        for name, w in weights.items():
            share = F.when(F.col("source").eqNullSafe(F.lit(name)), F.lit(float(w))).otherwise(share)
    n = n.withColumn("_share", share)
    total = n.agg(F.sum("n_rows").alias("_rows"), F.sum("_share").alias("_shares"))
    return n.crossJoin(F.broadcast(total)).select(  # one row: no growth
        "source", "n_rows", F.when(F.col("_shares") > 0, F.lit(epochs) * F.col("_rows") * F.col("_share") / F.col("_shares") / F.col("n_rows")).otherwise(0.0).alias("rate")
    )


def poisson_steps(rates: DataFrame) -> DataFrame:
    """Add ``steps``: the Poisson distribution function at 0, 1, ... up to where its tail is below 1e-16.

    Terms are taken in logarithms, so large rates don't underflow; the list grows with the rate, not with rows.
    """
    top = F.ceil(F.col("rate") + 9 * F.sqrt("rate") + 25).cast("int")
    each = rates.select("source", "n_rows", "rate", F.explode(F.sequence(F.lit(0), top)).alias("k"))
    upto = Window.partitionBy("source").orderBy("k")
    each = each.withColumn("_log", F.sum(F.when(F.col("k") > 0, F.ln("k")).otherwise(0.0)).over(upto))
    term = F.when(F.col("rate") > 0, F.exp(F.col("k") * F.ln("rate") - F.col("rate") - F.col("_log"))).otherwise(F.when(F.col("k") == 0, 1.0).otherwise(0.0))
    each = each.withColumn("_f", F.sum(term).over(upto))
    return each.groupBy("source", "n_rows", "rate").agg(F.transform(F.array_sort(F.collect_list(F.struct("k", "_f"))), lambda x: x["_f"]).alias("steps"))


def repeat_count(u: Column, steps: Column) -> Column:
    """Inverse distribution function: how many steps lie at or below ``u``."""
    return F.size(F.filter(steps, lambda s: s <= u))


def replicated(docs: DataFrame, weights: dict[str | None, float] | None = None, temper: float = TEMPER, epochs: float = 1.0, seed: int = 23, shuffle: bool = True, report: bool = False) -> DataFrame:
    """``docs`` repeated by source, in a global random order, with exactly the columns of ``docs``; with ``report`` the columns
    ``doc_id, source, copy, n_copies, rate, shuffle_key`` instead.

    The count depends on seed, id and text, so it is the same on any partitioning and after any retry. ``shuffle``
    range-partitions rows by a hash key of the copy: a global random order without one sorted task. Rows equal in id and text
    draw the same count. Null ids and texts hash as empty; a null source is one source. An empty table gives no rows.
    Columns of ``docs`` may have any names: they are held under others meanwhile.
    """
    steps = small(poisson_steps(repetition_rates(docs, weights, temper, epochs)).select(F.col("source").alias("_source"), F.col("rate").alias("_rate"), F.col("steps").alias("_steps")))
    own = [F.col(f"`{c}`").alias(f"_own{k}") for k, c in enumerate(docs.columns)]
    # the hash and the draw are columns below the join, so the lambda over the steps doesn't compute them again for each step
    base = docs.select(*own, F.col("doc_id").alias("_id"), F.col("source").cast("string").alias("_name"), F.md5(F.coalesce(F.col("text"), F.lit("")).cast("binary")).alias("_text"))
    base = base.withColumn("_u", unit_hash(F.col("_id"), F.col("_text"), seed=seed))
    drawn = base.join(steps, F.col("_name").eqNullSafe(F.col("_source"))).withColumn("_n", repeat_count(F.col("_u"), F.col("_steps")))
    out = drawn.where("_n > 0").withColumn("_copy", F.explode(F.sequence(F.lit(0), F.col("_n") - 1)))
    out = out.withColumn("_key", md5_key(F.col("_id"), F.col("_text"), F.col("_copy"), seed=seed + 1))
    if shuffle:
        out = out.repartitionByRange("_key").sortWithinPartitions("_key")
    if report:
        return out.select(F.col("_id").alias("doc_id"), F.col("_name").alias("source"), F.col("_copy").alias("copy"), F.col("_n").alias("n_copies"), F.col("_rate").alias("rate"), F.col("_key").alias("shuffle_key"))
    return out.select(*[F.col(f"_own{k}").alias(c) for k, c in enumerate(docs.columns)])
