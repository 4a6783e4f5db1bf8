"""Which reduce task a key goes to, as column expressions for ``repartitionById``."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def rank_3d(i: Column, j: Column, slot: Column, qj: int, rho: int) -> Column:
    """Rank of a key of a round, in ``[0, rho * qi * qj)``: the same in every round, so partial sums can stay put."""
    return ((i * qj + j) * rho + slot).cast("long")


def rank_2d(i: Column, j: Column, r: int, rho: int, s: int) -> Column:
    return (i * rho + F.pmod(j - i - F.lit(r * rho), F.lit(s))).cast("long")


def even_task(rank: Column, keys: int, tasks: int, seed: int = 17) -> Column:
    """Equal runs of ranks; the few keys that are left over go to tasks by a hash, the same after a retry."""
    run = keys // tasks
    if run == 0:
        return F.pmod(rank, F.lit(tasks)).cast("int")
    rest = F.pmod(F.xxhash64(rank, F.lit(seed)), F.lit(tasks))
    return F.when(rank < run * tasks, F.floor(rank / F.lit(run))).otherwise(rest).cast("int")


def polynomial_task(k1: Column, k2: Column, k3: Column, tasks: int) -> Column:
    """The usual hash of a triple of integers, modulo the tasks (wrapping at 32 bits isn't reached here)."""
    return F.pmod((k1 * 31 + k2) * 31 + k3, F.lit(tasks)).cast("int")
