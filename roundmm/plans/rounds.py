"""Committing rounds, and going on from the last committed one."""

from __future__ import annotations

import functools
import hashlib
import json
import time
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from roundmm.scratch import fresh_path, path_exists, read_texts, remove, write_text

MANIFEST = (
    "job string, plan_hash string, round int, slots int, status string, seconds double, path string"
)
STORES = ("parquet", "checkpoint", "persist", "none")


class Stopped(RuntimeError):
    """Raised by a driver that was told to stop after a round, in tests of restarts."""


def plan_hash(**parts: object) -> str:
    """A digest of what a product's rounds depend on: shapes, options, and the fingerprints of its inputs."""
    return hashlib.sha256(json.dumps(parts, sort_keys=True, default=str).encode()).hexdigest()[:16]


def fingerprint(df: DataFrame) -> str:
    """Names the rows of a frame, in any order and from any files: their number, and two order-free sums over 64-bit hashes of whole rows. One scan."""
    row = F.xxhash64(*[F.col(f"`{c}`") for c in df.columns])
    again = F.xxhash64(row, F.lit(41))
    low = lambda h: F.sum(h.bitwiseAND((1 << 32) - 1))
    n, a, b, x = df.agg(F.count(F.lit(1)), low(row), low(again), F.bit_xor(again)).first()
    return plan_hash(n=n, a=a, b=b, x=x)


@contextmanager
def small_batches(spark: SparkSession, block_bytes: int, limit: int = 64 << 20) -> Iterator[None]:
    """Arrow batches of so few rows that three blocks a row stay within ``limit`` bytes."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(key)
    spark.conf.set(key, str(max(1, min(int(before), limit // max(3 * block_bytes, 1)))))
    try:
        yield
    finally:
        spark.conf.set(key, before)


@dataclass
class RoundStore:
    """Where a round's output goes.

    ``parquet``: files and a manifest; a round counts once its manifest row is there, so a broken round is written again.
    ``checkpoint``: Spark's reliable checkpoint. ``persist``: executors' memory and disk, recomputed if lost.
    ``none``: nothing is kept, all rounds are one lazy plan.
    """

    spark: SparkSession
    mode: str = "parquet"
    path: str | None = None
    ledger: list[dict] = field(default_factory=list)

    def __post_init__(self):
        if self.mode not in STORES:
            raise ValueError(f"store must be one of {STORES}")
        if self.mode == "parquet" and self.path is None:
            self.path = fresh_path(self.spark, "rounds")

    def committed(self, digest: str) -> dict[int, str]:
        """Paths of committed rounds, of stores that outlive the driver. A manifest of another plan, or of the same plan on other data, raises."""
        if self.mode != "parquet":
            return {}
        rows = [r for r in self._rows() if r["status"] == "committed"]
        if any(r["plan_hash"] != digest for r in rows):
            raise ValueError("the store holds rounds of another plan or of other data")
        return {r["round"]: r["path"] for r in rows}

    def _rows(self) -> list[dict]:
        """Manifest rows, one small file each; no Spark job."""
        if self.mode != "parquet":
            return self.ledger
        return sorted((json.loads(t) for t in read_texts(self.spark, f"{self.path}/manifest", ".json")), key=lambda r: r["round"])

    def manifest(self) -> DataFrame:
        return self.spark.createDataFrame([tuple(x[c.split()[0]] for c in MANIFEST.split(", ")) for x in self._rows()], MANIFEST)

    def commit(self, job: str, digest: str, r: int, slots: int, df: DataFrame, save: Callable[[DataFrame, str], None] | None = None) -> DataFrame:
        """``save`` writes the rows to a folder in another layout than plain files; the manifest row comes after it as well."""
        began = time.time()
        where = ""
        if self.mode == "parquet":
            where = f"{self.path}/round={r}"
            if path_exists(self.spark, where):
                remove(self.spark, where)
            if save is None:
                df.write.parquet(where)
            else:
                save(df, where)
            out = self.spark.read.schema(df.schema).parquet(where)
        elif self.mode == "checkpoint":
            if self.spark.conf.get("spark.checkpoint.dir", None) is None:
                self.spark.sparkContext.setCheckpointDir(fresh_path(self.spark, "checkpoint"))
            out = df.checkpoint()
        elif self.mode == "persist":
            out = df.persist()
            out.count()
        else:
            out = df
        row = {"job": job, "plan_hash": digest, "round": r, "slots": slots, "status": "committed", "seconds": time.time() - began, "path": where}
        self.ledger.append(row)
        if self.mode == "parquet":
            write_text(self.spark, f"{self.path}/manifest/round-{r}.json", json.dumps(row))
        return out


@dataclass
class RoundDriver:
    """Runs rounds in order. ``step(r, before)`` gives round r's output from the round before."""

    store: RoundStore
    job: str
    digest: str
    block_bytes: int = 1

    def run(self, rounds: int, slots: Callable[[int], int], step: Callable[[int, DataFrame | None], DataFrame], resume: bool = True, stop_after: int | None = None, save: Callable[[int, DataFrame, str], None] | None = None) -> list[DataFrame]:
        """Outputs of all rounds; those committed before aren't run again. ``stop_after`` raises after that round."""
        spark, done = self.store.spark, self.store.committed(self.digest) if resume else {}
        out: list[DataFrame] = []
        for r in range(rounds):
            if r in done and all(k in done for k in range(r)):
                out.append(spark.read.parquet(done[r]))
                continue
            with small_batches(spark, self.block_bytes):
                out.append(self.store.commit(self.job, self.digest, r, slots(r), step(r, out[-1] if out else None), save and functools.partial(save, r)))
            if stop_after == r:
                raise Stopped(f"stopped after round {r}")
        return out


def seconds_by_round(store: RoundStore) -> DataFrame:
    return store.manifest().select("round", "slots", F.col("seconds")).orderBy("round")
