"""Quality classifier: n-gram indicators scaled by class log-count ratios, then a linear hinge-loss model.

The ratios of a naive Bayes model scale the features; dual coordinate descent fits the hinge loss; a logistic
curve over the margins of held-back training rows turns margins into scores. Labels are learned from a bounded sample
(``TRAIN_ROWS``, the first by hash); every document is scored over its whole text, in Arrow batches, with a model of fixed size.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from roundmm.llm.common import drop_stored, empty_text, md5_key, sliced, stored
from roundmm.llm.textnum import joined, mix, powers, slices, words

#: Most labelled rows that a model is fitted on.
TRAIN_ROWS = 12_000
#: Most bytes of features (four a feature) that the driver gathers for it.
TRAIN_BYTES = 128 << 20
BITS = 18
#: Byte classes whose order makes up a word's shape: lower case and beyond ASCII, upper case, digit, and each sign by itself.
SHAPE = np.arange(256, dtype=np.uint8)
SHAPE[97:123] = SHAPE[128:] = 1
SHAPE[65:91] = 2
SHAPE[48:58] = 3


def features(texts: list[bytes], bits: int = BITS) -> list[np.ndarray]:
    """Distinct hashed features of each text: words, word pairs, shapes, shape pairs and shape triples."""
    out = []
    salt = mix(np.arange(1, 6, dtype=np.uint64))
    down = np.uint64(64 - bits)
    for lo, hi in slices(texts):
        raw, begins = joined(texts[lo:hi])
        lower = np.where((raw >= 65) & (raw <= 90), raw + 32, raw).astype(np.uint8)
        starts, ends, word = words(lower)
        if not len(starts):
            out += [np.empty(0, np.int64)] * (hi - lo)
            continue
        kind = SHAPE[raw]
        first = np.zeros(len(raw) + 1, bool)
        first[starts] = True
        first[ends] = True
        change = np.empty(len(raw), bool)
        change[0] = True
        change[1:] = kind[1:] != kind[:-1]
        inside = np.cumsum(np.bincount(starts, minlength=len(raw) + 1)[: len(raw)] - np.bincount(ends, minlength=len(raw) + 1)[: len(raw)]) > 0
        kept = np.flatnonzero((change | first[:-1]) & inside)
        lead = np.searchsorted(kept, starts)
        place = np.arange(len(kept)) - np.repeat(lead, np.diff(np.append(lead, len(kept))))
        shape = mix(np.add.reduceat((kind[kept].astype(np.uint64) + np.uint64(1)) * powers(int(place.max()) + 1)[place], lead))
        cut = np.searchsorted(starts, begins)
        singles = [mix(word ^ salt[0]) >> down, mix(shape ^ salt[2]) >> down]
        pairs = [mix(word[:-1] * salt[1] + word[1:]) >> down, mix(shape[:-1] * salt[3] + shape[1:]) >> down]
        triples = [mix((shape[:-2] * salt[4] + shape[1:-1]) * salt[3] + shape[2:]) >> down]
        for i in range(hi - lo):
            a, b = int(cut[i]), int(cut[i + 1])
            own = [x[a:b] for x in singles] + [x[a : max(a, b - 1)] for x in pairs] + [x[a : max(a, b - 2)] for x in triples]
            out.append(np.unique(np.concatenate(own)).astype(np.int64))
    return out


@dataclass(frozen=True)
class Model:
    weight: np.ndarray
    bias: float
    slope: float
    offset: float

    def score(self, found: np.ndarray) -> float:
        norm = max(len(found), 1) ** 0.5
        margin = float(self.weight[found].sum()) / norm + self.bias
        return 1.0 / (1.0 + np.exp(-np.clip(self.slope * margin + self.offset, -30, 30)))


def log_count_ratio(rows: list[np.ndarray], y: np.ndarray, size: int, alpha: float = 1.0) -> np.ndarray:
    good, bad = np.full(size, alpha), np.full(size, alpha)
    for found, label in zip(rows, y, strict=True):
        (good if label else bad)[found] += 1
    return np.log(good / good.sum()) - np.log(bad / bad.sum())


def hinge_descent(rows: list[np.ndarray], y: np.ndarray, ratio: np.ndarray, c: float = 1.0, rounds: int = 12, seed: int = 3) -> tuple[np.ndarray, float]:
    """Dual coordinate descent for the L1 hinge loss with a bias feature; returns weights over the raw indicators."""
    w, b, alpha = np.zeros_like(ratio), 0.0, np.zeros(len(rows))
    norm = [1 / max(len(r), 1) ** 0.5 for r in rows]
    square = np.array([float(ratio[r] @ ratio[r]) * k * k + 1.0 for r, k in zip(rows, norm, strict=True)])
    rng = np.random.default_rng(seed)
    for _ in range(rounds):
        for i in rng.permutation(len(rows)):
            scaled = ratio[rows[i]] * norm[i]  # made anew: held for all rows it would fill the driver's memory
            slope = y[i] * (float(w[rows[i]] @ scaled) + b) - 1.0
            new = min(max(alpha[i] - slope / square[i], 0.0), c)
            step = (new - alpha[i]) * y[i]
            if step:
                w[rows[i]] += step * scaled
                b += step
                alpha[i] = new
    return w * ratio, b


def platt(margin: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and offset of a logistic curve, by damped Newton steps with smoothed targets."""
    n1, n0 = float((y > 0).sum()), float((y <= 0).sum())
    target = np.where(y > 0, (n1 + 1) / (n1 + 2), 1 / (n0 + 2))
    a, b = 1.0, 0.0
    for _ in range(60):
        p = 1 / (1 + np.exp(-np.clip(a * margin + b, -30, 30)))
        g = np.array([((p - target) * margin).sum() + 1e-3 * (a - 1), (p - target).sum()])
        v = p * (1 - p)
        h = np.array([[(v * margin * margin).sum() + 1e-3, (v * margin).sum()], [(v * margin).sum(), v.sum() + 1e-6]])
        step = np.linalg.solve(h, g)
        step *= min(1.0, 2.0 / max(abs(step).max(), 1e-12))
        a, b = a - step[0], b - step[1]
        if abs(step).max() < 1e-7:
            break
    return max(a, 1e-3), b


def fitted(rows: list[np.ndarray], y: np.ndarray, bits: int = BITS) -> Model:
    """The model of labelled rows. With one class only, or none, the score is that class's smoothed share."""
    if len(rows) < 10 or len(set(y.tolist())) < 2:
        p = (float((y > 0).sum()) + 1) / (len(y) + 2)
        return Model(np.zeros(1 << bits, np.float32), 0.0, 1.0, float(np.log(p / (1 - p))))
    aside = np.arange(len(rows)) % 5 == 4
    part = [r for r, x in zip(rows, aside, strict=True) if not x]
    ratio = log_count_ratio(part, y[~aside] > 0, 1 << bits)
    w, b = hinge_descent(part, y[~aside], ratio)
    model = Model(w.astype(np.float32), b, 1.0, 0.0)
    held = [i for i in range(len(rows)) if aside[i]]
    margin = np.array([float(w[rows[i]].sum()) / max(len(rows[i]), 1) ** 0.5 + b for i in held])
    return Model(model.weight, b, *platt(margin, y[held]))


def sample_for_training(docs: DataFrame, labels: DataFrame, label: str, usable: Column, limit: int = TRAIN_ROWS, seed: int = 5) -> DataFrame:
    """``doc_id, text, label``: at most ``limit`` labelled documents, the first by a hash of the id, each once; rows without a label are left out. Of rows that share a
    sampled id the one with the least md5 of its text counts (equal rows are one), found by partial aggregation, so that a frequent id gathers nowhere.
    Null ids have no label. Extra columns of either table are ignored; empty tables give no rows."""
    marked = labels.select(F.col("doc_id").alias("_id"), F.col(label).cast("int").alias("label")).where(f"{label} is not null").where(usable)
    marked = marked.groupBy("_id").agg(F.max("label").alias("label")).orderBy(md5_key(F.col("_id"), seed=seed), "_id").limit(limit)
    met = docs.select("doc_id", "text").join(F.broadcast(marked), F.col("doc_id") == F.col("_id"))  # at most limit rows
    one = met.groupBy("doc_id", "label").agg(F.min(F.struct(F.md5(empty_text().cast("binary")).alias("_m"), "text")).alias("_t"))
    return one.select("doc_id", F.col("_t.text").alias("text"), "label")


def train(docs: DataFrame, labels: DataFrame, usable: Column, limit: int = TRAIN_ROWS, label: str = "quality") -> Model:
    """Fit on the sample; only hashed features (not texts) reach the driver, at most ``TRAIN_BYTES`` of them: the documents are taken in the order of
    the hash as long as they fit, one that doesn't fit is left out. Null texts count as empty, extra columns are ignored, and without labels of both kinds the score
    is the smoothed share."""

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in sliced(batches):
            found = features([x.as_py().encode() if x.is_valid else b"" for x in batch["text"]])
            yield pa.RecordBatch.from_arrays(
                [batch["doc_id"], batch["label"], pa.array([f.astype("<i4").tobytes() for f in found], pa.binary())], names=["doc_id", "label", "found"]
            )

    made = stored(sample_for_training(docs, labels, label, usable, limit).mapInArrow(hashed, "doc_id long, label int, found binary"), "train-features")
    taken, left = [], TRAIN_BYTES
    sizes = made.select("doc_id", F.octet_length("found").alias("n")).collect()  # at most limit rows of two numbers
    for r in sorted(sizes, key=lambda r: (r["doc_id"] * 2654435761 % 4294967296, r["doc_id"])):
        if r["n"] <= left:
            taken.append(r["doc_id"])
            left -= r["n"]
    rows = made.collect() if len(taken) == len(sizes) else made.where(F.col("doc_id").isin(taken)).collect()  # at most TRAIN_BYTES
    drop_stored(made)
    rows.sort(key=lambda r: (r["doc_id"] * 2654435761 % 4294967296, r["doc_id"]))
    return fitted([np.frombuffer(r["found"], "<i4") for r in rows], np.array([1.0 if r["label"] else -1.0 for r in rows]))


def score_of(text: Column, model: Model, spark: SparkSession) -> Column:
    sent = spark.sparkContext.broadcast(model)  # fixed size: 2**BITS weights

    @F.arrow_udf("double")
    def score(parts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        model = sent.value
        for part in parts:
            # in slices: the features of a whole batch would be several times its size
            pieces = (part.slice(at, 256).cast(pa.binary()).to_pylist() for at in range(0, len(part), 256))
            yield pa.array([model.score(f) for texts in pieces for f in features(texts)], pa.float64())

    return score(text)


def scored(docs: DataFrame, model: Model) -> DataFrame:
    """``docs`` with ``score`` in [0, 1] added (a column of that name is replaced). Null texts score as empty ones, very long ones as a whole; repeated rows score
    alike; ids and other columns play no part; an empty table stays empty."""
    return docs.withColumn("score", score_of(empty_text(), model, docs.sparkSession))


def keep_good(docs: DataFrame, labels: DataFrame, usable: Column, threshold: float = 0.3) -> DataFrame:
    """The rows of ``docs`` that score at least ``threshold``, with the columns of ``docs``; a filter in the scan. Null and empty texts are judged as empty ones,
    repeated rows alike, whatever their ids; an empty table stays empty."""
    model = train(docs, labels, usable)
    return docs.where(score_of(empty_text(), model, docs.sparkSession) >= threshold)
