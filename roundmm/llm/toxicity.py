"""Toxicity of deobfuscated text.

A character trigram model is counted over all texts. Tokens that look disguised (digits or signs among letters, letters
set apart, letters repeated) become character lattices: what each sign may stand for, with a channel cost; a Viterbi search
under the trigram model restores the likeliest letters. Restored texts are searched by an automaton for word beginnings and
words that mark toxic training rows; a logistic curve turns the summed evidence into a score.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from roundmm.llm.common import drop_stored, empty_text, stored
from roundmm.llm.quality import platt, sample_for_training
from roundmm.llm.textnum import shingles

TRAIN_ROWS = 20_000
SYMBOLS = 64
#: A mark must stand out by this much: a likelihood-ratio statistic, and a log ratio of shares.
LEAST_G, LEAST_RATIO, LEAST_ROWS = 30.0, 2.0, 4
MEMO = 100_000

# What a sign may stand for.
STANDS_FOR = {"0": "o", "1": "il", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i", "|": "li", "+": "t", "(": "c", "*": "aeiou"}
APART = ".-_ ,/~'"
SPLIT = re.compile(f"[{re.escape(APART)}]+")
EDGES = ".,;:!?\"'()[]{}%&#*~<>=/\\^`-_…«»¿¡“”‘’"
#: Signs that are punctuation at a token's ends, or letters; both readings are taken.
SIGNS = "".join(c for c in STANDS_FOR if c in EDGES)
PLAIN_EDGES = "".join(c for c in EDGES if c not in STANDS_FOR)
THRICE = re.compile(r"([^\W\d_])\1\1")
REPEATED = re.compile(r"([^\W\d_])\1")


def symbol_table() -> np.ndarray:
    """Code point (beyond the basic plane: 0xFFFF) to symbol: 0 boundary, 1-26 a-z, others by letter class."""
    t = np.zeros(1 << 16, np.uint8)
    for cp in range(1 << 16):
        c = chr(cp)
        if "a" <= c <= "z":
            t[cp] = cp - 96
        elif cp > 127 and c.isalpha():
            t[cp] = 27 + cp % 37
    return t


def trigram_counts(docs: DataFrame) -> DataFrame:
    """``gram, n`` over the whole texts, lower-cased; each task sends one row per trigram that it saw."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t, total = symbol_table(), np.zeros(SYMBOLS**3, np.int64)
        for batch in batches:
            texts, held, size = batch["text"].to_pylist(), [], 0
            for x in [*texts, None]:
                if x is None or size + len(x) > 1 << 20:
                    code = np.frombuffer("  ".join(["", *held, ""]).lower().encode("utf-32-le", "replace"), "<u4")
                    s = t[np.minimum(code, 0xFFFF)].astype(np.int32)
                    # the trigram after a boundary sees two boundaries, as a word's first letter does
                    before = s[1:-1].copy()
                    back = np.where(before == 0, 0, s[:-2])
                    total += np.bincount((back * SYMBOLS + before) * SYMBOLS + s[2:], minlength=SYMBOLS**3)
                    held, size = [], 0
                if x is not None:
                    held.append(x)
                    size += len(x)
        seen = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(seen.astype(np.int32)), pa.array(total[seen])], names=["gram", "n"])

    return docs.select(empty_text().alias("text")).mapInArrow(count, "gram int, n long").groupBy("gram").agg(F.sum("n").alias("n"))


def language_model(docs: DataFrame) -> np.ndarray:
    """Costs (negative logarithms) of a symbol after two others; at most SYMBOLS**3 counts reach the driver."""
    n = np.zeros(SYMBOLS**3)
    for r in trigram_counts(docs).collect():
        n[r["gram"]] = r["n"]
    n = n.reshape(SYMBOLS, SYMBOLS, SYMBOLS)
    single = n.sum((0, 1)) + 0.5
    pair = n.sum(0) + 5 * single / single.sum()
    pair /= pair.sum(1, keepdims=True)
    full = n + 5 * pair[None]
    return -np.log(full / full.sum(2, keepdims=True)).astype(np.float32)


class Restorer:
    """Restores disguised tokens; holds the last decoded tokens, at most ``MEMO``."""

    def __init__(self, costs: np.ndarray):
        self.cost = costs.ravel().tolist()
        self.symbol = symbol_table().tolist()
        self.memo: dict[str, str] = {}

    def of(self, c: str) -> int:
        return self.symbol[min(ord(c), 0xFFFF)]

    def lattice(self, token: str) -> list[list[tuple[str, float]]]:
        out: list[list[tuple[str, float]]] = []
        letters_apart = max(map(len, SPLIT.split(token))) <= 1
        i = 0
        while i < len(token):
            c, j = token[i], i + 1
            while j < len(token) and token[j] == c:
                j += 1
            if c.isalpha():
                out.append([(c, 0.0)] if j == i + 1 else [(c, 1.0 if j == i + 2 else 0.5), (c + c, 0.0 if j == i + 2 else 1.0)])
            elif c in STANDS_FOR:
                own = [(x, 1.0) for x in STANDS_FOR[c]]
                if c not in SIGNS or (i and j < len(token)):  # at an end the reading without the sign is taken beside
                    own += [(" ", 9.0)] + ([("", 3.0)] if c in "*!|" else [])
                out += [own] * (1 if j - i > 2 else j - i)
            elif c in APART:
                out.append([("", 1.0), (" ", 4.0)] if letters_apart else [("", 2.5), (" ", 0.5)])
            else:
                out.append([("", 2.0), (" ", 1.0)])
            i = j
        return out

    def decode(self, token: str) -> str:
        known = self.memo.get(token)
        if known is not None:
            return known
        states: dict[tuple[int, int], tuple[float, tuple]] = {(0, 0): (0.0, ())}
        for options in self.lattice(token):
            after: dict[tuple[int, int], tuple[float, tuple]] = {}
            for (a, b), (spent, path) in states.items():
                for put, extra in options:
                    x, y, c = a, b, spent + extra
                    for letter in put:
                        s = self.of(letter)
                        if s or y:
                            c += self.cost[((0 if y == 0 else x) * SYMBOLS + y) * SYMBOLS + s]
                        x, y = y, s
                    old = after.get((x, y))
                    if old is None or c < old[0]:
                        after[(x, y)] = (c, (path, put))
            states = after
        best = min(((c + (self.cost[((0 if b == 0 else a) * SYMBOLS + b) * SYMBOLS] if b else 0.0), p) for (a, b), (c, p) in states.items()), key=lambda x: x[0])[1]
        parts = []
        while best:
            best, put = best
            parts.append(put)
        word = "".join(reversed(parts)).strip()
        if len(self.memo) >= MEMO:
            self.memo.clear()
        self.memo[token] = word
        return word

    def words(self, text: str) -> list[str]:
        """Lower-cased words of ``text``, disguised ones restored."""
        out: list[str] = []
        singles: list[str] = []
        text = text.lower()

        def end_of_singles() -> None:
            for run in readings("".join(singles), "".join(singles).strip(SIGNS)):
                if len(run) >= 3:
                    out.extend(self.decode(" ".join(run)).split())
            core = "".join(singles).strip(SIGNS)
            if len(core) >= 3:
                out.extend(self.decode(" ".join(core)).split())
            else:
                out.extend(c for c in core if c not in SIGNS)
            singles.clear()

        for token in text.split():
            core = token if token.isalpha() else token.strip(EDGES)
            if len(core) == 1:
                singles.append(core)
                continue
            if not core:  # a sign by itself may be a letter of a run; separators leave a run open
                if token in STANDS_FOR:
                    singles.append(token)
                continue
            if singles:
                end_of_singles()
            if core is not token and any(map(str.isalpha, core)):
                for x in readings(token.strip(PLAIN_EDGES), core):
                    out.extend(self.decode(x).split())
            if core.isalpha():
                twice = REPEATED.search(core)
                if twice:
                    out.extend(x for x in self.decode(core).split() if x != core)
                if not twice or not THRICE.search(core):
                    out.append(core)
                continue
            if core[-1] == core[-3:-2] and core[-1] in "$@+|":  # a run of signs behind a word is decoration
                core = core.rstrip(core[-1])
            out.extend(core.split() if core.isalpha() or core.isdigit() else self.decode(core).split())
        if singles:
            end_of_singles()
        return out


def readings(whole: str, core: str) -> list[str]:
    """``core`` with the signs around it in ``whole`` as letters: at either end none, the nearest one, or all of them."""
    if not core:
        return []
    before, _, after = whole.partition(core)
    left, right = ("".join(c for c in x if c in SIGNS) for x in (before, after))
    return list(dict.fromkeys(x + core + y for x in ("", left[-1:], left) for y in ("", right[:1], right) if x or y))


def marks(words: list[str]) -> set[str]:
    """What may mark a text: whole words and word beginnings, a blank for a word's border."""
    out = set()
    for w in set(words):
        if len(w) >= 3:
            out.add(f" {w} ")
            for k in range(4, min(len(w), 8)):
                out.add(f" {w[:k]}")
    return out


@dataclass(frozen=True)
class Model:
    costs: np.ndarray
    lexicon: tuple[tuple[str, float], ...]
    slope: float
    offset: float


class Scorer:
    def __init__(self, model: Model):
        self.restore, self.model = Restorer(model.costs), model
        self.machine = ahocorasick.Automaton()
        for mark, ratio in model.lexicon:
            self.machine.add_word(mark, (len(mark), ratio, mark))
        if model.lexicon:
            self.machine.make_automaton()

    def evidence(self, text: str) -> float:
        return self.evidence_of(self.restore.words(text)) if self.model.lexicon and text else 0.0

    def evidence_of(self, words: list[str]) -> float:
        """Summed ratios of the distinct marks found in restored words, the best one where several begin."""
        if not self.model.lexicon or not words:
            return 0.0
        best: dict[int, tuple[float, str]] = {}
        for end, (size, ratio, mark) in self.machine.iter(" " + "  ".join(words) + " "):
            at = end - size
            if at not in best or best[at][0] < ratio:
                best[at] = (ratio, mark)
        return sum({mark: ratio for ratio, mark in best.values()}.values())

    def score(self, text: str) -> float:
        return float(1 / (1 + np.exp(-np.clip(self.model.slope * min(self.evidence(text), 40.0) + self.model.offset, -30, 30))))


def restored_sample(sample: DataFrame, costs: np.ndarray) -> DataFrame:
    """``least, label, text`` of ``sample(text, label)``: its least shingle, and its restored words."""
    sent = sample.sparkSession.sparkContext.broadcast(costs)

    def restored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        restore = Restorer(sent.value)
        for batch in batches:
            texts = batch["text"].to_pylist()
            least = [int(s[0].astype(np.int64)) if len(s) else 0 for s in shingles([x.encode() for x in texts])]
            yield pa.RecordBatch.from_arrays([pa.array(least, pa.int64()), batch["label"], pa.array([" ".join(restore.words(x)) for x in texts])], names=["least", "label", "text"])

    return sample.select("text", "label").mapInArrow(restored, "least long, label int, text string")


def learn_lexicon(restored: DataFrame) -> tuple[tuple[str, float], ...]:
    """Marks that stand out in toxic rows of a :func:`restored_sample`. Near copies count about once: of rows with the same least shingle one counts."""

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = (Counter(), Counter())
        for batch in batches:
            for label, text in zip(batch["label"].to_pylist(), batch["text"].to_pylist(), strict=True):
                n[1 if label else 0].update(marks(text.split()))
                n[1 if label else 0][""] += 1
        keys = [*n[1], *(k for k in n[0] if k not in n[1])]
        yield pa.RecordBatch.from_arrays([pa.array(keys, pa.string()), pa.array([n[1][k] for k in keys], pa.int64()), pa.array([n[0][k] for k in keys], pa.int64())], names=["mark", "toxic", "clean"])

    once = restored.dropDuplicates(["least", "label"])
    counts = once.mapInArrow(counted, "mark string, toxic long, clean long").groupBy("mark").agg(F.sum("toxic").alias("toxic"), F.sum("clean").alias("clean"))
    rows = {r["mark"]: (r["toxic"], r["clean"]) for r in counts.where(f"mark = '' or (toxic >= {LEAST_ROWS} and toxic > clean / 8)").collect()}  # bounded by the sample
    all_toxic, all_clean = rows.pop("", (0, 0))
    if not all_toxic or not all_clean:
        return ()
    share = all_toxic / (all_toxic + all_clean)
    out = []
    for mark, (t, c) in sorted(rows.items()):
        g = 2 * (t * np.log(t / ((t + c) * share)) + (c * np.log(c / ((t + c) * (1 - share))) if c else 0.0))
        ratio = float(np.log((t + 0.5) / (all_toxic + 1)) - np.log((c + 0.5) / (all_clean + 1)))
        if g >= LEAST_G and ratio >= LEAST_RATIO:
            out.append((mark, ratio))
    return tuple(out)


def train(docs: DataFrame, labels: DataFrame, usable: Column, limit: int = TRAIN_ROWS) -> Model:
    """Language model from every text; lexicon and curve from at most ``limit`` labelled documents, the first by hash, each once (:func:`sample_for_training`).

    Null texts count as empty, extra columns are ignored; an empty table, or labels of one kind, give a model whose score is the smoothed share."""
    costs = language_model(docs)
    sample = sample_for_training(docs, labels, "toxic", usable, limit).withColumn("text", empty_text())
    restored = stored(restored_sample(sample, costs), "restored")
    lexicon = learn_lexicon(restored)
    sent = docs.sparkSession.sparkContext.broadcast(Model(costs, lexicon, 1.0, 0.0))

    def weigh(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(sent.value)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array([min(scorer.evidence_of(x.split()), 40.0) for x in batch["text"].to_pylist()], pa.float64()), batch["label"]], names=["evidence", "label"])

    rows = restored.select("text", "label").mapInArrow(weigh, "evidence double, label int").collect()  # at most limit rows
    drop_stored(restored)
    y = np.array([1.0 if r["label"] else -1.0 for r in rows])
    if len(set(y.tolist())) < 2:
        p = (float((y > 0).sum()) + 1) / (len(y) + 2)
        return Model(costs, (), 1.0, float(np.log(p / (1 - p))))
    return Model(costs, lexicon, *platt(np.array([r["evidence"] for r in rows]), y))


def scored(docs: DataFrame, model: Model) -> DataFrame:
    """``docs`` with ``score`` in [0, 1] added (a column of that name is replaced). Null texts score as empty ones;
    repeated rows score alike; an empty table stays empty; without labels of both kinds the score is the smoothed share."""
    sent = docs.sparkSession.sparkContext.broadcast(model)  # SYMBOLS**3 costs and a lexicon bounded by the sample

    @F.arrow_udf("double")
    def score(parts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        scorer = Scorer(sent.value)
        for part in parts:
            yield pa.array([scorer.score(x) for x in part.to_pylist()], pa.float64())

    return docs.withColumn("score", score(empty_text()))
