"""Benchmark decontamination by the q-gram lemma.

An occurrence of an item of ``m`` bytes with at most ``e`` edits shares at least ``m + 1 - q * (e + 1)`` q-grams with
the text, on diagonals that differ by at most ``e``. Shared q-grams are counted in overlapping bands of ``2 * (e + 1)``
diagonals, one band beginning every ``e + 1``; bands that reach the bound are kept and verified by a banded alignment.
Benchmark items are the query set; they are taken in blocks of bounded size, each a broadcast index over one pass of the texts.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from roundmm.llm.common import empty_text, sliced
from roundmm.llm.textnum import joined, rolling, slices

GRAM = 10
#: The same of short items, whose edits would leave no longer one. Items too short even for these are matched exactly, between bytes that are no letters or digits.
SHORT_GRAM = 6
EDIT_SHARE = 0.08
#: Most bytes of benchmark text in one broadcast index.
BLOCK_BYTES = 8 << 20
FILTER_BITS = 22

#: A-Z lower-cased and white space made blank; lengths stay, so offsets are offsets of the text's UTF-8.
FOLD = bytes(32 if b in (9, 10, 11, 12, 13) else b + 32 if 65 <= b <= 90 else b for b in range(256))


def budget(m: int, share: float = EDIT_SHARE) -> int:
    """Edits allowed for an item of ``m`` bytes."""
    return int(share * m)


def gram_of(m: int) -> int:
    """The q-grams by which an item of ``m`` bytes is found: short enough that its budget leaves one untouched. 0: the item is searched as a word."""
    return next((q for q in (GRAM, SHORT_GRAM) if m + 1 - q * (budget(m) + 1) >= 1), 0)


@dataclass(frozen=True)
class Index:
    q: int
    ids: tuple[int | None, ...]
    items: tuple[bytes, ...]
    edits: np.ndarray
    grams: np.ndarray  # distinct hashes, sorted
    first: np.ndarray  # where each gram's postings begin
    item: np.ndarray
    place: np.ndarray
    sieve: np.ndarray


@dataclass(frozen=True)
class Block:
    """Benchmark items that one pass of the texts looks for: q-gram indexes, and the items searched as words."""

    indexes: tuple[Index, ...]
    words: tuple[tuple[int | None, re.Pattern], ...]


EDGE = rb"0-9A-Za-z\x80-\xff"


def block_of(rows: list[tuple[int | None, bytes]]) -> Block:
    by = {q: [(i, t) for i, t in rows if t and gram_of(len(t)) == q] for q in (GRAM, SHORT_GRAM, 0)}
    words = tuple((i, re.compile(b"(?<![" + EDGE + b"])" + re.escape(t) + b"(?![" + EDGE + b"])")) for i, t in by[0])
    return Block(tuple(build(by[q], q) for q in (GRAM, SHORT_GRAM) if by[q]), words)


def found_in(texts: list[bytes], block: Block) -> list[tuple[int, int | None, int, int, int]]:
    """Verified regions: (text number, item id, begin, end, edits)."""
    out = [(t, index.ids[i], begin, end, edits) for index in block.indexes for t, i, begin, end, edits in regions(texts, index)]
    for name, pattern in block.words:
        out += [(t, name, m.start(), m.end(), 0) for t, text in enumerate(texts) for m in pattern.finditer(text.translate(FOLD))]
    return out


def build(rows: list[tuple[int | None, bytes]], q: int = GRAM) -> Index:
    rows = [(i, t) for i, t in rows if len(t) >= q]
    hashed = [rolling(np.frombuffer(t, np.uint8), q) for _, t in rows]
    grams = np.concatenate(hashed) if hashed else np.empty(0, np.uint64)
    item = np.repeat(np.arange(len(rows), dtype=np.int32), [len(h) for h in hashed])
    place = np.concatenate([np.arange(len(h), dtype=np.int32) for h in hashed]) if hashed else np.empty(0, np.int32)
    order = np.argsort(grams, kind="stable")
    grams, first = np.unique(grams[order], return_index=True)
    sieve = np.zeros(1 << FILTER_BITS, bool)
    sieve[(grams >> np.uint64(64 - FILTER_BITS)).astype(np.int64)] = True
    edits = np.array([budget(len(t)) for _, t in rows], np.int64)
    return Index(q, tuple(i for i, _ in rows), tuple(t for _, t in rows), edits, grams, np.append(first, len(order)), item[order], place[order], sieve)


def aligned(item: bytes, window: bytes, e: int, anchored: bool = False) -> tuple[int, int]:
    """Fewest edits of ``item`` against a part of ``window``, right where that is at most ``e``, and where the first such part ends.
    The part begins anywhere, or, ``anchored``, where the window begins.

    Row by row over a band of diagonals: those that the window leaves open, and ``e`` more on either side, where bytes that
    match nothing stand; insertions by a running minimum.
    """
    p = np.frombuffer(item, np.uint8)
    w = np.frombuffer(bytes(e) + window + bytes(e), np.uint8)
    spread = max(len(w) - len(p), 0) + 1
    w = np.append(w, np.zeros(max(0, len(p) + spread - 1 - len(w)), np.uint8))
    steps = np.arange(spread)
    cost = np.where(steps >= e, steps - e, len(item) + len(window)) if anchored else np.zeros(spread, np.int64)
    for i in range(len(p)):
        now = cost + (w[i : i + spread] != p[i])
        np.minimum(now[:-1], cost[1:] + 1, out=now[:-1])
        cost = np.minimum.accumulate(now - steps) + steps
    best = int(cost.argmin())
    return int(cost[best]), min(max(len(p) + best - e, 0), len(window))


def regions(texts: list[bytes], index: Index) -> list[tuple[int, int, int, int, int]]:
    """Verified regions: (text number, item number, begin, end, edits), in order."""
    out, q = [], index.q
    if not len(index.grams):
        return out
    wide = index.edits + 1
    sizes = np.array([len(t) for t in index.items], np.int64)
    needed = sizes + 1 - q * wide
    for lo, hi in slices(texts):
        part = [t.translate(FOLD) for t in texts[lo:hi]]
        buffer, begins = joined(part)
        hashed = rolling(buffer, q)
        maybe = np.flatnonzero(index.sieve[(hashed >> np.uint64(64 - FILTER_BITS)).astype(np.int64)])
        slot = np.searchsorted(index.grams, hashed[maybe])
        slot[slot == len(index.grams)] = 0
        same = index.grams[slot] == hashed[maybe]
        at, slot = maybe[same], slot[same]
        if not len(at):
            continue
        many = index.first[slot + 1] - index.first[slot]
        run = np.arange(int(many.sum())) - np.repeat(np.cumsum(many) - many, many)
        posting = np.repeat(index.first[slot], many) + run
        item = index.item[posting].astype(np.int64)
        diagonal = np.repeat(at, many) - index.place[posting]
        # bands of different texts must not meet: a text's diagonals begin at minus the item's length
        owner = np.repeat(np.searchsorted(begins, at, side="right") - 1, many)
        band = (diagonal - begins[owner] + sizes[item]) // wide[item]
        span = int(band.max()) + 2
        key = (owner * len(index.items) + item) * span + band
        keys, counts = np.unique(np.concatenate((key, key - (band > 0))), return_counts=True)
        which = keys // span
        enough = counts >= needed[which % len(index.items)]
        keys, which = keys[enough], which[enough]
        cut = np.flatnonzero(np.diff(keys) > 1) + 1
        for group in np.split(np.arange(len(keys)), cut):
            if not len(group):
                continue
            for own in np.split(group, np.flatnonzero(np.diff(which[group])) + 1):
                t, i = divmod(int(which[own[0]]), len(index.items))
                e, m = int(index.edits[i]), int(sizes[i])
                low = int(keys[own[0]] % span) * (e + 1) - m
                high = int(keys[own[-1]] % span + 2) * (e + 1) - m
                begin, end = max(0, low - e), min(len(part[t]), high + m + e)
                edits, stop = aligned(index.items[i], part[t][begin:end], e)
                if edits <= e:
                    _, back = aligned(index.items[i][::-1], part[t][begin : begin + stop][::-1], e, anchored=True)
                    out.append((lo + t, i, begin + stop - back, begin + stop, edits))
    return out


def blocks(benchmark: DataFrame, limit: int = BLOCK_BYTES) -> Iterator[Block]:
    """The items in blocks of at most ``limit`` bytes (a longer item alone), streamed, never all at once."""
    held, size = [], 0
    for r in benchmark.select(F.col("item_id").cast("long"), empty_text().alias("text")).toLocalIterator():
        t = r[1].encode().translate(FOLD).strip(b" ")
        if held and size + len(t) > limit:
            yield block_of(held)
            held, size = [], 0
        held.append((r[0], t))
        size += len(t)
    if held:
        yield block_of(held)


def contamination(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """``doc_id, item_id, begin, end, edits``: every region of a text within the edit budget of a benchmark item.

    Offsets count UTF-8 bytes. Empty and null items match nothing, items of a few bytes only where they stand as words; null and empty texts hold no
    region; repeated rows are each reported; an empty benchmark or table gives no rows; other columns are ignored.
    Texts are read whole and in slices, so memory follows the longest text.
    """
    spark, found = docs.sparkSession, None
    schema = "doc_id long, item_id long, begin long, end long, edits int"
    for block in blocks(benchmark):
        sent = spark.sparkContext.broadcast(block)

        def scan(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            for batch in sliced(batches):
                hit = found_in(batch["text"].cast(pa.binary()).to_pylist(), sent.value)
                yield pa.RecordBatch.from_arrays(
                    [
                        batch["doc_id"].take(pa.array([h[0] for h in hit], pa.int64())),
                        pa.array([h[1] for h in hit], pa.int64()),
                        pa.array([h[2] for h in hit], pa.int64()),
                        pa.array([h[3] for h in hit], pa.int64()),
                        pa.array([h[4] for h in hit], pa.int32()),
                    ],
                    names=["doc_id", "item_id", "begin", "end", "edits"],
                )

        one = docs.select(F.col("doc_id").cast("long").alias("doc_id"), empty_text().alias("text")).mapInArrow(scan, schema)
        found = one if found is None else found.unionAll(one)
    return spark.createDataFrame([], schema) if found is None else found


def is_clean(text: Column, sent: Broadcast) -> Column:
    @F.arrow_udf("boolean")
    def clean(parts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for part in parts:
            ok = np.ones(len(part), bool)
            ok[[h[0] for h in found_in(part.cast(pa.binary()).to_pylist(), sent.value)]] = False
            yield pa.array(ok)

    return clean(text)


def decontaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows of ``docs`` without such a region, with its columns; a filter in the scan, no join. Null and empty texts, and null ids, stay; repeated rows
    are judged alike; an empty benchmark keeps every row, an empty table stays empty."""
    for block in blocks(benchmark):
        docs = docs.where(is_clean(empty_text(), docs.sparkSession.sparkContext.broadcast(block)))
    return docs
