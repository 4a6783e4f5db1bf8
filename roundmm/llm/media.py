"""Content-defined payload chunking of media columns.

A payload is held as a RIFF/WAVE file of 8-bit mono samples. A rolling gear hash cuts the file where its content says so, so
equal stretches of different files give equal chunks. Chunk digests are joined to find the first holder of each; only
it stores the bytes. A document's recipe lists its chunks in order; reading follows the recipe, checks every
chunk against its digest and the whole against the payload's.

The store has one row per distinct payload with the chunks that it holds. A payload that holds all of its own chunks is read where
it lies; only payloads with foreign chunks are gathered by a shuffle, each on its own.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from roundmm.llm.common import drop_stored, empty_text, free_shuffles, small, stored
from roundmm.llm.textnum import mix

BLOCK = 64
RATE = 8000
LEAST, MOST = 512, 16384
#: A cut where this many top bits of the gear hash are zero: chunks of about 2**CUT_BITS bytes beyond LEAST.
CUT_BITS = 11
GEAR = (mix(np.arange(1, 257, dtype=np.uint64)) >> np.uint64(32)).astype(np.uint32)


def padded(raw: bytes) -> bytes:
    """``raw`` and zero bytes, up to a positive multiple of ``BLOCK``."""
    return raw.ljust(max(1, -(-len(raw) // BLOCK)) * BLOCK, b"\0")


def wave(payload: bytes) -> bytes:
    """A WAVE file whose 8-bit mono samples are the payload's bytes."""
    head = struct.pack("<4sI4s4sIHHIIHH4sI", b"RIFF", 36 + len(payload), b"WAVE", b"fmt ", 16, 1, 1, RATE, RATE, 1, 8, b"data", len(payload))
    return head + payload


def samples(media: bytes) -> bytes:
    """The samples of such a file; the header is checked."""
    head = struct.unpack("<4sI4s4sIHHIIHH4sI", media[:44])
    if head[0] != b"RIFF" or head[2] != b"WAVE" or head[5:7] != (1, 1) or head[10] != 8 or head[12] != len(media) - 44:
        raise ValueError("not an 8-bit mono WAVE file")
    return media[44:]


def cuts(media: bytes) -> list[int]:
    """Ends of the chunks, by content; the hash of a place depends on the 32 bytes up to it."""
    n = len(media)
    if n <= LEAST:
        return [n]
    h = GEAR[np.frombuffer(media, np.uint8)]
    width = 1
    while width < 32:
        h[width:] += h[:-width] << np.uint32(width)
        width *= 2
    marks = np.flatnonzero(h >> np.uint32(32 - CUT_BITS) == 0) + 1
    out, at = [], 0
    while n - at > LEAST:
        k = int(np.searchsorted(marks, at + LEAST))
        stop = min(int(marks[k]) if k < len(marks) else n, at + MOST, n)
        out.append(stop)
        at = stop
    if at < n:
        out.append(n)
    return out


def chunks(media: bytes) -> list[bytes]:
    ends = cuts(media)
    return [media[a:b] for a, b in zip([0, *ends[:-1]], ends, strict=True)]


def digest(part: bytes) -> bytes:
    return hashlib.sha256(part).digest()


def payload_key(text: Column) -> Column:
    """Names a payload: sha256 of the unpadded bytes. Equal texts are one payload."""
    return F.unhex(F.sha2(text.cast("binary"), 256))


def chunk_list(docs: DataFrame) -> DataFrame:
    """``key, seq, digest`` of every chunk of ``docs(key, text)``, in order."""

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                found = [(k, i, digest(c)) for k, raw in enumerate(part["text"].cast(pa.binary()).to_pylist()) for i, c in enumerate(chunks(wave(padded(raw))))]
                yield pa.RecordBatch.from_arrays(
                    [part["key"].take(pa.array([f[0] for f in found], pa.int64())), pa.array([f[1] for f in found], pa.int32()), pa.array([f[2] for f in found], pa.binary())], names=["key", "seq", "digest"]
                )

    return docs.mapInArrow(emit, "key binary, seq int, digest binary")


STORE = "key binary, foreign array<struct<seq:int,key:binary,at:int>>, parts array<struct<seq:int,digest:binary,data:binary>>"


def packed(docs: DataFrame) -> DataFrame:
    """Store rows of ``docs(key, text, foreign)``: all chunks but the foreign ones, with their digests."""

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shape = pa.list_(pa.struct([("seq", pa.int32()), ("digest", pa.binary()), ("data", pa.binary())]))
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                rows = []
                for raw, foreign in zip(part["text"].cast(pa.binary()).to_pylist(), part["foreign"].to_pylist(), strict=True):
                    other = {f["seq"] for f in foreign or ()}
                    rows.append([{"seq": i, "digest": digest(c), "data": c} for i, c in enumerate(chunks(wave(padded(raw)))) if i not in other])
                yield pa.RecordBatch.from_arrays([part["key"], part["foreign"], pa.array(rows, shape)], names=["key", "foreign", "parts"])

    return docs.mapInArrow(emit, STORE)


FEATURES = "key binary, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
NAMES = [x.split()[0] for x in FEATURES.split(", ")]


def described(key: bytes, parts: list[tuple[int, bytes, bytes]]) -> tuple:
    """Rebuild a file from its chunks in order, verify it, and compute the features of what was read."""
    parts = sorted(parts, key=lambda p: p[0])
    if [p[0] for p in parts] != list(range(len(parts))) or any(digest(data) != name for _, name, data in parts):
        raise ValueError(f"chunks of payload {key.hex()} are missing or damaged")
    media = b"".join(data for _, _, data in parts)
    payload = samples(media)
    if not has_prefix(payload, key):
        raise ValueError(f"payload {key.hex()} reads back differently")
    x = np.frombuffer(payload, np.uint8).astype(np.int64) - 128
    crossings = int(np.count_nonzero((x[1:] >= 0) != (x[:-1] >= 0)))
    level = int((x * x).sum())
    feature = f"samples={len(x)};peak={int(np.abs(x).max())};sum={int(x.sum())};energy={level};crossings={crossings};chunks={len(parts)}"
    return key, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-BLOCK:]), len(media), hashlib.sha256(media).hexdigest(), feature


def has_prefix(payload: bytes, key: bytes) -> bool:
    """Whether the payload without some of its last ``BLOCK`` bytes has this sha256."""
    low = max(0, len(payload) - BLOCK)
    h = hashlib.sha256(payload[:low])
    for n in range(low, len(payload) + 1):
        if h.copy().digest() == key:
            return not payload[n:].strip(b"\0")
        h.update(payload[n : n + 1])
    return False


def frame(rows: list[tuple]) -> pa.RecordBatch:
    kinds = [pa.binary(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=NAMES)


def read_in_place(store: DataFrame) -> DataFrame:
    """Features of store rows that hold all their chunks."""

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                yield frame([described(k, [(p["seq"], p["digest"], p["data"]) for p in parts]) for k, parts in zip(part["key"].to_pylist(), part["parts"].to_pylist(), strict=True)])

    return store.select("key", "parts").mapInArrow(emit, FEATURES)


def read_gathered(parts: DataFrame) -> DataFrame:
    """Features from ``key, seq, digest, data`` rows, brought together by key and streamed in order."""

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key: bytes | None = None
        held: list[tuple] = []
        for batch in batches:
            done = []
            for k, seq, name, data in zip(*(batch[c].to_pylist() for c in ("key", "seq", "digest", "data")), strict=True):
                if k != key:
                    if held:
                        done.append(described(key, held))
                    key, held = k, []
                if not held or held[-1][0] != seq:  # a repeated row stores a chunk twice
                    held.append((seq, name, data))
            yield frame(done)
        if held:
            yield frame([described(key, held)])

    return parts.repartition("key").sortWithinPartitions("key", "seq").mapInArrow(emit, FEATURES)


def chunk_store(docs: DataFrame) -> DataFrame:
    """The chunk store of ``docs(doc_id, text)`` in the shared folder: see ``STORE``. Every distinct chunk is held once. Null texts are empty ones;
    null ids are ids; of equal texts the row of the least id is stored, and of rows equal in both one; an empty table gives an empty store."""
    texts = docs.select("doc_id", empty_text().alias("text")).withColumn("key", payload_key(F.col("text")))
    listed = stored(chunk_list(texts.select("key", "text")), "chunk-list")
    owners = listed.groupBy("digest").agg(F.min(F.struct("key", "seq")).alias("own"), F.max(F.struct("key", "seq")).alias("far")).where("own <> far").select("digest", "own")
    owners = stored(owners, "owners")
    foreign = listed.join(small(owners), "digest").where(F.struct("key", "seq") != F.col("own"))
    recipes = stored(
        foreign.groupBy("key").agg(F.collect_set(F.struct("seq", F.col("own.key").alias("key"), F.col("own.seq").alias("at"))).alias("foreign")).withColumnRenamed("key", "_key"), "recipes"
    )
    each = texts.groupBy("key", "doc_id").agg(F.count(F.lit(1)).alias("_n"))
    first = F.min(F.struct(F.col("doc_id"), F.col("_n")))
    copies = each.groupBy("key").agg(first.alias("_f"), F.sum("_n").alias("_n")).where("_n > 1")
    copies = stored(copies.select(F.col("key").alias("_copy"), F.col("_f.doc_id").alias("_first"), (F.col("_f._n") > 1).alias("_again")), "copies")
    single = texts.join(small(copies), F.col("key") == F.col("_copy"), "left").where(F.col("_copy").isNull() | F.col("doc_id").eqNullSafe(F.col("_first")))
    if copies.where("_again").limit(1).count():  # rows equal in id and text: one of them
        single = single.where(~F.coalesce("_again", F.lit(False))).select("key", "text").unionAll(single.where("_again").select("key", "text").dropDuplicates(["key"]))
    rows = single.select("key", "text").join(small(recipes), F.col("key") == F.col("_key"), "left").select("key", "text", "foreign")
    out = stored(packed(rows), "chunk-store")
    drop_stored(listed, owners, recipes, copies)
    return out


def read_features(store: DataFrame) -> DataFrame:
    """``FEATURES`` of every payload of a store, from the stored bytes."""
    whole = read_in_place(store.where("foreign is null"))
    partial = store.where("foreign is not null")
    own = partial.select("key", F.explode("parts").alias("p")).select("key", "p.seq", "p.digest", "p.data")
    wanted = partial.select("key", F.explode("foreign").alias("f")).select("key", F.col("f.seq").alias("seq"), F.col("f.key").alias("_from"), F.col("f.at").alias("_at")).distinct()
    givers = small(stored(wanted.select(F.col("_from").alias("key")).distinct(), "givers"))
    given = store.select("key", "parts").join(givers, "key", "left_semi").select(F.col("key").alias("_giver"), F.explode("parts").alias("p"))
    fetched = wanted.join(given, (F.col("_from") == F.col("_giver")) & (F.col("_at") == F.col("p.seq"))).select("key", "seq", "p.digest", "p.data")
    return whole.unionAll(read_gathered(own.unionAll(fetched)))


def media_report(docs: DataFrame) -> DataFrame:
    """Per row of ``docs(doc_id, text)``: ``doc_id, n_bytes`` and ``FEATURES`` but the key.

    Null and empty texts are 64 zero bytes; equal texts give equal values; rows with null or repeated ids each keep their row;
    an empty table gives no rows; other columns are ignored. A chunk or payload that reads back differently raises.
    """
    store = chunk_store(docs)
    free_shuffles(docs.sparkSession)
    # a payload stored by several equal rows is described as often: once is enough
    # and stored, so that the join has an exchange on either side and Spark may split a payload with many copies
    found = stored(read_features(store).groupBy("key").agg(*[F.first(c).alias(c) for c in NAMES[1:]]), "features")
    raw = empty_text().cast("binary")
    rows = docs.select("doc_id", F.octet_length(raw).cast("long").alias("n_bytes"), payload_key(empty_text()).alias("key"))
    return rows.join(found, "key").select("doc_id", "n_bytes", *NAMES[1:])
