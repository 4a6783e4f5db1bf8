"""Line deduplication by a segment-partition edit join.

If two lines differ by at most ``t`` edits, one of ``t + 1`` segments of the shorter line stands unchanged in the longer one,
near its place. Every distinct line sends an index row for each of its segments, and a probe row for each substring that
could be such a segment of a line 0 to ``t`` characters shorter (only starts that leave enough edits left and right).
Rows meet by (segment number, length, hash) in buckets, streamed in order; a parity sketch of the letters, which ``t`` edits change in at most ``2 * t``
bits, drops rows without a likely partner; a banded bit-parallel edit distance confirms the rest on the lines, inside the buckets. Pairs
never leave a bucket: links that join two groups do, and how many links each line has. A pair is counted in one bucket of those it meets in.

``t`` depends on the length of the shorter line (``Settings.budget``). Equal lines are one class at every length.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from roundmm.llm.common import components, drop_stored, empty_text, free_shuffles, sliced, small, stored

#: Distinct lines that a task remembers, to send a line it sees again only once. It bounds memory, not results.
SEEN = 200_000


@dataclass(frozen=True)
class Settings:
    edits: int = 2
    #: Lines of fewer characters are not joined within ``edits``: two short lines are within two edits by chance.
    min_chars: int = 20
    #: Members and bytes up to which a bucket is compared in place, and rows up to which one is held while it is streamed.
    leaf: int = 4096
    leaf_bytes: int = 16 << 20
    hold: int = 16_384
    #: (characters, edits), longest first: the edits of shorter lines. Below all of them only equal lines are joined.
    short: tuple[tuple[int, int], ...] = ()

    @property
    def least(self) -> int:
        """Fewest characters of a line that takes part in the edit join."""
        return min([self.min_chars, *(n for n, _ in self.short)])

    def budget(self, length: int) -> int:
        """Edits within which a line of ``length`` characters is joined to one that is no shorter."""
        return next((e for n, e in ((self.min_chars, self.edits), *self.short) if length >= n), 0)


#: What the report and the deletion of repeats take: one edit from 10 characters on, two from 20 on.
BY_LENGTH = Settings(short=((10, 1),))


def segments(length: int, parts: int) -> list[tuple[int, int]]:
    """Start and length of ``parts`` even segments, the longer ones last."""
    size, longer = divmod(length, parts)
    out, at = [], 0
    for i in range(parts):
        n = size + (i >= parts - longer)
        out.append((at, n))
        at += n
    return out


def plan(length: int, s: Settings) -> list[tuple[int, int, int, int, int]]:
    """(segment, indexed length, start, size, role) of a line's rows; role 1 index, 2 probe, 3 both."""
    out = []
    for shorter in range(max(s.least, length - s.edits), length + 1):
        over, edits = length - shorter, s.budget(shorter)
        if over > edits:
            continue
        for i, (at, n) in enumerate(segments(shorter, edits + 1)):
            right = edits - i
            for start in range(max(0, at - i, at + over - right), min(length - n, at + i, at + over + right) + 1):
                out.append((i, shorter, start, n, 3 if over == 0 and start == at else 2))
    return out


def line_name(line: str) -> bytes:
    """128-bit name of a line: what classes are made of."""
    return xxhash.xxh3_128_digest(line.encode("utf-8", "surrogatepass"))


def handle(name: bytes) -> int:
    """64 bits of a name, by which buckets list lines. Lines that share one are told apart by their texts."""
    return int.from_bytes(name[:8], "little", signed=True)


def bucket_key(segment: str, shorter: int, number: int) -> int:
    return xxhash.xxh3_64_intdigest(segment.encode("utf-8", "surrogatepass"), shorter * 8 + number) - (1 << 63)


def parities(lines: list[str]) -> np.ndarray:
    """A bit per letter class: whether the line holds an odd number of them."""
    code = np.frombuffer("".join(lines).encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64)
    bits = np.uint64(1) << ((code * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(58))
    starts = np.cumsum([0, *map(len, lines[:-1])])
    return np.bitwise_xor.reduceat(bits, starts).view(np.int64)


def lines_of(text: str, least: int = 1) -> list[tuple[int, str]]:
    """Number and trimmed text of the lines of at least ``least`` characters."""
    return [(i, x) for i, raw in enumerate(text.split("\n")) if len(x := raw.strip()) >= least]


def signatures(docs: DataFrame, s: Settings) -> DataFrame:
    """``key, id, parity, role, size`` of the lines of ``docs(text)``."""

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        plans: dict[int, list] = {}
        seen: set[int] = set()
        for batch in sliced(batches):
            fresh: dict[int, str] = {}
            for text in batch["text"].to_pylist():
                for _, x in lines_of(text, s.least):
                    i = handle(line_name(x))
                    if i not in seen:
                        seen.add(i)
                        fresh[i] = x
                if len(seen) > SEEN:
                    seen.clear()
            ids, lines = list(fresh), list(fresh.values())
            for at in range(0, len(ids), 4096):
                part = lines[at : at + 4096]
                key, owner, role = [], [], []
                for k, x in enumerate(part):
                    n = len(x)
                    rows = plans.get(n)
                    if rows is None:
                        rows = plans[n] = plan(n, s)
                    for seg, short, start, size, kind in rows:
                        key.append(bucket_key(x[start : start + size], short, seg))
                        role.append(kind)
                    owner.append(len(rows))
                many = np.array(owner)
                spread = lambda values: np.repeat(np.array(values, np.int64), many)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(key, pa.int64()), pa.array(spread(ids[at : at + 4096])), pa.array(spread(parities(part))), pa.array(role, pa.int32())], names=["key", "id", "parity", "role"]
                )

    return docs.mapInArrow(emit, "key long, id long, parity long, role int")


MEMBERS = "key long, id long, parity long, large boolean"


def near_parities(parity: np.ndarray, index: np.ndarray, run: np.ndarray, bits: int) -> np.ndarray:
    """Which rows have, in their run, another of at most ``bits`` different parities, one of the two an index row."""
    out = np.zeros(len(parity), bool)
    starts = np.flatnonzero(np.concatenate(([True], run[1:] != run[:-1])))
    size = np.diff(np.append(starts, len(run)))
    for at, n in zip(starts[size > 64], size[size > 64], strict=True):  # long runs: a block of rows against all
        p, k = parity[at : at + n], index[at : at + n]
        for lo in range(0, n, 256):
            close = (np.bitwise_count(p[lo : lo + 256, None] ^ p) <= bits) & (k[lo : lo + 256, None] | k)
            close[np.arange(len(close)), np.arange(lo, lo + len(close))] = False
            out[at + lo : at + lo + len(close)] = close.any(axis=1)
    left = np.repeat(starts + size, size) - np.arange(len(run))
    left[np.repeat(size > 64, size)] = 0
    rows, step = np.flatnonzero(left > 1), 1
    while len(rows):  # short runs: all rows against the one so many places on
        other = rows + step
        close = (np.bitwise_count(parity[rows] ^ parity[other]) <= bits) & (index[rows] | index[other])
        out[rows[close]] = out[other[close]] = True
        step += 1
        rows = rows[left[rows] > step]
    return out


def bucket_members(rows: DataFrame, s: Settings) -> DataFrame:
    """``MEMBERS``: the rows that could be linked with another of their bucket, once each. Rows are sorted by key and streamed, one bucket is held at a
    time; the rows of a bucket of more than ``hold`` pass through unheld, marked ``large``."""

    def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [np.empty(0, np.int64)] * 4
        passing: int | None = None

        def out(part: list[np.ndarray], keep: np.ndarray, large: bool) -> pa.RecordBatch:
            key, i, parity = (pa.array(x[keep]) for x in part[:3])
            return pa.RecordBatch.from_arrays([key, i, parity, pa.array(np.full(len(key), large))], names=["key", "id", "parity", "large"])

        def met(part: list[np.ndarray]) -> pa.RecordBatch:
            key, i, parity, role = part
            first = np.flatnonzero(np.concatenate(([True], (key[1:] != key[:-1]) | (i[1:] != i[:-1])))) if len(key) else np.empty(0, np.int64)
            part = [key[first], i[first], parity[first]]
            bits = part[2].view(np.uint64)  # of signed numbers the bits of the absolute value would be counted
            index = np.bitwise_or.reduceat(role, first) & 1 > 0 if len(first) else np.empty(0, bool)
            return out(part, near_parities(bits, index, part[0], 2 * s.edits), False)

        for batch in batches:
            now = [batch[c].to_numpy().astype(np.int64) for c in ("key", "id", "parity", "role")]
            if passing is not None:
                same = now[0] == passing
                yield out(now, same, True)
                if same.all():
                    continue
                now, passing = [x[~same] for x in now], None
            now = [np.concatenate(x) for x in zip(held, now, strict=True)]
            if not len(now[0]):
                continue
            last = int(np.searchsorted(now[0], now[0][-1]))
            yield met([x[:last] for x in now])
            held = [x[last:] for x in now]
            if len(held[0]) > s.hold:
                passing = int(held[0][0])
                yield out(held, np.ones(len(held[0]), bool), True)
                held = [np.empty(0, np.int64)] * 4
        yield met(held)

    return rows.repartition("key").sortWithinPartitions("key", "id").mapInArrow(stream, MEMBERS)


def common(a: str, b: str) -> int:
    """Characters that both begin with."""
    lo, hi = 0, min(len(a), len(b))
    while lo < hi:
        mid = (lo + hi + 1) // 2
        if a[lo:mid] == b[lo:mid]:
            lo = mid
        else:
            hi = mid - 1
    return lo


def within(a: str, b: str, limit: int) -> bool:
    """Whether the edit distance is at most ``limit``: common ends are cut, then a band of ``2 * limit + 1`` cells is
    carried along the diagonal as bit vectors of vertical differences."""
    if len(a) > len(b):
        a, b = b, a
    if len(b) - len(a) > limit:
        return False
    n = common(a, b)
    a, b = a[n:], b[n:]
    n = common(a[::-1], b[::-1])
    a, b = a[: len(a) - n], b[: len(b) - n]
    if not a:
        return len(b) <= limit
    place: dict[str, int] = {}
    for k, c in enumerate(a):
        place[c] = place.get(c, 0) | 1 << k
    width = 2 * limit + 1
    full = (1 << width) - 1
    # bit r of the column for b[j] stands for row j - limit + r of a; the lower half starts above the text
    up, down = full >> limit << limit, 0
    rows = len(a)
    score = min(limit, rows)
    for j, c in enumerate(b):
        shift = j - limit
        mask = place.get(c, 0)
        mask = (mask >> shift if shift >= 0 else mask << -shift) & full
        zero = ((((mask & up) + up) ^ up) | mask | down) & full
        plus = (down | ~(zero | up)) & full
        minus = zero & up
        bottom = j + limit  # row of the band's last cell
        if bottom < rows:
            score += not zero >> (width - 1) & 1
        else:
            at = width - 1 - (bottom - rows + 1)  # the cell of the last row of a
            score += (plus >> at & 1) - (minus >> at & 1)
        if score > limit + (len(b) - j):
            return False
        up = (minus | ~((zero >> 1) | plus)) & full
        down = (zero >> 1) & plus & full
    return score <= limit


def line_texts(docs: DataFrame, s: Settings) -> DataFrame:
    """``id, name, line`` of the lines of ``docs(text)`` that take part in the edit join."""

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in sliced(batches):
            lines = list({x: None for text in batch["text"].to_pylist() for _, x in lines_of(text, s.least)})
            names = [line_name(x) for x in lines]
            yield pa.RecordBatch.from_arrays([pa.array([handle(x) for x in names], pa.int64()), pa.array(names, pa.binary()), pa.array(lines, pa.string())], names=["id", "name", "line"])

    return docs.mapInArrow(emit, "id long, name binary, line string")


def occurrences(docs: DataFrame, s: Settings) -> DataFrame:
    """``doc_id, print, line_no, long, name`` of every line of ``docs(doc_id, print, text)`` that isn't empty; ``long``: of at least ``min_chars`` characters."""

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in sliced(batches):
            found = [(k, i, len(x) >= s.min_chars, line_name(x)) for k, text in enumerate(batch["text"].to_pylist()) for i, x in lines_of(text)]
            owner = pa.array([f[0] for f in found], pa.int64())
            yield pa.RecordBatch.from_arrays(
                [batch["doc_id"].take(owner), batch["print"].take(owner), *(pa.array([f[k] for f in found], t) for k, t in ((1, pa.int32()), (2, pa.bool_()), (3, pa.binary())))],
                names=["doc_id", "print", "line_no", "long", "name"],
            )

    return docs.mapInArrow(emit, "doc_id long, print binary, line_no int, long boolean, name binary")


def near_pairs(lines: list[str], parity: np.ndarray, own: np.ndarray, s: Settings) -> Iterator[tuple[int, int]]:
    """Every two of ``lines`` within their edits; where ``own`` has blocks (not -1), every two of different blocks."""
    length, at = np.array([len(x) for x in lines]), np.arange(len(lines))
    for i in range(len(lines) - 1):
        maybe = (np.bitwise_count(parity[i + 1 :] ^ parity[i]) <= 2 * s.edits) & (abs(length[i + 1 :] - length[i]) <= s.edits)
        if own[i] >= 0:
            maybe &= own[i + 1 :] != own[i]
        for j in at[i + 1 :][maybe].tolist():
            if within(lines[i], lines[j], s.budget(int(min(length[i], length[j])))):
                yield i, j


def line_keys(line: str, s: Settings) -> dict[int, int]:
    """The buckets of a line, and its roles in each."""
    out: dict[int, int] = {}
    for seg, short, start, size, kind in plan(len(line), s):
        key = bucket_key(line[start : start + size], short, seg)
        out[key] = out.get(key, 0) | kind
    return out


#: Links ``a < b`` that join the groups of a node; and, with a null ``b``, how many links of ``a`` the node counts.
FOUND = "a binary, b binary, n long"
#: Members of a node: ``keys`` are the buckets that it stands for, ``part`` the part of the parities that its members share (or -1), ``own`` the block (or -1 where
#: members of one block meet).
NODE = ("node", "name", "parity", "line", "keys", "part", "own")


def parity_part(k: int, s: Settings) -> tuple[int, int]:
    """Shift and mask of one of ``2 * edits + 1`` parts of a parity: of two that differ in at most ``2 * edits`` bits one part is equal."""
    width = -(-64 // (2 * s.edits + 1))
    return k * width, (1 << min(width, 64 - k * width)) - 1


def first_equal_part(x: int, y: int, s: Settings) -> int:
    for k in range(2 * s.edits + 1):
        shift, mask = parity_part(k, s)
        if not (x ^ y) >> shift & mask:
            return k
    return -1


def node_links(nodes: DataFrame, s: Settings) -> DataFrame:
    """``FOUND`` of every node of ``NODE``; rows are sorted by node and streamed, one node is held at a time. All members are compared. A pair can meet in several nodes:
    it is counted in the one that stands for the least bucket that both lines share, an index row among them, and for the first equal part of their parities.
    Links go out only where they join two groups, counts as a row a line, so a group of g lines sends rows in the order of g."""

    def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at: int | None = None
        held: dict[bytes, tuple] = {}

        def done() -> pa.RecordBatch:
            names, rows = list(held), list(held.values())
            lines, own = [x[1] for x in rows], np.array([x[4] for x in rows], np.int64)
            parity = np.array([x[0] for x in rows], np.int64).view(np.uint64)
            above, many, buckets, spans = list(range(len(rows))), {}, {}, []

            def top(k: int) -> int:
                while above[k] != k:
                    above[k] = k = above[above[k]]
                return k

            for i, j in near_pairs(lines, parity, own, s):
                x, y = top(i), top(j)
                if x != y:
                    above[y] = x
                    spans.append((min(names[i], names[j]), max(names[i], names[j])))
                for k in (i, j):
                    if k not in buckets:
                        buckets[k] = line_keys(lines[k], s)
                p, q = buckets[i], buckets[j]
                least = min(key for key in p.keys() & q.keys() if (p[key] | q[key]) & 1)
                part = rows[i][3]
                if least in rows[i][2] and (part < 0 or part == first_equal_part(int(parity[i]), int(parity[j]), s)):
                    many[i], many[j] = many.get(i, 0) + 1, many.get(j, 0) + 1
            out = [*((a, b, None) for a, b in spans), *((names[k], None, n) for k, n in many.items())]
            return pa.RecordBatch.from_arrays([pa.array([x[k] for x in out], t) for k, t in enumerate((pa.binary(), pa.binary(), pa.int64()))], names=["a", "b", "n"])

        for batch in batches:
            for node, name, *row in zip(*(batch[c].to_pylist() for c in NODE), strict=True):
                if node != at:
                    if len(held) > 1:
                        yield done()
                    at, held = node, {}
                row[2] = set(row[2])
                held[name] = row
        if len(held) > 1:
            yield done()

    return nodes.select(*NODE).repartition("node").sortWithinPartitions("node", "name").mapInArrow(stream, FOUND)


def parity_nodes(members: DataFrame, s: Settings) -> DataFrame:
    """Nodes of a node's members that agree in one part of their parities."""
    cut = []
    for k in range(2 * s.edits + 1):
        shift, mask = parity_part(k, s)
        cut.append(F.struct(F.xxhash64(F.col("node"), F.lit(k), F.shiftrightunsigned("parity", shift).bitwiseAND(mask)).alias("node"), F.lit(k).alias("part")))
    return members.drop("part").withColumn("_p", F.explode(F.array(*cut))).select(*[c for c in members.columns if c not in ("node", "part")], "_p.node", "_p.part")


def blocked(members: DataFrame, s: Settings) -> DataFrame:
    """Nodes as pairs of blocks of bounded size, each pair a node: every two members meet in one."""
    sizes = members.groupBy("node").agg(F.greatest(F.ceil(2 * F.count(F.lit(1)) / F.lit(s.leaf)), F.ceil(2 * F.sum("n_bytes") / F.lit(s.leaf_bytes)), F.lit(1)).cast("int").alias("_k"), F.count(F.lit(1)).alias("_n")).where("_n > 1")
    met = members.drop("own").join(sizes, "node").withColumn("own", F.pmod(F.xxhash64("name"), F.col("_k")).cast("int"))
    met = met.withColumn("_other", F.explode(F.expr("sequence(0, _k - 1)")))
    return met.withColumns({"node": F.xxhash64("node", F.least("own", "_other"), F.greatest("own", "_other")), "own": F.when(F.col("own") == F.col("_other"), -1).otherwise(F.col("own"))}).drop("_k", "_n", "_other")


def links(texts: DataFrame, s: Settings) -> DataFrame:
    """Links ``a < b`` between the names of distinct lines that join what the links of all pairs join; how many links each line has is in :func:`joined`."""
    return joined(texts, s).where("b is not null").select("a", "b").distinct()


def joined(texts: DataFrame, s: Settings) -> DataFrame:
    """``FOUND`` of all buckets: every two distinct lines within their edits are found and counted once at each of the two; of a group of g lines about g links
    are sent, not g * g.

    Buckets of at most ``leaf`` members and ``leaf_bytes`` bytes are compared in place. Members of larger ones meet by equal parts of the parities, in pairs of blocks.
    """
    spark = texts.sparkSession
    members = stored(bucket_members(signatures(texts, s), s), "line-members")
    free_shuffles(spark)
    wanted = stored(members.select("id").distinct(), "line-wanted")
    lines = stored(line_texts(texts, s).join(small(wanted), "id", "left_semi").dropDuplicates(["name"]).withColumn("n_bytes", F.octet_length("line")), "lines")
    free_shuffles(spark)
    named = members.join(lines.select("id", "name", "n_bytes"), "id").select(F.col("key").alias("node"), "name", "parity", "n_bytes", "large")
    named = stored(named, "line-named")
    drop_stored(members, wanted)
    size = F.sum(F.xxhash64("name").bitwiseAND((1 << 40) - 1))
    stats = named.groupBy("node").agg(F.count(F.lit(1)).alias("n"), F.sum("n_bytes").alias("_b"), F.bool_or("large").alias("_l"), size.alias("_s"), F.bit_xor(F.xxhash64("name", F.lit(1))).alias("_x")).where("n > 1")
    # one node for each set of members: as many buckets as two lines can share at most
    once = stats.groupBy("n", "_b", "_s", "_x").agg(F.min("node").alias("node"), F.bool_or("_l").alias("_l"), F.collect_list("node").alias("keys"))
    fits = (F.col("n") <= s.leaf) & (F.col("_b") <= s.leaf_bytes) & ~F.col("_l")
    once = stored(once.select("node", fits.alias("fits"), "keys"), "line-nodes")
    body = lines.select("name", "line")
    whole = [F.lit(-1).alias("part"), F.lit(-1).alias("own")]
    near = named.join(once.where("fits").select("node", "keys"), "node").join(body.hint("merge"), "name")
    found = node_links(near.select("*", *whole), s)
    if once.where("not fits").limit(1).count():
        large = named.join(once.where("not fits").select("node", "keys"), "node").select("node", "name", "parity", "n_bytes", "keys", *whole).dropDuplicates(["node", "name"])
        found = found.unionAll(node_links(blocked(parity_nodes(large, s), s).join(body.hint("merge"), "name"), s))
    found = stored(found, "line-links")
    drop_stored(named, lines, once)
    return found


def classed(docs: DataFrame, settings: Settings | None = None) -> tuple[DataFrame, DataFrame]:
    """Occurrences with their line's ``class`` and ``n_links``, ``n_pairs``, and, of classes that occur more than once, the first occurrence."""
    s = settings or BY_LENGTH
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), empty_text().alias("text"))
    found = joined(texts.select("text"), s)
    labels = components(found.where("b is not null").select("a", "b"))
    sizes = labels.groupBy("component").agg((F.count(F.lit(1)) - 1).alias("n_links"))
    pairs = found.where("b is null").groupBy(F.col("a").alias("node")).agg(F.sum("n").alias("n_pairs"))
    near = stored(labels.join(sizes, "component").join(pairs, "node").withColumnRenamed("node", "name"), "line-classes")
    drop_stored(found, labels)
    held = occurrences(texts.withColumn("print", text_print(F.col("text"))).select("doc_id", "print", "text"), s).join(small(near), "name", "left")
    held = stored(held.select("doc_id", "print", "line_no", "long", F.coalesce("component", "name").alias("class"), *[F.coalesce(c, F.lit(0)).alias(c) for c in ("n_links", "n_pairs")]), "occurrences")
    drop_stored(near)
    first = held.groupBy("class").agg(F.min(F.struct("doc_id", "print", "line_no")).alias("first"), F.min("doc_id").alias("class_doc"), F.count(F.lit(1)).alias("_n")).where("_n > 1")
    # stored, so that the join back has an exchange on either side and Spark may split a hot class
    return held, stored(first.select("class", "first", "class_doc"), "line-first")


def text_print(text: Column) -> Column:
    """Tells texts apart that share an id."""
    return F.unhex(F.md5(text.cast("binary")))


def is_first() -> Column:
    """Whether an occurrence, left-joined with the repeated classes, is the one to keep."""
    return F.col("first").isNull() | (F.col("doc_id").eqNullSafe(F.col("first.doc_id")) & (F.col("print") == F.col("first.print")) & (F.col("line_no") == F.col("first.line_no")))


def document_classes(held: DataFrame, first: DataFrame) -> DataFrame:
    """``node, component``: documents joined by shared line classes, over any number of steps, and the smallest id of each
    component. Every document of a class is linked with the class's smallest id. The document with a null id has no row; it joins the documents
    of its classes, whose smallest id it takes from any of them."""
    star = held.select("doc_id", "class").distinct().join(first.select("class", "class_doc"), "class").select("doc_id", "class_doc").distinct()
    star = stored(star.where("class_doc is not null"), "line-documents")
    hub = star.where("doc_id is null").agg(F.min("class_doc")).first()[0]  # one number
    return components(star.select(F.coalesce("doc_id", F.lit(hub).cast("long")).alias("a"), F.col("class_doc").alias("b")))


def line_report(docs: DataFrame, settings: Settings | None = None) -> DataFrame:
    """One row per document: ``doc_id, n_lines, n_kept, n_short, n_short_kept, n_links, n_pairs, class_id``.

    ``n_lines`` counts lines of at least ``min_chars`` characters (trimmed), ``n_kept`` those that are their class's first
    occurrence by (doc_id, md5 of the text, line number), ``n_short`` and ``n_short_kept`` the same of shorter lines that aren't empty, ``n_links`` the other
    distinct lines in the classes of its lines, ``n_pairs`` the links of its lines themselves (other distinct lines within their edits), ``class_id`` the smallest doc_id
    that shared line classes join with it, over any number of documents between (itself without any). Null and empty texts have no lines. Rows that share an id are
    one document, whose counts are those of all its rows; a null id sorts before all others. Very long lines are compared whole.
    An empty table gives no rows; other columns are ignored.
    """
    held, first = classed(docs, settings)
    marked = held.join(first, "class", "left")
    each = marked.groupBy(F.col("doc_id").alias("_id")).agg(F.count_if("long").alias("n_lines"), F.count_if(F.col("long") & is_first()).alias("n_kept"), F.count_if(~F.col("long")).alias("n_short"), F.count_if(~F.col("long") & is_first()).alias("n_short_kept"), F.sum("n_links").alias("n_links"), F.sum("n_pairs").alias("n_pairs"), F.min("class_doc").alias("_doc"))
    ids = docs.select(F.col("doc_id").cast("long").alias("doc_id")).distinct()
    out = ids.join(each, F.col("doc_id").eqNullSafe(F.col("_id")), "left").withColumn("_doc", F.coalesce("doc_id", "_doc"))
    out = out.join(document_classes(held, first), F.col("_doc") == F.col("node"), "left")
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("long").alias(c)
    return out.select("doc_id", *[zero(c) for c in ("n_lines", "n_kept", "n_short", "n_short_kept", "n_links", "n_pairs")], F.coalesce("component", "_doc").alias("class_id"))


def without_repeats(docs: DataFrame, settings: Settings | None = None) -> DataFrame:
    """``docs`` with texts that keep, of each line class, only the first occurrence; empty lines stay.

    Null texts stay null, empty ones empty. Rows that share an id but not a text each lose their own lines; rows equal in id and text are one occurrence and
    keep the same lines. A null id sorts first. Columns and their names stay as they are; an empty table stays empty.
    """
    held, first = classed(docs, settings)
    gone = held.join(first, "class").where(~is_first()).groupBy(F.col("doc_id").alias("_gone_id"), F.col("print").alias("_gone_print")).agg(F.collect_set("line_no").alias("_gone"))
    same = F.col("doc_id").cast("long").eqNullSafe(F.col("_gone_id")) & (text_print(empty_text()) == F.col("_gone_print"))
    out = docs.join(gone, same, "left")
    kept = F.filter(F.split("text", "\n"), lambda x, i: ~F.coalesce(F.array_contains("_gone", i), F.lit(False)))
    return out.withColumn("text", F.when(F.col("_gone").isNull(), F.col("text")).otherwise(F.array_join(kept, "\n"))).select(*docs.columns)
