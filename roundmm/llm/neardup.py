"""Near duplicates by a chosen-path similarity join over word-shingle sets.

A set's minwise tokens are the minima of ``TOKENS`` hash functions over its shingles. In each of several independent
trees a document follows the branches named by (position, token), where the positions are chosen by the path so far;
documents that share most tokens keep meeting, others part. Paths start ``START`` tokens deep. Then, level by level:

* documents with equal sets are one node member (a representative), and nodes with equal members are one node;
* small nodes are compared exhaustively on the full shingle sets, and send one link for each two groups found linked;
* large nodes first compare their members with one pivot, so a group of k copies costs k comparisons; those that are one
  component by then are dropped, the others branch again; what is still large after the last level is
  compared exhaustively in pairs of blocks.

Every link is confirmed on the full sets, shingle by shingle. The number of trees follows from the recall asked for at the threshold.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from roundmm.llm.common import components, drop_stored, empty_text, free_shuffles, sliced, stored
from roundmm.llm.textnum import mix, shingles

TOKENS = 64
BRANCHES = 2
START = 3


@dataclass(frozen=True)
class Settings:
    words: int = 5
    percent: int = 75
    #: Of pairs at the threshold, even if every node on their paths stays large; where nodes are small the default misses about 2 in 100,000.
    recall: float = 0.999
    #: Members and bytes of text up to which a node counts as small.
    leaf: int = 4096
    leaf_bytes: int = 16 << 20
    levels: int = 5

    @property
    def trees(self) -> int:
        """The fewest trees that miss a pair at the threshold with a chance of at most ``1 - recall``; raises where there are too few tokens for them."""
        for trees in range(1, TOKENS // BRANCHES + 1):
            if missed(trees * BRANCHES, self.percent / 100, self.levels) <= 1 - self.recall:
                return trees
        raise ValueError(f"{TOKENS} tokens are too few for a recall of {self.recall} at {self.percent} %")

    @property
    def agree(self) -> int:
        """Fewest agreeing tokens of a pivot's candidate: 4.6 standard deviations under the threshold."""
        p = self.percent / 100
        return max(1, math.floor(TOKENS * p - 4.6 * math.sqrt(TOKENS * p * (1 - p))))


def missed(starts: int, p: float, levels: int) -> float:
    """The chance that no path of ``starts`` keeps a pair of similarity ``p``. All paths draw from the same ``TOKENS`` minima, so it is averaged over how many
    of them agree; every node is taken to stay large down to the last level, where a path goes on by ``BRANCHES`` tokens a level."""
    total = 0.0
    for x in range(TOKENS + 1):
        q = x / TOKENS
        kept = q ** (START - 1) * (1 - (1 - q) ** BRANCHES) ** (levels - 1)
        agreeing = (math.comb(x, h) * math.comb(TOKENS - x, starts - h) / math.comb(TOKENS, starts) * (1 - kept) ** h for h in range(max(0, starts - TOKENS + x), min(x, starts) + 1))
        total += math.comb(TOKENS, x) * p**x * (1 - p) ** (TOKENS - x) * sum(agreeing)
    return total


def minwise(found: np.ndarray) -> np.ndarray:
    """``TOKENS`` 32-bit minima of multiply-add hashes over a set of shingle hashes."""
    a = mix(np.arange(1, TOKENS + 1, dtype=np.uint64)) | np.uint64(1)
    b = mix(np.arange(1001, TOKENS + 1001, dtype=np.uint64))
    low = np.full(TOKENS, np.iinfo(np.uint64).max, np.uint64)
    for i in range(0, len(found), 2048):
        np.minimum(low, (found[i : i + 2048, None] * a + b).min(axis=0), out=low)
    return (low >> np.uint64(32)).astype("<u4")


def text_print(text: Column) -> Column:
    """Tells texts apart that share an id."""
    return F.unhex(F.md5(text.cast("binary")))


def profiled(docs: DataFrame, words: int = 5) -> DataFrame:
    """``doc_id, print, n_shingles, n_bytes, name, tokens``: set size, text size, a 128-bit name of the set (null: empty), its minwise tokens."""

    def profile(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in sliced(batches):
            texts = batch["text"].cast(pa.binary()).to_pylist()
            sets = shingles(texts, words)
            yield pa.RecordBatch.from_arrays(
                [
                    batch["doc_id"], batch["print"], pa.array([len(s) for s in sets], pa.int64()), pa.array([len(t) for t in texts], pa.int64()),
                    pa.array([xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None for s in sets], pa.binary()), pa.array([minwise(s).tobytes() if len(s) else None for s in sets], pa.binary()),
                ],
                names=["doc_id", "print", "n_shingles", "n_bytes", "name", "tokens"],
            )

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), empty_text().alias("text")).withColumn("print", text_print(F.col("text")))
    return rows.mapInArrow(profile, "doc_id long, print binary, n_shingles long, n_bytes long, name binary, tokens binary")


def rep_of(name: Column) -> Column:
    """64 bits of a name, by which nodes list sets. Sets that share one are told apart when their texts are joined."""
    return F.conv(F.substring(F.hex(name), 1, 15), 16, 10).cast("long")


def token_rows(column: pa.Array) -> np.ndarray:
    return np.frombuffer(b"".join(x.as_py() for x in column), "<u4").reshape(-1, TOKENS)


def step(node: np.ndarray, tokens: np.ndarray, branch: int) -> np.ndarray:
    """The children of nodes on one branch: a hash of the node chooses the position, the token there names the child."""
    place = (mix(node + np.uint64(branch + 1)) % np.uint64(TOKENS)).astype(np.int64)
    return mix(mix(node ^ np.uint64(branch + 77)) + tokens[np.arange(len(node)), place] * np.uint64(0x9E3779B97F4A7C15))


def roots(reps: DataFrame, trees: int) -> DataFrame:
    """First nodes: ``node, rep, n_bytes``; tree t branches on its own ``BRANCHES`` positions and goes on to ``START`` tokens."""

    def branch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            tokens, out = token_rows(batch["tokens"]).astype(np.uint64), []
            for spot in range(trees * BRANCHES):
                node = mix(tokens[:, spot] * np.uint64(0x9E3779B97F4A7C15) + mix(np.array([5001 + spot], np.uint64)))
                for _ in range(START - 1):
                    node = step(node, tokens, 0)
                out.append(node)
            ids, sizes = (pa.array(np.tile(batch[c].to_numpy(), len(out))) for c in ("rep", "n_bytes"))
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(out).view(np.int64)), ids, sizes], names=["node", "rep", "n_bytes"])

    return reps.mapInArrow(branch, "node long, rep long, n_bytes long")


def children(members: DataFrame) -> DataFrame:
    """Next level of ``node, rep, n_bytes, tokens``: each node on ``BRANCHES`` branches."""

    def branch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                node, tokens = batch["node"].to_numpy().view(np.uint64), token_rows(batch["tokens"]).astype(np.uint64)
                out = np.concatenate([step(node, tokens, k) for k in range(BRANCHES)])
                ids, sizes = (pa.array(np.tile(batch[c].to_numpy(), BRANCHES)) for c in ("rep", "n_bytes"))
                yield pa.RecordBatch.from_arrays([pa.array(out.view(np.int64)), ids, sizes], names=["node", "rep", "n_bytes"])

    return members.mapInArrow(branch, "node long, rep long, n_bytes long")


PAIRS = "a binary, b binary"


def agreeing(pairs: DataFrame, classes: DataFrame, least: int) -> DataFrame:
    """The pairs ``a, b`` of names whose tokens agree in at least ``least`` positions. Those left out still meet further down."""

    def kept(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                same = (token_rows(batch["t_a"]) == token_rows(batch["t_b"])).sum(axis=1) >= least
                yield batch.select(["a", "b"]).filter(pa.array(same))

    left = classes.select(F.col("name").alias("a"), F.col("tokens").alias("t_a"))
    right = classes.select(F.col("name").alias("b"), F.col("tokens").alias("t_b"))
    return pairs.join(right, "b").join(left, "a").mapInArrow(kept, PAIRS)


def shingle_set(text: bytes, words: int) -> set[tuple[bytes, ...]]:
    """The shingles themselves, not their hashes."""
    w = text.lower().split()
    return set(zip(*(w[i:] for i in range(words)), strict=False)) if len(w) >= words else {tuple(w)} if w else set()


def reaches(x: set, y: set, percent: int) -> bool:
    both = len(x & y)
    return both > 0 and 100 * both >= percent * (len(x) + len(y) - both)


def confirmed(pairs: DataFrame, texts: DataFrame, settings: Settings) -> DataFrame:
    """The pairs of names whose full shingle sets reach the threshold; the shingles are compared, no hashes of them."""

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last: tuple[bytes, set] | None = None
        for batch in batches:
            a, keep = batch["a"].to_pylist(), []
            for i in range(batch.num_rows):
                if last is None or last[0] != a[i]:
                    last = (a[i], shingle_set(batch["x_a"][i].as_py().encode(), settings.words))
                keep.append(reaches(last[1], shingle_set(batch["x_b"][i].as_py().encode(), settings.words), settings.percent))
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    left = texts.select(F.col("name").alias("a"), F.col("text").alias("x_a"))
    right = texts.select(F.col("name").alias("b"), F.col("text").alias("x_b"))
    return pairs.join(right, "b").join(left, "a").mapInArrow(check, PAIRS)


def linked(texts: list[bytes], settings: Settings) -> list[tuple[int, int]]:
    """Links between ``texts`` that join their groups. All are compared with the first; those it reaches are one group, whose
    members need no comparison with each other; every other one is compared with all, by one pass over their hashed shingles, and
    sends one link to each group that it reaches. A link is sent once the shingles themselves reach the threshold."""
    sets = shingles(texts, settings.words)
    size = np.array([len(x) for x in sets])
    starts = np.cumsum(size) - size
    _, number = np.unique(np.concatenate(sets), return_inverse=True)
    mark = np.zeros(int(number.max()) + 1, bool)
    group = np.arange(len(sets))
    out = []
    for i in range(len(sets)):
        if i and group[i] == group[0]:
            continue
        own = number[starts[i] : starts[i] + size[i]]
        mark[own] = True
        both = np.add.reduceat(mark[number], starts, dtype=np.int64)
        mark[own] = False
        near = np.flatnonzero(100 * both >= settings.percent * (size + size[i] - both))
        mine, whole = {int(group[i])}, None
        for j in near.tolist():
            if int(group[j]) in mine:
                continue
            whole = whole or shingle_set(texts[i], settings.words)
            if reaches(whole, shingle_set(texts[j], settings.words), settings.percent):
                out.append((i, j))
                mine.add(int(group[j]))
        group[np.isin(group, list(mine))] = group[0] if group[0] in mine else i
    return out


def node_links(members: DataFrame, settings: Settings) -> DataFrame:
    """Links within each small node of ``node, name, text``. Rows are sorted by node and streamed; one node is held at a time."""

    def found(held: dict[bytes, bytes]) -> list[tuple[bytes, bytes]]:
        if len(held) < 2:
            return []
        names = list(held)
        return [(min(names[i], names[j]), max(names[i], names[j])) for i, j in linked(list(held.values()), settings)]

    def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        node: int | None = None
        held: dict[bytes, bytes] = {}  # a repeated row is one member
        for batch in batches:
            out: list[tuple[bytes, bytes]] = []
            for n, name, text in zip(batch["node"].to_pylist(), batch["name"].to_pylist(), batch["text"].cast(pa.binary()).to_pylist(), strict=True):
                if n != node:
                    out += found(held)
                    node, held = n, {}
                held[name] = text
            yield pairs(out)
        yield pairs(found(held))

    def pairs(out: list[tuple[bytes, bytes]]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([p[k] for p in out], pa.binary()) for k in (0, 1)], names=["a", "b"])

    return members.repartition("node").sortWithinPartitions("node").mapInArrow(stream, PAIRS).distinct()


def blocked(members: DataFrame, settings: Settings) -> DataFrame:
    """Large nodes as pairs of blocks, each pair a small node: every two members meet in one."""
    rows, weight = F.ceil(2 * F.col("size") / F.lit(settings.leaf)), F.ceil(2 * F.col("bytes") / F.lit(settings.leaf_bytes))
    own = members.withColumn("_k", F.greatest(rows, weight, F.lit(1)).cast("int")).withColumn("_own", F.pmod(F.xxhash64("rep"), F.col("_k")).cast("int"))
    met = own.withColumn("_other", F.explode(F.expr("sequence(0, _k - 1)")))
    return met.select(F.xxhash64("node", F.least("_own", "_other"), F.greatest("_own", "_other")).alias("node"), "rep")


def met(members: DataFrame) -> DataFrame:
    """``node, rep, n_bytes, size, bytes`` of nodes with at least two members, one node for each set of members."""
    stats = members.groupBy("node").agg(
        F.count(F.lit(1)).alias("size"), F.sum("n_bytes").alias("bytes"), F.sum(F.xxhash64("rep").bitwiseAND((1 << 40) - 1)).alias("_s"), F.bit_xor(F.xxhash64("rep", F.lit(1))).alias("_x")
    ).where("size > 1")
    once = stats.groupBy("size", "bytes", "_s", "_x").agg(F.min("node").alias("node")).select("node", "size", "bytes")
    return members.join(once.hint("merge"), "node")


def same_id(named: DataFrame) -> DataFrame:
    """Links between the sets of one id: rows that share an id are one document."""
    several = named.groupBy("doc_id").agg(F.min("name").alias("a"), F.max("name").alias("_hi")).where("a <> _hi").select("doc_id", "a")
    return named.join(several, "doc_id").where("name <> a").select("a", F.col("name").alias("b")).distinct()


def near_duplicates(docs: DataFrame, settings: Settings | None = None) -> DataFrame:
    """Per row of ``docs(doc_id, text)``: ``doc_id, n_shingles, component_id, kept``.

    Texts null, empty or without words have the empty set and stand alone. A row with a null id is counted, has a null
    component and a null ``kept``. Rows that share an id are one document with all their sets: in whatever order they come, their links count for the id.
    Very long texts are read whole; other columns are ignored; an empty table gives no rows.
    """
    s = settings or Settings()
    spark = docs.sparkSession
    held = stored(profiled(docs, s.words), "profile")
    named = held.where("name is not null and doc_id is not null")
    classes = named.groupBy("name").agg(F.min(F.struct("doc_id", "print", "n_bytes")).alias("first"), F.first("tokens").alias("tokens"))
    classes = stored(classes.select("name", rep_of(F.col("name")).alias("rep"), F.col("first.doc_id").alias("doc"), F.col("first.print").alias("print"), F.col("first.n_bytes").alias("n_bytes"), "tokens"), "sets")
    reps = classes.select("rep", "n_bytes", "tokens")
    by_text = docs.select(F.col("doc_id").cast("long").alias("doc"), empty_text().alias("text")).withColumn("print", text_print(F.col("text")))
    texts = by_text.join(classes.select("name", "doc", "print"), ["doc", "print"]).select("name", "text")
    members, links, small_nodes, levels = roots(reps, s.trees), [stored(same_id(named), "links")], [], []
    for depth in range(s.levels):
        level = stored(met(members), "nodes")
        levels.append(level)
        free_shuffles(spark)
        fits = (F.col("size") <= s.leaf) & (F.col("bytes") <= s.leaf_bytes)
        small_nodes.append(level.where(fits).select("node", "rep"))
        large = level.where(~fits)
        if not large.limit(1).count():
            break
        large = large.join(classes.select("rep", "name"), "rep")
        pivots = large.groupBy("node").agg(F.min("name").alias("a"))
        star = large.join(pivots, "node").where("name <> a").select("a", F.col("name").alias("b")).distinct()
        links.append(stored(confirmed(agreeing(star, classes, s.agree), texts, s), "links"))
        labels = components(union(links))
        labelled = large.join(labels.select(F.col("node").alias("_name"), "component"), F.col("name") == F.col("_name"), "left").withColumn("_c", F.coalesce("component", "name"))
        mixed = labelled.groupBy("node").agg(F.min("_c").alias("_lo"), F.max("_c").alias("_hi")).where("_lo <> _hi").select("node")
        large = stored(large.join(mixed, "node"), "large")
        levels.append(large)
        drop_stored(labels)
        if depth == s.levels - 1:
            small_nodes.append(blocked(large, s))
        members = children(large.select("node", "name").join(classes, "name").select("node", "rep", "n_bytes", "tokens")).distinct()
    # the same joins at every size: texts are large, and a broadcast of the members would not last
    placed = union(small_nodes).join(classes.select("rep", "name", "doc", "print"), "rep")
    links.append(stored(node_links(placed.join(by_text.hint("merge"), ["doc", "print"]).select("node", "name", "text"), s), "links"))
    free_shuffles(spark)
    labels = components(union(links))
    drop_stored(*levels, *links)
    joined = classes.select("name", "doc").join(labels, F.col("name") == F.col("node"), "left").withColumn("_label", F.coalesce("component", "name"))
    least = joined.groupBy("_label").agg(F.min("doc").alias("_class"))
    found = held.select("doc_id", "n_shingles", "name").join(joined.join(least, "_label").select(F.col("name").alias("_name"), "_class"), F.col("name") == F.col("_name"), "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("_class", "doc_id"))
    return found.select("doc_id", "n_shingles", component.alias("component_id"), (component == F.col("doc_id")).alias("kept"))


def union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionAll(f)
    return out


def keep_one(docs: DataFrame, settings: Settings | None = None) -> DataFrame:
    """The rows of ``docs`` whose document is its component's smallest id, with the columns of ``docs``. Rows with a null id, and those whose text is null,
    empty or without words, stay; rows that share an id stay or go together; repeated rows stay as often as they are; an empty table stays empty."""
    gone = near_duplicates(docs, settings).where("not kept").select(F.col("doc_id").alias("_gone")).distinct()
    return docs.join(gone, F.col("doc_id") == F.col("_gone"), "left_anti")
