"""The whole pipeline on a small corpus against a plain version of every stage."""

import hashlib
import math
import random
import zlib
from collections import Counter
from itertools import combinations

import corpus_pipeline as p
import numpy as np
from tests.llm.test_exact import slow_features
from tests.llm.test_joins import distance, shingle_set, smallest

from roundmm.llm import decontam, quality

SOURCES = ("hot", "hot", "hot", "a", "b", None)


def md5(*parts):
    return hashlib.md5(":".join("" if x is None else str(x) for x in parts).encode()).hexdigest()


def unit(*parts):
    return int(md5(*parts)[:12], 16) / 16**12


def corpus():
    rng = random.Random(8)
    good = ["river", "stone", "window", "letter", "garden", "morning", "paper", "quiet", "market", "winter"]
    text = lambda: " ".join(rng.choice(good) + str(rng.randrange(40)) for _ in range(rng.randrange(12, 30)))
    marks = [text() for _ in range(3)]
    texts = []
    for i in range(90):
        if i % 6 == 5:
            texts.append(" ".join(rng.choice(["!!$$", "CLICK!", "WIN$$$", "#1#"]) for _ in range(20)))
        elif i % 9 == 4:
            mark = list(marks[i % 3])
            mark[len(mark) // 2] = "#"
            texts.append(text() + "\n" + "".join(mark).upper() + "\n" + text())
        elif i % 5 == 3:
            texts.append(texts[rng.randrange(len(texts))] + " tail")
        else:
            texts.append(text())
    texts += [None, "", "two words"]
    rows = [(i, t, "en", SOURCES[i % 6 if i % 7 else 0], 0) for i, t in enumerate(texts, 1)]
    labels = [(i, int("$" not in (t or "") and "#1#" not in (t or "")), 0) for i, t, *_ in rows if i <= 90]
    return rows, labels, marks


def keep_good(rows, labels):
    """Plain features, numbered as they come; ratio, descent and curve are tested on their own."""
    text = {i: t or "" for i, t, *_ in rows}
    taken = [(i, y) for i, y, _ in labels if zlib.crc32(str(i).encode()) % 5 != 0]
    taken.sort(key=lambda r: (r[0] * 2654435761 % 4294967296, r[0]))
    number = {}
    found = {i: np.array(sorted(number.setdefault(f, len(number)) for f in slow_features(t)), np.int64) for i, t in text.items()}
    model = quality.fitted([found[i] for i, _ in taken], np.array([1.0 if y else -1.0 for _, y in taken]))
    score = {i: model.score(f) for i, f in found.items()}
    assert min(abs(s - 0.3) for s in score.values()) > 0.01  # hashed features meet now and then: no row may hang on it
    return [r for r in rows if score[r[0]] >= 0.3]


def one_of_each(rows):
    sets = {r[0]: shingle_set(r[1]) for r in rows}
    links = [(a, b) for a, b in combinations(sets, 2) if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b])]
    first = smallest(sets, links)
    return [r for r in rows if first[r[0]] == r[0]]


def fewest_edits(item, text):
    """Fewest edits of the item against any part of the text: a free start and a free end."""
    row = np.zeros(len(text) + 1, np.int64)
    steps = np.arange(len(text) + 1)
    letters = np.frombuffer(text, np.uint8)
    for i, x in enumerate(item, 1):
        now = np.append(i, np.minimum(row[:-1] + (letters != x), row[1:] + 1))
        row = np.minimum.accumulate(now - steps) + steps
    return int(row.min())


def without_marks(rows, marks):
    fold = lambda t: (t or "").encode().translate(decontam.FOLD)
    return [r for r in rows if all(fewest_edits(fold(m), fold(r[1])) > int(0.08 * len(m)) for m in marks)]


def mixed(rows):
    n = Counter(r[3] for r in rows)
    shares = sum(k**0.7 for k in n.values())
    out = []
    for r in rows:
        rate = len(rows) * n[r[3]] ** 0.7 / shares / n[r[3]]
        u = unit(23, r[0], hashlib.md5((r[1] or "").encode()).hexdigest())
        count, total, k = 0, math.exp(-rate), 0
        while total <= u:
            count, k = count + 1, k + 1
            total += math.exp(k * math.log(rate) - rate - math.lgamma(k + 1))
        out += [r] * count
    return out


def sharded(rows, shards=40):
    seen, keyed = Counter(), []
    for i, t, _, source, _ in rows:
        raw = (t or "").encode()
        crc, size = zlib.crc32(raw), len(raw) + 16
        copy = seen[i, source, crc, size]
        seen[i, source, crc, size] += 1
        keyed.append((md5(11, i, crc, size, copy), i, crc, size, copy, source))
    n = Counter(k[-1] for k in keyed)
    at, placed = Counter(), []
    for k in sorted(keyed, key=lambda k: k[:5]):
        placed.append(((at[k[-1]] + 0.5) / n[k[-1]], *k))
        at[k[-1]] += 1
    slots, out = Counter(), []
    for place, (_, _, i, crc, size, _, source) in enumerate(sorted(placed, key=lambda k: k[:6])):
        shard = place * shards // len(placed)
        out.append((i, source, size, crc, shard, slots[shard]))
        slots[shard] += 1
    return out


def test_fewest_edits():
    for item, text in (("abc", "xxabdxx"), ("abcd", ""), ("kitten", "a sitting cat")):
        parts = [text[i:j] for i in range(len(text) + 1) for j in range(i, len(text) + 1)]
        assert fewest_edits(item.encode(), text.encode()) == min(distance(item, x) for x in parts)


def test_run_matches_plain_stages(spark, tmp_path):
    rows, labels, marks = corpus()
    for name, held, schema in (
        ("documents", rows, "doc_id long, text string, lang string, source string, n_chars long"),
        ("labels", labels, "doc_id long, quality int, toxic int"),
        ("benchmark", list(enumerate(marks)), "item_id long, text string"),
    ):
        spark.createDataFrame(held, schema).write.parquet(f"{tmp_path}/{name}.parquet")
    good = keep_good(rows, labels)
    single = one_of_each(good)
    clean = without_marks(single, marks)
    assert len(rows) > len(good) > len(single) > len(clean) > 40
    names = ("doc_id", "source", "size", "text_crc32", "shard", "slot")
    got = [tuple(r[c] for c in names) for r in p.run(spark, str(tmp_path)).collect()]
    key = lambda r: (r[4], r[5])
    assert sorted(got, key=key) == sorted(sharded(mixed(clean)), key=key)
