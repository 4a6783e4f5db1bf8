"""Rows that share ids, frequent ids, words made to collide, bounds of training: the results are those of brute force."""

import random
from collections import Counter
from itertools import permutations

import numpy as np
import pytest
from pyspark.sql import functions as F

from roundmm.llm import common, neardup, quality
from roundmm.llm.common import remainder
from roundmm.llm.media import chunk_store
from roundmm.llm.sharding import stratified_shards
from roundmm.llm.textnum import joined, words


def thue_morse(n, a, b):
    return "".join(a if bin(k).count("1") % 2 == 0 else b for k in range(n))


def test_words_that_cancel_in_a_polynomial_differ(documents):
    x, y = thue_morse(2048, "a", "b"), thue_morse(2048, "b", "a")
    _, _, found = words(joined([x.encode(), y.encode()])[0])
    assert found[0] != found[1]
    got = neardup.near_duplicates(documents([(1, x), (2, y)])).collect()
    assert all(r.kept and r.component_id == r.doc_id for r in got)


def test_word_hashes_follow_the_words():
    rng = random.Random(1)
    text = [bytes(rng.choice(b"ab") for _ in range(rng.randrange(1, 20))) for _ in range(3000)]
    _, _, found = words(joined([b" ".join(text)])[0])
    assert len(set(zip(text, found.tolist()))) == len(set(text)) == len(set(found.tolist()))


@pytest.mark.parametrize("order", [(0, 1, 2, 3), (1, 0, 2, 3), (3, 2, 1, 0)])
def test_rows_that_share_an_id_link_as_one_document(documents, order):
    t1, t2 = (" ".join(f"{c}{i}" for i in range(60)) for c in "pq")
    rows = [(1, t1), (1, t2), (5, t2 + " x"), (6, t1 + " x"), ]
    got = {(r.doc_id, r.component_id, r.kept) for r in neardup.near_duplicates(documents([rows[k] for k in order])).collect()}
    assert got == {(1, 1, True), (5, 1, False), (6, 1, False)}


def test_trees_reach_the_recall_or_raise():
    s = neardup.Settings()
    assert neardup.missed(s.trees * neardup.BRANCHES, 0.75, s.levels) <= 1 - s.recall < neardup.missed((s.trees - 1) * neardup.BRANCHES, 0.75, s.levels)
    with pytest.raises(ValueError, match="too few"):
        neardup.Settings(percent=40).trees  # noqa: B018


def test_measured_paths_follow_the_formula():
    """Pairs of sets at the threshold: how often no first path keeps them, measured on the minima themselves."""
    rng = np.random.default_rng(5)
    missed, pairs, starts = 0, 400, 4
    for _ in range(pairs):
        both, own = rng.integers(0, 2**63, 300).astype(np.uint64), rng.integers(0, 2**63, 100).astype(np.uint64)
        a, b = (neardup.minwise(np.sort(np.concatenate((both, x)))).astype(np.uint64)[None] for x in (own[:50], own[50:]))
        nodes = []
        for t in (a, b):
            out = []
            for spot in range(starts):
                node = t[:, spot] * np.uint64(0x9E3779B97F4A7C15) + np.uint64(spot)
                for _ in range(neardup.START - 1):
                    node = neardup.step(node, t, 0)
                out.append(int(node[0]))
            nodes.append(out)
        missed += not any(x == y for x, y in zip(*nodes, strict=True))
    want = neardup.missed(starts, 0.75, 1)
    assert abs(missed / pairs - want) < 4 * (want / pairs) ** 0.5


def test_copies_are_spread_over_shards(documents):
    """Two copies of a row share one of ten shards about one time in ten."""
    rows = [(i, f"text {i}", f"s{i % 3}") for i in range(1500)]
    got = stratified_shards(documents(rows + rows), 10, range_rows=100).collect()
    shards = {}
    for r in got:
        shards.setdefault(r.doc_id, []).append(r.shard)
    together = sum(len(set(x)) == 1 for x in shards.values())
    assert all(len(x) == 2 for x in shards.values()) and 90 < together < 220


def test_a_frequent_id_has_many_keys(documents, monkeypatch):
    monkeypatch.setattr("roundmm.llm.sharding.LOT", 7)
    got = stratified_shards(documents([(7, "same", "a")] * 500 + [(None, "", None)] * 100), 6, range_rows=20).collect()
    assert Counter(r.shard for r in got) == Counter({k: 100 for k in range(6)})
    assert all(sorted(r.slot for r in got if r.shard == k) == list(range(100)) for k in range(6))


def test_training_is_bounded(spark, documents, monkeypatch):
    labels = spark.createDataFrame([(i, i % 2, 0) for i in range(60)], "doc_id long, quality int, toxic int")
    docs = documents([(3, f"copy number {k % 5}") for k in range(400)] + [(i, f"text {'good' if i % 2 else 'bad'} {i} " + "w " * 50) for i in range(60)])
    sample = quality.sample_for_training(docs, labels, "quality", remainder(5) != 0, 40).collect()
    assert len(sample) == len({r.doc_id for r in sample}) == 40
    monkeypatch.setattr(quality, "TRAIN_BYTES", 1500)
    seen = []
    monkeypatch.setattr(quality, "fitted", lambda rows, y: seen.append(sum(4 * len(r) for r in rows)))
    quality.train(docs, labels, remainder(5) != 0)
    assert 0 < seen[0] <= 1500


def test_small_counts_bytes(spark):
    wide = spark.range(10).select(F.repeat(F.lit("x"), 1000).alias("t"), F.array_repeat(F.lit(1), 500).alias("a"))
    hinted = lambda df: "broadcast" in df._jdf.queryExecution().analyzed().toString().lower()
    assert hinted(common.small(wide)) and not hinted(common.small(wide, max_bytes=12_000)) and not hinted(common.small(wide, max_rows=9))


def test_equal_rows_are_stored_once(documents):
    base = " ".join(f"word{i * i % 977}" for i in range(4000))
    store = chunk_store(documents([(1, base), (1, base), (2, base), (3, "other"), (3, "other")])).collect()
    held = [p["digest"] for r in store for p in r["parts"]]
    assert len(store) == 2 and len(held) == len(set(held))


# ---- the classifier against a plain version


def slow_features(text):
    """Words, word pairs, shapes and their pairs and triples, as strings."""
    kind = lambda b: 1 if 97 <= b <= 122 or b >= 128 else 2 if 65 <= b <= 90 else 3 if 48 <= b <= 57 else b
    raw = text.encode().split()
    shape = [tuple(k for n, k in enumerate(map(kind, w)) if n == 0 or k != kind(w[n - 1])) for w in raw]
    low = [w.lower() for w in raw]
    grams = lambda x, n: [tuple(x[i : i + n]) for i in range(len(x) - n + 1)]
    return {(name, n, g) for name, x, most in (("w", low, 2), ("s", shape, 3)) for n in range(1, most + 1) for g in grams(x, n)}


def test_features_are_those_of_a_plain_version():
    rng = random.Random(3)
    texts = [" ".join(rng.choice(["the", "The", "A1!", "x-y", "é", "99", "B2?"]) for _ in range(rng.randrange(0, 40))) for _ in range(60)]
    fast = quality.features([t.encode() for t in texts], bits=40)
    slow = [slow_features(t) for t in texts]
    assert [len(x) for x in fast] == [len(x) for x in slow]
    for i, j in permutations(range(0, 60, 7), 2):
        assert len(set(fast[i].tolist()) & set(fast[j].tolist())) == len(slow[i] & slow[j])


def test_log_count_ratios_by_hand():
    rows, y = [np.array([0, 1]), np.array([1, 2]), np.array([1])], np.array([True, False, True])
    good, bad = np.array([2, 3, 1]) / 6, np.array([1, 2, 2]) / 5
    assert quality.log_count_ratio(rows, y, 3) == pytest.approx(np.log(good / bad))


def test_dual_descent_reaches_the_hinge_optimum():
    """Against projected gradient steps on the dual, many of them: the same primal objective."""
    rng = np.random.default_rng(2)
    rows = [np.unique(rng.integers(0, 30, 8)) for _ in range(60)]
    y = np.where(rng.random(60) < 0.5, -1.0, 1.0)
    ratio = rng.normal(size=30)
    x = np.zeros((60, 31))
    for i, r in enumerate(rows):
        x[i, r], x[i, 30] = ratio[r] / len(r) ** 0.5, 1.0
    q = (x * y[:, None]) @ (x * y[:, None]).T
    alpha, step = np.zeros(60), 1 / np.linalg.eigvalsh(q).max()
    for _ in range(60_000):
        alpha = np.clip(alpha - step * (q @ alpha - 1), 0, 1)
    loss = lambda w: 0.5 * w @ w + np.maximum(0, 1 - y * (x @ w)).sum()
    w, b = quality.hinge_descent(rows, y, ratio, rounds=400)
    assert loss(np.append(w / ratio, b)) == pytest.approx(loss((alpha * y) @ x), rel=1e-3)
