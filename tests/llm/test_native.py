import random
import re
import zlib
from collections import Counter, defaultdict

import pytest
from tests.llm.conftest import ODD

from roundmm.llm.licences import COVER, PHRASES, SENTENCES, SLACK, licence_report, scanned, spans
from roundmm.llm.mixing import replicated, repetition_rates
from roundmm.llm.sharding import stratified_shards


def test_shards_are_even_and_proportional(documents):
    rows = [(i, f"text {i}", "hot" if i % 3 == 0 else f"s{i % 5}") for i in range(1000)]
    got = stratified_shards(documents(rows), 8, range_rows=50).collect()
    assert sorted(r.doc_id for r in got) == list(range(1000))
    by = defaultdict(list)
    for r in got:
        by[r.shard].append(r)
        assert r.text_crc32 == zlib.crc32(f"text {r.doc_id}".encode()) and r.size == len(f"text {r.doc_id}") + 16
    assert set(map(len, by.values())) == {125}
    whole = Counter(r[2] for r in rows)
    for held in by.values():
        assert sorted(r.slot for r in held) == list(range(125))
        for source, n in Counter(r.source for r in held).items():
            assert abs(n - whole[source] / 8) <= 1.5


def test_shards_do_not_depend_on_ranges(documents):
    docs = documents([(i, "t" * (i % 7), f"s{i % 3}") for i in range(200)])
    a = {(r.doc_id, r.shard, r.slot) for r in stratified_shards(docs, 7, range_rows=5).collect()}
    assert a == {(r.doc_id, r.shard, r.slot) for r in stratified_shards(docs, 7, range_rows=10_000).collect()}


def test_shards_of_odd_rows(documents):
    docs = documents(ODD).selectExpr("*", "1 as size", "'x' as _rank", "2 as shard")
    got = stratified_shards(docs, 4).collect()
    assert len(got) == len(ODD) and [r.size for r in got if r.doc_id == 1] == [16]
    assert stratified_shards(documents([]), 4).count() == 0


def test_rates_follow_targets(documents):
    docs = documents([(i, "x", "a" if i < 30 else "b") for i in range(40)])
    got = {r.source: r.rate for r in repetition_rates(docs, {"a": 1.0, "b": 1.0}).collect()}
    assert got == pytest.approx({"a": 20 / 30, "b": 2.0})


def test_poisson_counts(documents):
    docs = documents([(i, f"t{i}", "a") for i in range(4000)])
    n = Counter(r.doc_id for r in replicated(docs, {"a": 1.0}, epochs=2.5).collect())
    mean = sum(n.values()) / 4000
    var = sum((n[i] - mean) ** 2 for i in range(4000)) / 4000
    assert abs(mean - 2.5) < 0.12 and abs(var - 2.5) < 0.25


def test_large_rates_do_not_underflow(documents):
    got = replicated(documents([(1, "x", "a"), (2, "y", "b")]), {"a": 1.0, "b": 0.0}, epochs=800.0).collect()
    assert {r.doc_id for r in got} == {1} and abs(len(got) - 1600) < 200


def test_mixture_of_odd_rows(documents):
    docs = documents(ODD).selectExpr("*", "7 as rate", "8 as _copy", "9 as `a.b`")
    got = replicated(docs, epochs=3.0)
    assert got.columns == docs.columns and got.count() > 0 and {r.rate for r in got.collect()} == {7}
    assert replicated(documents([])).count() == 0


def licences(documents, *texts):
    return {r.doc_id: r for r in licence_report(documents(list(enumerate(texts)))).collect()}


def test_licence_places(documents):
    got = licences(documents, "MIT License, mit-license mit  x license", "no licence", "Gnu General Public License", "gnu general license", "CC BY cc\u00e9 by")
    assert (got[0].n_base, got[0].first_word, got[0].last_word, got[0].base_labels, got[0].n_words) == (2, 0, 2, "mit", 7)
    assert (got[1].n_base, got[1].first_word, got[1].labels, got[1].score) == (0, None, "", 0.0)
    assert got[2].base_labels == "gpl" and got[3].base_labels == "" and got[4].base_labels == "cc-by" and got[4].n_base == 1


def test_licence_sentences_with_missing_words(documents):
    got = licences(documents, "x Licensed under the Apache License, Version 2.0 y", "Licensed under an Apache License, Version 2.0", "Licensed to none")
    assert got[0].labels == "apache,apache-2.0" and got[0].score == 1.0
    assert "apache-2.0" in got[1].labels and got[2].labels == ""


def test_licence_spans_are_aligned(documents):
    # every gram votes, on neighbouring diagonals, but no stretch of the text is the sentence
    got = licences(documents, "released under under the the mit mit license", "released under mit license", "so released under the mit license mit license mit license")
    assert got[0].labels == "mit" and got[0].score == 1.0
    assert got[1].labels == "mit" and got[2].labels == "mit,mit-notice"
    got = licences(documents, "licensed under apache license version 2 0", "licensed under the new apache license version 2 0", "licensed under the new big apache license version 3 0")
    assert ["apache-2.0" in got[i].labels for i in range(3)] == [True, True, False]


def word_edits(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


def plain_spans(text):
    words = [w for w in re.split(r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+", text) if w]
    for t in PHRASES + SENTENCES:
        n = len(t.words)
        votes = defaultdict(set)
        for d in range(len(words) - 1):
            for p in range(n - 1):
                if tuple(words[d : d + 2]) == t.words[p : p + 2]:
                    votes[d - p].add(p)
        if t.exact:
            yield from ((t.label, o, 1.0, 0) for o, ps in votes.items() if len(ps) == n - 1)
            continue
        runs = []
        for o in sorted(votes):
            if not runs or o - runs[-1][-1] > SLACK:
                runs.append([])
            runs[-1].append(o)
        for run in runs:
            cover = len(set().union(*(votes[o] for o in run))) / (n - 1)
            if cover >= COVER:
                far, at = min((word_edits(words[max(o, 0) : e + n], t.words), o) for o in run for e in run if abs(e - o) <= t.budget)
                if far <= t.budget:
                    yield t.label, at, cover, far


def test_licence_spans_against_plain_python(documents):
    draw = random.Random(5)
    texts = []
    for _ in range(250):
        words = []
        for t in draw.choices(PHRASES + SENTENCES, k=draw.randint(1, 4)):
            for w in t.words:
                r = draw.random()
                words += [] if r < 0.05 else ["other"] if r < 0.1 else [w, w] if r < 0.17 else [w, "more"] if r < 0.22 else [w]
        texts.append(" ".join(words))
    want = sorted((i, *s) for i, text in enumerate(texts) for s in plain_spans(text))
    templates = PHRASES + SENTENCES
    got = spans(scanned(documents(list(enumerate(texts))), ["doc_id"], templates), ["doc_id"], templates)
    assert sorted((r.doc_id, r.label, r.start, r.cover, r.edits) for r in got.collect()) == want
    assert sum(1 for w in want if w[4]) > 30


def test_licences_of_odd_rows(documents):
    docs = documents([*ODD, (9, "mit license " * 3000)]).selectExpr("*", "1 as words", "2 as gram", "3 as offset")
    got = licence_report(docs).collect()
    assert len(got) == len(ODD) + 1
    many = next(r for r in got if r.doc_id == 9)
    assert (many.n_base, many.last_word) == (3000, 5998)
    assert licence_report(documents([])).count() == 0
    assert {p.label for p in PHRASES} == {"gpl", "apache", "cc-by", "mit"}
