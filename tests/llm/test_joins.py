import random
import re
from dataclasses import replace
from itertools import combinations

import numpy as np
import pytest
from tests.llm.conftest import ODD

from roundmm.llm import decontam, linededup, neardup
from roundmm.llm.common import components


def smallest(ids, links):
    parent = {i: i for i in ids}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in links:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    return {i: find(i) for i in ids}


def test_components(spark):
    rng = random.Random(3)
    links = [(rng.randrange(300), rng.randrange(300)) for _ in range(200)] + [(1000 + i, 1001 + i) for i in range(40)]
    ids = {x for a, b in links if a != b for x in (a, b)}
    got = {r.node: r.component for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == smallest(ids, links)
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def shingle_set(text):
    w = [x for x in re.split(rb"[\x20\x09-\x0D]+", (text or "").encode().lower()) if x]
    return frozenset(tuple(w[i : i + 5]) for i in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)] if w else [])


def corpus(seed, families=12, size=9):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(5))
    rows = []
    for _ in range(families):
        base = [word() for _ in range(rng.randrange(4, 160))]
        for _ in range(rng.randrange(1, size)):
            w = list(base)
            for _ in range(rng.randrange(0, 4)):
                w[rng.randrange(len(w))] = word()
            rows.append(" ".join(w))
    rows += rows[:5] + [rows[0].upper()]
    rng.shuffle(rows)
    return list(enumerate(rows, 10))


@pytest.mark.parametrize("settings", [neardup.Settings(), neardup.Settings(leaf=3, levels=3), neardup.Settings(leaf=2, levels=1)])
def test_near_duplicates_match_brute_force(documents, settings):
    rows = corpus(5)
    sets = {i: shingle_set(t) for i, t in rows}
    links = [(a, b) for a, b in combinations(sets, 2) if sets[a] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b])]
    want = smallest(sets, links)
    got = {r.doc_id: r for r in neardup.near_duplicates(documents(rows), settings).collect()}
    assert {i: r.n_shingles for i, r in got.items()} == {i: len(s) for i, s in sets.items()}
    assert {i: r.component_id for i, r in got.items()} == want
    assert all(r.kept == (r.doc_id == r.component_id) for r in got.values())


def test_near_duplicates_of_odd_rows(documents):
    docs = documents(ODD).selectExpr("*", "1 as node", "2 as tokens", "3 as kept")
    got = neardup.near_duplicates(docs).collect()
    assert len(got) == len(ODD)
    assert all(r.n_shingles == 0 and r.component_id == r.doc_id for r in got if r.doc_id in (1, 2))
    assert all(r.component_id is None and r.kept is None for r in got if r.doc_id is None)
    kept = neardup.keep_one(docs)
    assert kept.columns == docs.columns and kept.count() == len(ODD)
    assert neardup.near_duplicates(documents([])).count() == 0


def test_keep_one_leaves_one_of_a_group(documents):
    text = " ".join(f"w{i}" for i in range(60))
    got = neardup.keep_one(documents([(5, text), (3, text + " x"), (9, text), (4, "other words than these ones")]))
    assert sorted(r.doc_id for r in got.collect()) == [3, 4]


def distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        row, last = [i], row
        for j, y in enumerate(b, 1):
            row.append(min(last[j] + 1, row[-1] + 1, last[j - 1] + (x != y)))
    return row[-1]


def edited(rng, text, n, letters):
    out = list(text)
    for _ in range(n):
        k, op = rng.randrange(len(out) + 1), rng.random()
        if op < 0.4:
            out.insert(k, rng.choice(letters))
        elif out and op < 0.7:
            out.pop(min(k, len(out) - 1))
        elif out:
            out[min(k, len(out) - 1)] = rng.choice(letters)
    return "".join(out)


def test_banded_distance():
    rng = random.Random(1)
    for _ in range(4000):
        a = "".join(rng.choice("abc") for _ in range(rng.randrange(14)))
        b = edited(rng, a, rng.randrange(5), "abc")
        for limit in (0, 1, 2, 3):
            assert linededup.within(a, b, limit) == (distance(a, b) <= limit), (a, b, limit)


def line_classes(rows):
    """Least name of each linked line's class, from link rows."""
    pairs = [(r.a, r.b) for r in rows]
    return smallest({bytes(x) for p in pairs for x in p}, [(bytes(a), bytes(b)) for a, b in pairs])


SMALL_NODES = [{}, {"leaf": 3, "hold": 5}, {"leaf": 6, "hold": 10_000}]


@pytest.mark.parametrize("nodes", SMALL_NODES)
def test_line_classes_match_brute_force(documents, nodes):
    rng = random.Random(7)
    lines = ["".join(rng.choice("abcdé ") for _ in range(rng.randrange(18, 60))) for _ in range(40)]
    lines += [edited(rng, rng.choice(lines), rng.randrange(1, 4), "abcdé ") for _ in range(120)]
    docs = documents([(k, "\n".join(lines[k * 4 : k * 4 + 4])) for k in range(40)])
    held = sorted({x.strip() for x in lines if len(x.strip()) >= 20})
    near = [(linededup.line_name(a), linededup.line_name(b)) for a, b in combinations(held, 2) if distance(a, b) <= 2]
    found = linededup.links(docs.select("text"), linededup.Settings(**nodes)).collect()
    assert line_classes(found) == smallest({x for p in near for x in p}, near) and near
    assert {(bytes(r.a), bytes(r.b)) for r in found} <= {tuple(sorted(p)) for p in near}


@pytest.mark.parametrize("nodes", SMALL_NODES)
def test_classes_with_edits_by_length(documents, nodes):
    rng = random.Random(8)
    lines = ["".join(rng.choice("abcdé ") for _ in range(rng.randrange(7, 26))) for _ in range(60)]
    lines += [edited(rng, rng.choice(lines), rng.randrange(1, 4), "abcdé ") for _ in range(140)]
    docs = documents([(k, "\n".join(lines[k * 4 : k * 4 + 4])) for k in range(50)])
    budget = lambda a, b: (n := min(len(a), len(b))) >= 20 and 2 or int(n >= 10)
    near = [(a, b) for a, b in combinations(sorted({x.strip() for x in lines}), 2) if 0 < distance(a, b) <= budget(a, b)]
    assert {tuple(sorted(map(len, p))) for p in near} >= {(19, 20)} and any(len(a) < 19 for a, _ in near)
    want = [(linededup.line_name(a), linededup.line_name(b)) for a, b in near]
    found = linededup.links(docs.select("text"), replace(linededup.BY_LENGTH, **nodes)).collect()
    assert line_classes(found) == smallest({x for p in want for x in p}, want)


def test_a_group_of_near_copies_sends_few_links(documents):
    """2000 lines within two edits of one: the links found are of the order of the lines, and the class is whole."""
    rng = random.Random(4)
    base = "".join(rng.choice("abcdefgh ") for _ in range(50)).strip() + " end"
    lines = sorted({edited(rng, base, rng.randrange(1, 3), "abcdefghxyz").strip() for _ in range(3200)} - {base})
    lines = [x for x in lines if distance(base, x) <= 2][:2000]
    assert len(lines) == 2000
    for held, settings in ((lines, linededup.Settings()), (lines[::10], linededup.Settings(leaf=50, hold=100))):
        found = linededup.links(documents([(k, "\n".join([base, *held[k::20]])) for k in range(20)]).select("text"), settings).collect()
        assert len(set(line_classes(found).values())) == 1 and len(line_classes(found)) == len(held) + 1
        assert len(found) < 30 * len(held)
    got = linededup.line_report(documents([(k, "\n".join([base, *lines[k::200]])) for k in range(20)])).where("doc_id = 3").first()
    assert (got.n_links, got.class_id, got.n_kept) == (11 * 200, 0, 0)


@pytest.mark.parametrize("nodes", SMALL_NODES)
def test_every_link_of_a_line_is_counted(documents, nodes):
    """Lines that reach each other by several steps: each counts the lines within its own edits, also those that other links join already."""
    rng = random.Random(9)
    base = "".join(rng.choice("abcdé ") for _ in range(30)) + "."
    lines = sorted({edited(rng, base, rng.randrange(1, 4), "abcdé").strip() for _ in range(60)} | {edited(rng, base[:17] + "x", rng.randrange(1, 3), "abcdé").strip() for _ in range(40)})
    budget = lambda a, b: (n := min(len(a), len(b))) >= 20 and 2 or int(n >= 10)
    want = [sum(a != b and distance(a, b) <= budget(a, b) for b in lines) for a in lines]
    got = {r.doc_id: r for r in linededup.line_report(documents(list(enumerate(lines))), replace(linededup.BY_LENGTH, **nodes)).collect()}
    assert [got[k].n_pairs for k in range(len(lines))] == want
    assert sum(want) > 2 * len(lines) and any(got[k].n_links > n > 0 for k, n in enumerate(want))


def test_rows_that_share_an_id_lose_their_own_lines(documents):
    shared, own = "this line stands in several of the texts", "only the second text of the id holds this one"
    docs = documents([(1, shared), (1, f"{own}\n{shared}"), (2, shared), (2, shared)])
    got = sorted(r.text for r in linededup.without_repeats(docs).collect())
    assert sum(own in x for x in got) == 1 and sum(shared in x for x in got) == 1


def test_line_names_take_any_text():
    assert linededup.line_name("\ud800 alone") and linededup.parities(["\ud800 alone"]).shape == (1,)


def test_short_lines_join_as_equals(documents):
    docs = documents([(1, "Les.\n\nalone"), (2, " Les. \n\nLet."), (3, "And ornd. And\nLes."), (4, "And ornd, And")])
    got = {r.doc_id: (r.n_lines, r.n_kept, r.n_short, r.n_short_kept, r.n_links) for r in linededup.line_report(docs).collect()}
    assert got == {1: (0, 0, 2, 2, 0), 2: (0, 0, 2, 1, 0), 3: (0, 0, 2, 1, 1), 4: (0, 0, 1, 0, 1)}
    texts = {r.doc_id: r.text for r in linededup.without_repeats(docs).collect()}
    assert texts == {1: "Les.\n\nalone", 2: "\nLet.", 3: "And ornd. And", 4: ""}


def test_document_classes_are_components(documents):
    rng = random.Random(11)
    lines = [f"{k:03d} " + "".join(rng.choice("abcdefgh ") for _ in range(30)) + "." for k in range(60)]
    rows = [(k, [rng.choice(lines) for _ in range(rng.randrange(0, 4))] + [f"{k} alone"]) for k in range(100, 60, -1)]
    rows += [(10, ["L" * 30, "own of ten"]), (20, ["L" * 30, "M" * 8]), (3, ["M" * 8]), (None, [lines[0], lines[1]]), (300, ["only the null document"]), (None, ["only the null document"])]
    want = smallest([d for d, _ in rows if d], [(a, b) for (a, x), (b, y) in combinations([r for r in rows if r[0]], 2) if set(x) & set(y)] + [(a, b) for a, b in combinations([d for d, x in rows if d and set(x) & {lines[0], lines[1], "only the null document"}], 2)])
    got = {r.doc_id: r.class_id for r in linededup.line_report(documents([(d, "\n".join(x)) for d, x in rows])).collect()}
    assert got.pop(None) == want[300] and got == want
    assert got[10] == got[20] == got[3] == 3


def test_line_report(documents):
    one, near, other = "this line is long enough to count", "this line is long enough to counts", "a line that stands all alone here"
    got = {r.doc_id: r for r in linededup.line_report(documents([(2, f"{one}\nshort\n{other}"), (1, near), (3, f"{one}\n{one}")])).collect()}
    assert [(got[i].n_lines, got[i].n_kept, got[i].n_links, got[i].class_id) for i in (1, 2, 3)] == [(1, 1, 1, 1), (2, 1, 1, 1), (2, 0, 2, 1)]
    texts = {r.doc_id: r.text for r in linededup.without_repeats(documents([(2, f"{one}\nshort\n{other}"), (1, near), (3, f"{one}\n{one}")])).collect()}
    assert texts == {1: near, 2: f"short\n{other}", 3: ""}


def test_lines_of_odd_rows(documents):
    docs = documents(ODD).selectExpr("*", "1 as class", "2 as id")
    got = linededup.line_report(docs).collect()
    assert len(got) == len({r[0] for r in ODD})
    assert linededup.without_repeats(docs).columns == docs.columns
    assert linededup.line_report(documents([])).count() == 0


def items(spark, rows):
    return spark.createDataFrame(rows, "item_id long, text string")


def test_alignment_matches_brute_force():
    rng = random.Random(4)
    for _ in range(400):
        a = "".join(rng.choice("ab") for _ in range(rng.randrange(1, 12)))
        w = "".join(rng.choice("ab") for _ in range(rng.randrange(0, 25)))
        free = min(distance(a, w[i:j]) for i in range(len(w) + 1) for j in range(i, len(w) + 1))
        held = min(distance(a, w[:j]) for j in range(len(w) + 1))
        for best, anchored in ((free, False), (held, True)):
            edits, stop = decontam.aligned(a.encode(), w.encode(), 4, anchored)
            assert (edits == best) if best <= 4 else edits > 4
            if anchored and best <= 4:
                assert distance(a, w[:stop]) == best


def test_planted_passages(spark, documents):
    rng = random.Random(9)
    letters = "abcdefghij "
    text = lambda n: "".join(rng.choice(letters) for _ in range(n))
    marks = [(k, text(rng.randrange(90, 300))) for k in range(12)]
    docs, want = [], set()
    for i in range(80):
        body = text(rng.randrange(0, 800))
        if i % 4 == 0:
            k = rng.randrange(12)
            m = marks[k][1].strip()
            # substitutions only, so that the planted distance is at most their number
            e = rng.randrange(0, decontam.budget(len(m)) // 2 + 1)
            put = list(m)
            for at in rng.sample(range(len(m)), e):
                put[at] = "z"
            body = f"{body}\n{''.join(put).upper()}\n{text(30)}"
            want.add((i, k))
        docs.append((i, body))
    got = decontam.contamination(documents(docs), items(spark, marks)).collect()
    assert {(r.doc_id, r.item_id) for r in got} == want
    for r in got:
        assert distance(dict(docs)[r.doc_id].encode()[r.begin : r.end].decode().lower().replace("\n", " "), dict(marks)[r.item_id].strip()) == r.edits <= decontam.budget(len(dict(marks)[r.item_id].strip()))
    kept = decontam.decontaminated(documents(docs), items(spark, marks))
    assert {r.doc_id for r in kept.collect()} == set(range(80)) - {i for i, _ in want}


def test_all_edits_within_the_budget_are_found(spark, documents):
    """Insertions and deletions shift diagonals: the bands must still gather enough q-grams."""
    rng = random.Random(2)
    m = "".join(rng.choice("abcdefghijklmnopqrstuvwxyz ") for _ in range(200)).strip()
    docs = [(i, "x" * rng.randrange(50) + edited(rng, m, decontam.budget(len(m)) - 2, "abcdefgh") + "y" * 40) for i in range(60)]
    got = {r.doc_id for r in decontam.contamination(documents(docs), items(spark, [(1, m)])).collect()}
    assert got == set(range(60))


def test_blocks_of_items(spark, monkeypatch, documents):
    rows = [(k, f"item number {k} " + "abcdefg hij klm " * 8 + str(k) * 30) for k in range(6)]
    assert len(list(decontam.blocks(items(spark, rows), 300))) > 2
    assert len(list(decontam.blocks(items(spark, rows)))) == 1


def test_contamination_of_odd_rows(spark, documents):
    marks = items(spark, [(1, None), (2, ""), (3, "short"), (None, "the same row twice and a second line that is long enough"), (4, "word " * 60)])
    docs = documents(ODD).selectExpr("*", "1 as item_id", "2 as begin")
    got = decontam.contamination(docs, marks).collect()
    assert {(r.doc_id, r.item_id) for r in got} == {(3, None), (4, 4)} and sum(r.doc_id == 3 for r in got) == 2
    assert decontam.decontaminated(docs, marks).columns == docs.columns
    assert decontam.contamination(documents([]), marks).count() == 0
    assert decontam.contamination(docs, marks.limit(0)).count() == 0
    assert np.array_equal(decontam.build([]).grams, np.empty(0, np.uint64))


def test_short_items_are_found(spark, documents):
    """Items of every length with all the edits of their budget; items of a few bytes only as words."""
    rng = random.Random(6)
    marks = [(m, "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(m))) for m in [3, 5, *range(6, 50)]]
    put = lambda m: list(m)
    docs = []
    for m, item in marks:
        out = put(item)
        for at in rng.sample(range(m), decontam.budget(m)):
            out[at] = "#"
        docs.append((m, f"0000 1111 {''.join(out)} 2222"))
    docs.append((100, "0" + marks[0][1] + "0"))
    got = {(r.doc_id, r.item_id) for r in decontam.contamination(documents(docs), items(spark, marks)).collect()}
    assert got == {(m, m) for m, _ in marks}
