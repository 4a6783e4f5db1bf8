import numpy as np
import pytest
from pyspark.sql import functions as F
from tests.llm.conftest import ODD

from roundmm.llm import quality, toxicity
from roundmm.llm.common import remainder


def labelled(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, quality int, toxic int")


def test_hinge_descent_separates():
    rng = np.random.default_rng(0)
    rows = [np.unique(np.concatenate([rng.integers(0, 400, 20), [500 if k % 2 else 501]])) for k in range(300)]
    y = np.array([1.0 if k % 2 else -1.0 for k in range(300)])
    model = quality.fitted(rows, y, bits=10)
    right = sum((model.score(r) > 0.5) == (v > 0) for r, v in zip(rows, y, strict=True))
    assert right >= 295


def test_features_do_not_depend_on_slices():
    texts = [b"A b c!! 12", b"", b"word " * 400, "É ñ".encode()]
    once = quality.features(texts)
    assert all(np.array_equal(a, b) for a, b in zip(once, [quality.features([t])[0] for t in texts], strict=True))
    assert len(once[1]) == 0


@pytest.fixture(scope="module")
def judged(spark, documents):
    good = [(i, f"plain words number {i} go on in calm order with more of them {i * 7}") for i in range(120)]
    bad = [(200 + i, f"BUY!! NOW!! {i}$$$ CLICK!!! {i * 3}%%% WIN!!") for i in range(60)]
    labels = labelled(spark, [(i, 1, 0) for i in range(120)] + [(200 + i, 0, 0) for i in range(60)])
    return documents(good + bad), labels


def test_quality_on_held_out_rows(judged):
    docs, labels = judged
    model = quality.train(docs, labels, remainder(5) != 0)
    held = quality.scored(docs, model).where(remainder(5) == 0).select("doc_id", "score").collect()
    assert len(held) > 20 and all((r.score >= 0.3) == (r.doc_id < 200) for r in held)


def test_quality_of_odd_rows(documents, judged):
    docs, labels = judged
    model = quality.train(docs, labels, remainder(5) != 0)
    odd = documents(ODD).withColumn("label", F.lit(1)).withColumn("score", F.lit("x"))
    got = quality.scored(odd, model).collect()
    assert len(got) == len(ODD) and all(0 <= r.score <= 1 for r in got)
    kept = quality.keep_good(odd, labels, remainder(5) != 0)
    assert kept.columns == odd.columns and {r.score for r in kept.collect()} <= {"x"}
    assert quality.scored(documents([]), model).count() == 0


def test_quality_without_labels(spark, documents):
    docs = documents([(1, "a"), (2, "b")])
    assert quality.keep_good(docs, labelled(spark, []), remainder(5) != 0).count() == 2


@pytest.fixture(scope="module")
def toxic(spark, documents):
    plain = "the way of the river goes on and the trees in the valley stand as they did in the year before so we went on to the town".split()
    rng = np.random.default_rng(1)
    rows, labels = [], []
    for i in range(600):
        words = [plain[k] for k in rng.integers(0, len(plain), 40)] + [f"w{chr(97 + i % 26)}{chr(97 + i // 26)}"]
        if i % 4 == 0:
            words[int(rng.integers(0, 40))] = ["idiot", "moron", "scum", "worthless"][i // 4 % 4]
        rows.append((i, " ".join(words)))
        labels.append((i, 1, int(i % 4 == 0)))
    return documents(rows), labelled(spark, labels)


def test_toxicity_on_held_out_and_disguised_rows(documents, toxic):
    docs, labels = toxic
    model = toxicity.train(docs, labels, remainder(3) != 1)
    held = toxicity.scored(docs, model).where(remainder(3) == 1).collect()
    assert len(held) > 120 and all((r.score >= 0.7) == (r.doc_id % 4 == 0) for r in held)
    hidden = ["you 1d10t of the river", "the m0r0n went on", "so i d i o t we went", "the w.o.r.t.h.l.e.s.s town", "an idiooooot of the town", "the sc*m of the valley"]
    clean = ["the year 2023 of the river", "we went to a b and on", "the 3rd tree", "a-b-c of the town"]
    got = {r.doc_id: r.score for r in toxicity.scored(documents(list(enumerate(hidden + clean))), model).collect()}
    assert all(got[i] >= 0.7 for i in range(len(hidden))), got
    assert all(got[i] < 0.7 for i in range(len(hidden), len(got))), got


def test_doubled_letters_edge_signs_and_spaced_signs(documents, toxic):
    docs, labels = toxic
    restorer = toxicity.Restorer(toxicity.language_model(docs))
    for text, word in (("!diot", "idiot"), ('"(!diot)".', "idiot"), ("iidiiot", "idiot"), ("sscuumm", "scum"), ("i d ! o t", "idiot"), ("m - o - r - o - n", "moron"), ("! d i o t", "idiot")):
        assert word in restorer.words(f"the {text} town"), (text, restorer.words(f"the {text} town"))
    assert {"town", "and", "trees"} <= set(restorer.words("a town! (and) trees"))
    model = toxicity.train(docs, labels, remainder(3) != 1)
    hidden = ["you !diot of the river", "the sscuumm went on", "so i d ! o t we went", "the m - o - r - o - n of the town"]
    clean = ["the town! (and the trees) of the valley*", "see a - b - c of the town", "* a b * the river !"]
    got = {r.doc_id: r.score for r in toxicity.scored(documents(list(enumerate(hidden + clean))), model).collect()}
    assert all((got[i] >= 0.7) == (i < len(hidden)) for i in got), got


def test_trigram_counts_match_brute_force(documents):
    texts = ["Ab ab", "b", "", None]
    got = {r.gram: r.n for r in toxicity.trigram_counts(documents(list(enumerate(texts)))).collect()}
    table, want = toxicity.symbol_table(), {}
    s = [int(table[ord(c)]) for c in "  ".join(["", *[x or "" for x in texts], ""]).lower()]
    n = toxicity.SYMBOLS
    total = sum(got.values())
    # texts are joined per task, so borders may differ by a few boundary trigrams; letters may not
    for a, b, c in zip(s, s[1:], s[2:], strict=False):
        key = ((0 if b == 0 else a) * n + b) * n + c
        want[key] = want.get(key, 0) + 1
    assert {k: v for k, v in got.items() if k} == {k: v for k, v in want.items() if k} and total > 0


def test_decode_is_the_cheapest_path(documents, toxic):
    """Against listing all paths of a lattice."""
    import itertools

    restorer = toxicity.Restorer(toxicity.language_model(toxic[0]))
    n = toxicity.SYMBOLS

    def cost(parts, lattice):
        total = sum(e for part, options in zip(parts, lattice, strict=True) for p, e in [min((o for o in options if o[0] == part), key=lambda o: o[1])])
        a = b = 0
        for ch in "".join(parts):
            s = restorer.of(ch)
            if s or b:
                total += restorer.cost[((0 if b == 0 else a) * n + b) * n + s]
            a, b = b, s
        return total + (restorer.cost[((0 if b == 0 else a) * n + b) * n] if b else 0.0)

    for token in ("m0r0n", "1d10t", "s.c.u.m", "ri v er", "aab1"):
        lattice = restorer.lattice(token)
        best = min(cost(parts, lattice) for parts in itertools.product(*[[o[0] for o in options] for options in lattice]))
        found = restorer.decode(token)
        assert min(cost(p, lattice) for p in itertools.product(*[[o[0] for o in options] for options in lattice]) if "".join(p).strip() == found) == pytest.approx(best)


def test_toxicity_of_odd_rows(documents, toxic):
    docs, labels = toxic
    model = toxicity.train(docs, labels, remainder(3) != 1)
    got = toxicity.scored(documents(ODD).withColumn("score", F.lit("x")).withColumn("label", F.lit(3)), model).collect()
    assert len(got) == len(ODD) and all(0 <= r.score <= 1 for r in got)
    assert toxicity.scored(documents([]), toxicity.train(documents([]), labels.limit(0), remainder(3) != 1)).count() == 0
