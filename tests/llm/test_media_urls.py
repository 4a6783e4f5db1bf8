import hashlib
import zlib

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from tests.llm.conftest import ODD

from roundmm.llm import media, urls


@given(st.binary(max_size=4000))
@settings(max_examples=60, deadline=None)
def test_chunks_join_to_the_file(raw):
    payload = media.padded(raw)
    assert len(payload) % 64 == 0 and len(payload) >= 64
    file = media.wave(payload)
    assert media.samples(file) == payload and b"".join(media.chunks(file)) == file
    assert media.has_prefix(payload, hashlib.sha256(raw).digest())


def test_chunk_sizes_and_shared_chunks():
    import random

    raw = random.Random(2).randbytes(200_000)
    parts = media.chunks(raw)
    assert all(media.LEAST <= len(p) <= media.MOST for p in parts[:-1])
    moved = media.chunks(raw[:50] + b"inserted" + raw[50:])
    assert len(set(parts) & set(moved)) > 0.9 * len(parts)


def expected(text):
    raw = (text or "").encode()
    p = media.padded(raw)
    return len(raw), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:]), len(p) + 44, hashlib.sha256(media.wave(p)).hexdigest()


def test_report_reads_back_what_was_stored(documents):
    base = " ".join(f"word{i * i % 977}" for i in range(4000))
    rows = [(1, base), (2, base + " tail"), (3, "head " + base), (4, base), (5, "small"), (6, "ends in zeros\x00\x00"), *[(r[0], r[1]) for r in ODD]]
    docs = documents(rows).selectExpr("*", "1 as key", "2 as parts")
    got = media.media_report(docs).collect()
    assert len(got) == len(rows)
    want = sorted((str(i), *expected(t)) for i, t in rows)
    assert sorted((str(r.doc_id), r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32, r.media_bytes, r.media_sha256) for r in got) == want
    assert len({r.feature for r in got if r.payload_sha256 == expected(base)[2]}) == 1
    assert media.media_report(documents([])).count() == 0


def test_store_holds_each_chunk_once(documents):
    base = " ".join(f"word{i * i % 977}" for i in range(8000))
    store = media.chunk_store(documents([(1, base), (2, base + " tail"), (3, "head " + base), (4, base)])).collect()
    held = [p["digest"] for r in store for p in r["parts"]]
    assert len(held) == len(set(held)) and len(store) == 3
    assert sum(len(p["data"]) for r in store for p in r["parts"]) < 2 * len(base)


def test_damage_is_noticed():
    file = media.wave(media.padded(b"some text"))
    key = hashlib.sha256(b"some text").digest()
    media.described(key, [(0, media.digest(file), file)])
    with pytest.raises(ValueError):
        media.described(key, [(0, media.digest(file), file[:-1] + b"x")])
    other = media.wave(media.padded(b"other"))
    with pytest.raises(ValueError):
        media.described(key, [(0, media.digest(other), other)])


PAGES = [
    ("https://a.example.net/en/1", "allow", "example.net/en/"),
    ("https://a.example.net/fr/1", "block", "net/"),
    ("https://example.com/de/x", "block", "example.com/de/"),
    ("https://notexample.com/de/x", "allow", None),
    ("https://x.org/fr/", "allow", "org/fr/"),
    ("https://spam-farm.example.org/fr/1", "allow", "org/fr/"),
    ("https://spam-farm.example.org/en/1", "block", None),
    ("https://spammer.example.org/en/1", "allow", None),
    ("https://free-bets.example.com/en/1", "block", None),
    ("https://ads-track.example.com/en/1", "allow", None),
    ("https://ads-track.example.com/promo", "block", None),
    ("https://cheap.example.org/en/free", "block", None),
    ("https://cheap.example.org/en/cheap", "allow", None),
    ("HTTP://A.NET?x", "allow", None),
    ("HTTP://A.NET/?x", "block", "net/"),
    ("no scheme.net/", "allow", None),
    ("a://b://c.net/", "allow", None),
    (None, "allow", None),
    ("", "allow", None),
]


def test_rules_and_terms(spark):
    rows = [(i, u, "html") for i, (u, _, _) in enumerate(PAGES)] + [(None, "https://casino.example.org", None)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "1 as host", "2 as rule")
    got = {r.page_id: r for r in urls.judged(pages).collect()}
    for i, (u, verdict, rule) in enumerate(PAGES):
        assert (got[i].verdict, got[i].rule) == (verdict, rule), u
    assert got[None].verdict == "block" and got[17].host == "" and got[13].host == "a.net"
    assert urls.judged(pages.limit(0)).count() == 0


def test_a_vocabulary_from_a_table(spark):
    terms = spark.createDataFrame([("Gold", 0.5), ("gold", 0.6), ("mine", 0.4), ("rush", 2.0), (None, 1.0), ("", 1.0), ("never", 0.0), ("word", None)], "term string, weight double")
    v = urls.Vocabulary.of_table(terms, rules=())
    assert v.weights == {"gold": 0.6, "mine": 0.4, "rush": 2.0}
    pages = spark.createDataFrame([(1, "http://GOLD.a/mine"), (2, "http://gold.a/gold"), (3, "http://a/rush"), (4, "http://a/golden"), (5, "x" * 100_000)], "page_id long, url string")
    assert {r.page_id: (r.verdict, r.strict_terms, r.soft_terms) for r in urls.judged(pages, v).collect()} == {1: ("block", 0, 2), 2: ("allow", 0, 1), 3: ("block", 1, 0), 4: ("allow", 0, 0), 5: ("allow", 0, 0)}
    assert {r.verdict for r in urls.judged(pages, urls.Vocabulary({}, rules=())).collect()} == {"allow"}
    with pytest.raises(ValueError):
        urls.Vocabulary.of_table(terms, most=2)
