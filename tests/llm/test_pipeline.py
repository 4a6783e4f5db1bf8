from collections import Counter

import corpus_pipeline as p
from tests.llm.conftest import ODD

from roundmm.llm import queries


def test_stages_and_run(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    names = docs.columns
    ids = [docs.count()]
    for name, stage in p.STAGES[:-1]:
        docs = p.stored(stage(spark, docs, sf_dir), "stage-" + name.replace(" ", "-"))
        assert docs.columns == names
        ids.append(docs.count())
    assert ids[0] >= ids[1] > ids[2] > ids[3] > 0 and ids[4] > 0
    last = p.STAGES[-1][1](spark, docs, sf_dir)
    assert sorted(map(tuple, last.collect())) == sorted(map(tuple, p.run(spark, sf_dir).collect()))


def test_stages_take_odd_rows(spark, sf_dir, documents):
    docs = documents(ODD).selectExpr("*", "1 as shard", "2 as rate", "3 as score")
    rows = lambda df: Counter((r.doc_id, r.text) for r in df.collect())
    whole = rows(docs)
    for (_, stage), most in zip(p.STAGES[:-1], ("some", "all", "all", "copies"), strict=True):
        got = stage(spark, docs, sf_dir)
        assert got.columns == docs.columns
        kept = rows(got)
        if most == "all":
            assert kept == whole
        elif most == "some":
            assert kept and all(n == whole[r] for r, n in kept.items())
        else:
            assert kept and all(r in whole and n % whole[r] == 0 for r, n in kept.items())
        assert stage(spark, docs.limit(0), sf_dir).count() == 0
    plan = p.STAGES[-1][1](spark, docs, sf_dir)
    assert Counter(r.doc_id for r in plan.collect()) == Counter(r[0] for r in ODD)
    assert p.STAGES[-1][1](spark, docs.limit(0), sf_dir).count() == 0


def test_a_query_for_each_operator():
    assert {k.split("_")[0] for k in queries.QUERIES} == {f"op{n}" for n in range(1, 11)}
