import re

import corpus_pipeline as P

from .test_dedup_join import brute, lower


def test_stages_on_a_fixture(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    kept = {}
    for name, stage in P.STAGES:
        before = docs
        docs = stage(spark, docs, data).cache()
        kept[name] = docs
        if name != "packing":
            assert docs.columns == before.columns, name
    rows = lambda n: [(r.doc_id, r.text) for r in kept[n].select("doc_id", "text").collect()]
    clean = rows("toxicity")
    best = {}
    for i, t in clean:
        best[lower(t)] = max(best.get(lower(t), -1), i)
    assert sorted(i for i, _ in rows("exact_dedup")) == sorted(best.values())
    groups = brute(rows("exact_dedup"))
    assert sorted(i for i, _ in rows("jaccard_join")) == sorted(set(groups.values()))
    words = lambda n: sum(len(re.findall(r"[^\x20\x09-\x0D]+", t)) for _, t in rows(n))
    assert abs(words("mixing") - 1.5 * words("jaccard_join")) <= 30
    packed = kept["packing"].collect()
    assert {r.doc_id for r in packed} == {i for i, _ in rows("mixing")}


def test_stages_on_empty_input(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet").where("false")
    for name, stage in P.STAGES:
        out = stage(spark, docs, data)
        assert out.count() == 0, name
        docs = docs if name == "packing" else out
