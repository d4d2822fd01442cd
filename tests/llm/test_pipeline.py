"""The stages against plain versions of what each must do with its own input."""

import corpus_pipeline
from orderstat.llm import classifier, common, decontaminate, mixing, simhash


def test_stages(spark, small):
    docs = common.table(spark, small, "documents")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality", "near_dedup", "decontamination", "mixing", "tokens"]
    seen = {}
    for name, stage in corpus_pipeline.STAGES:
        seen[name] = common.stored(stage(spark, docs, small), name)
        if name != "tokens":
            assert seen[name].dtypes == docs.dtypes
        before, docs = docs, seen[name]
        if name == "quality":
            want = {r["doc_id"] for r in classifier.quality(before, common.table(spark, small, "labels")).filter("predicted = 1").collect()}
            assert {r["doc_id"] for r in docs.collect()} == want
        if name == "near_dedup":
            assert {r["doc_id"] for r in docs.collect()} == {r["component_id"] for r in simhash.near_duplicates(before).collect()} and docs.count() == docs.select("doc_id").distinct().count()
        if name == "decontamination":
            bad = {r["doc_id"] for r in decontaminate.contained(before, common.table(spark, small, "benchmark")).collect()}
            assert {r["doc_id"] for r in docs.collect()} == {r["doc_id"] for r in before.collect()} - bad
        if name == "mixing":
            copies = {r["doc_id"]: r["copies"] for r in mixing.mixed(before).collect() if r["copies"]}
            assert {r["doc_id"]: r["count"] for r in docs.groupBy("doc_id").count().collect()} == copies
        if name == "tokens":
            assert docs.count() == before.count()


def test_odd_rows_pass_all_stages(spark, odd, none, small):
    for start in (odd, none):
        docs = start
        for name, stage in corpus_pipeline.STAGES:
            docs = common.stored(stage(spark, docs, small), name)
        assert docs.columns == ["doc_id", "start", "n_tokens", "ids_crc32"]
