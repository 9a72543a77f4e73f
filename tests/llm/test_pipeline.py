"""The pipeline's stages on a small table, each held against its operator's rule."""

import corpus_pipeline
import pytest
from pyspark.sql import functions as F

from tsproof.llm import queries, shared, toxicity


def test_stages_keep_the_columns_and_take_effect(spark, sf):
    docs = shared.table(spark, sf, "documents")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = shared.written(stage(spark, docs, sf))
        assert out.columns == docs.columns and 0 < out.count() <= docs.count()
        assert out.join(docs, "doc_id", "left_anti").count() == 0, name
        docs = out
    leaked = queries.decontamination.find_leaks(docs, shared.table(spark, sf, "benchmark"))
    assert leaked.where("_leak_coverage >= 0.5").count() == 0
    assert queries.near_dedup.near_duplicates(docs).where("not kept").count() == 0
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, sf)
    assert packed.select("doc_id").distinct().count() == docs.count()


def test_run_and_empty(spark, sf):
    assert corpus_pipeline.run(spark, sf).where(F.col("n_tokens") > F.col("capacity")).count() == 0
    empty = shared.table(spark, sf, "documents").where("doc_id < 0")
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, empty, sf).count() == 0


def test_odd_rows_pass_the_filters(spark, sf):
    docs = shared.table(spark, sf, "documents").where("doc_id < 20")
    odd = spark.createDataFrame([(None, "a text without an id", "en", "x", 20), (900, None, None, None, None), (901, "", "en", "x", 0), (902, "twice here", "en", "x", 10), (902, "twice here", "en", "x", 10)], docs.schema)
    rows = docs.unionByName(odd)
    for _, stage in corpus_pipeline.STAGES[:-1]:
        rows = shared.written(stage(spark, rows, sf))
    kept = [(r["doc_id"], r["text"]) for r in rows.collect() if r["doc_id"] is None or r["doc_id"] >= 900]
    assert sorted(kept, key=str) == sorted([(None, "a text without an id"), (900, None), (901, ""), (902, "twice here"), (902, "twice here")], key=str)


def test_scratch_is_released(spark):
    start = shared.mark(spark)
    a, b = (shared.written(spark.range(3)) for _ in range(2))
    assert shared.release(spark, start, keep=(b,)) == 1 and b.count() == 3
    with pytest.raises(Exception):
        a.count()
    assert shared.release(spark, start) == 1


def resident():
    """MB of the process's own memory."""
    rows = dict(x.split(":") for x in open("/proc/self/status"))
    return int(rows["RssAnon"].split()[0]) // 1024


def test_freed_memory_goes_back_to_the_system():
    held = [bytearray(60_000) for _ in range(3000)]
    pins = held[1::100]  # allocations in between keep the allocator from shrinking by itself
    del held
    before = resident()
    shared.give_back()
    assert before - resident() > 100 and len(pins) == 30


def test_training_leaves_nothing_behind(spark, sf, monkeypatch):
    back, give_back = [], shared.give_back
    monkeypatch.setattr(shared, "give_back", lambda: back.append(1) or give_back())
    toxicity.train(shared.table(spark, sf, "documents"), shared.table(spark, sf, "labels"))
    assert back
