"""The five stages in order, each on its own input, against what each must do."""

import hashlib

import corpus_pipeline
from boolmat.llm import pii, quality_rules
from boolmat.llm.common import load, written


def test_stages(spark, sf):
    docs = load(spark, sf, "documents")
    columns = docs.columns
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["quality_rules", "minhash_near_dedup", "pii", "mixing", "byte_bpe"]
    out = {}
    for name, stage in corpus_pipeline.STAGES:
        before = docs
        docs = out[name] = written(stage(spark, docs, sf), name)
        assert docs.count() > 0
        if name != "byte_bpe":
            assert docs.columns == columns
        if name in ("quality_rules", "minhash_near_dedup"):
            assert docs.exceptAll(before).count() == 0 and docs.count() < before.count()
    rules = quality_rules.learn_rules(load(spark, sf, "documents"), load(spark, sf, "labels"))
    judged = quality_rules.apply_rules(load(spark, sf, "documents").select("doc_id", "text"), rules).where("kept").select("doc_id")
    assert "Generate" in judged._jdf.queryExecution().optimizedPlan().toString()  # the filter stays above the statistics
    assert sorted(r[0] for r in judged.collect()) == sorted(r.doc_id for r in out["quality_rules"].select("doc_id").collect())
    assert all(not pii.base_spans(r.text) for r in out["pii"].collect())
    assert all(r.n_tokens == len(r.ids) for r in docs.collect())
    texts = sorted(hashlib.sha256(r.text.encode()).hexdigest() for r in out["mixing"].collect())
    assert texts == sorted(r.decoded_sha256 for r in docs.collect())


def test_copies_with_equal_or_null_ids_go(spark):
    text = lambda k: " ".join(f"w{k}x{i}" for i in range(40))
    rows = [(7, text(0)), (7, text(0)), (None, text(0)), (9, text(0) + " tail"), (None, text(1)), (None, text(1)), (3, text(2)), (3, text(3)), (8, text(4)), (None, text(5))]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string").repartition(3)
    got = corpus_pipeline.near_duplicate_stage(spark, docs, "")
    want = [(7, text(0)), (None, text(1)), (3, text(2)), (3, text(3)), (8, text(4)), (None, text(5))]
    assert got.columns == docs.columns and sorted(map(str, map(tuple, got.collect()))) == sorted(map(str, want))


def test_stages_take_odd_rows(spark, sf):
    """Null, empty, blank and very long texts, repeated rows, null ids and sources, clashing names, an empty table."""
    long = " ".join(f"word{i % 977}of{i % 89}" for i in range(60_000))
    prose = lambda k: " ".join(f"plain{(i * k) % 211} tale{i}" for i in range(60))
    texts = [None, "", " \n\t", long, prose(3), prose(3), prose(5) + " mail me at a.b@c.example.org"]
    rows = [(i, t, "en", ["s", None][i % 2], len(t or "")) for i, t in enumerate(texts)] + [(4, prose(3), "en", "s", 1), (None, prose(7), None, None, None)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    for c in ("row", "kept", "key", "n_words", "p", "ids"):
        docs = docs.withColumn(c, docs.doc_id)
    for table in (docs, docs.limit(0)):
        now = table
        for name, stage in corpus_pipeline.STAGES:
            now = written(stage(spark, now, sf), name)
            if name != "byte_bpe":
                assert now.columns == docs.columns, name
            if name == "minhash_near_dedup" and table is docs:
                assert sorted(len(r.text) for r in now.collect()) == sorted(map(len, (long, prose(3), texts[6], prose(7))))
        assert (now.count() == 0) == (table is not docs)
