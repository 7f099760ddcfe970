import collections

import corpus_pipeline
from ctxloom.llm import registry
from ctxloom.session import load


def test_stages(spark, sf):
    docs = load(spark, sf, "documents")
    columns, before = docs.columns, docs.count()
    kept = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        kept = stage(spark, kept, sf)
        assert kept.columns == columns, name
        if name != "mixture":
            now = kept.count()
            assert 0 < now <= before, name
            before = now
    out = corpus_pipeline.run(spark, sf).collect()
    assert max(collections.Counter(r.doc_id for r in out).values()) <= 2 and len(out) > 0


def test_empty_tables(spark, sf):
    docs = load(spark, sf, "documents").where("false")
    for name, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs, sf).count() == 0, name


ODD = "doc_id long, text string, lang string, source string, n_chars long, gone_id long, key string, copies int"


def test_odd_rows(spark, sf):
    """Nulls in every column, empty and long texts, repeated rows, one id with two texts, and columns that clash with the operators'."""
    docs = [(r.doc_id, r.text, r.lang, r.source) for r in load(spark, sf, "documents").collect()]
    long = " ".join(t for _, t, lang, _ in docs if lang == "en")
    rows = [*docs, docs[3], docs[3], (docs[4][0], docs[5][1], "en", None), (None, docs[6][1] + " more", None, None), (None, None, None, None), (9001, "", "en", "a"), (9002, " \n\t", None, "b"), (9003, long, "en", None), (9004, "123 !!", "en", "é")]
    odd = spark.createDataFrame([(i, t, a, b, len(t or ""), i, "k", 7) for i, t, a, b in rows], ODD)
    kept, seen = odd, odd.collect()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        kept = stage(spark, kept, sf)
        assert kept.columns == odd.columns, name
        now = kept.collect()
        assert set(now) <= set(seen), name
        if name == "language":
            assert not any(r.text is None or not any(c.isalpha() for c in r.text) for r in now) and 9003 in {r.doc_id for r in now}
        if name != "mixture":
            assert len(now) <= len(seen)
        else:
            assert max(collections.Counter(now).values()) <= 2 * max(collections.Counter(seen).values())
        seen = now
    assert corpus_pipeline.STAGES[-1][1](spark, kept, sf).count() == len(seen)


def test_ten_queries():
    assert [n.split("_")[0] for n in registry.QUERIES] == [f"op{i}" for i in range(1, 11)]
