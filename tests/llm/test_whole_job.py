"""Training-data operators must do the whole job."""

import string

import numpy as np

import corpus_pipeline
from ctxloom.llm import langid, simhash
from ctxloom.session import load

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def test_every_language_has_a_filter(spark):
    r = np.random.default_rng(5)
    words = {f"l{k:02d}": ["".join(r.choice(list(string.ascii_lowercase), 6)) for _ in range(12)] for k in range(70)}
    rows = [(i, " ".join(r.choice(words[f"l{i % 70:02d}"], 40)), f"l{i % 70:02d}", "s", 0) for i in range(560)]
    rows.append((1000, "abcdef", "once", "s", 0))  # one row with rare 4-grams only
    rows.append((1001, "abcdef", "once", "s", 0))
    rows.append((1002, "abcdef", "once", "s", 0))
    docs = spark.createDataFrame(rows, DOCS)
    filters = langid.train(docs)
    assert filters.languages == [*sorted(words), "once"] and filters.masks.shape[1] == 2
    got = {x.doc_id: x.lang_pred for x in langid.identify(docs, filters).collect()}
    assert all(got[i] == lang for i, _, lang, _, _ in rows)


def test_texts_that_no_filter_knows_go(spark, sf):
    docs = load(spark, sf, "documents")
    clean = docs.where("lang is not null and length(text) > 200")
    strange = spark.createDataFrame([(-1, "съешь же ещё этих мягких французских булок " * 9, None, "s", 0), (-2, "zqxj vkqz xwqj " * 9, None, "s", 0)], docs.schema)
    ids = lambda df: {r.doc_id for r in df.select("doc_id").collect()}
    assert ids(corpus_pipeline.language(spark, clean.unionByName(strange), sf)) == ids(clean)


def test_near_copies_across_the_bound_of_short_texts():
    r = np.random.default_rng(3)
    texts = [" ".join("".join(r.choice(list(string.ascii_lowercase), 6)) for _ in range(32)) for _ in range(50)]
    prints = simhash.fingerprints([*texts, *(t.rsplit(" ", 1)[0] for t in texts)])
    assert simhash.likeness(prints[:50], prints[50:]).mean() > 0.85
