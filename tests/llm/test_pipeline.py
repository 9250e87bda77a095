"""The pipeline's stages against plain versions of their decisions."""

import corpus_pipeline
from balcut.llm import decontaminate, secrets
from balcut.llm.quality import quality_rules, trusted_labels
from balcut.llm.shared import settle, table

from .test_near_copies import both


def test_stages_one_by_one(spark, sf):
    docs = table(spark, sf, "documents")
    columns = docs.columns
    kept = {r["doc_id"] for r in quality_rules(docs, trusted_labels(table(spark, sf, "labels"))).where("kept").collect()}
    one = settle(corpus_pipeline.STAGES[0][1](spark, docs, sf), "one")
    assert one.columns == columns and {r["doc_id"] for r in one.collect()} == kept

    text = {r["doc_id"]: r["text"] for r in one.collect()}
    want = both(text)
    two = settle(corpus_pipeline.STAGES[1][1](spark, one, sf), "two")
    assert two.columns == columns and sorted(r["doc_id"] for r in two.collect()) == sorted(set(want.values()))

    items = [(r["item_id"], decontaminate.normalised(r["text"])) for r in table(spark, sf, "benchmark").collect()]
    three = settle(corpus_pipeline.STAGES[2][1](spark, two, sf), "three")
    left = {r["doc_id"] for r in three.collect()}
    for r in two.collect():
        if any(b in decontaminate.normalised(r["text"]) for _, b in items):
            assert r["doc_id"] not in left
    assert len(left) > 0.8 * two.count()

    four = settle(corpus_pipeline.STAGES[3][1](spark, three, sf), "four")
    assert four.columns == columns and four.count() == three.count()
    assert secrets.secret_scan(four).where("size(base) > 0").count() == 0

    five = corpus_pipeline.STAGES[4][1](spark, four, sf)
    assert five.count() == four.count() and five.where("not round_trip").count() == 0


def test_run(spark, sf):
    assert len(corpus_pipeline.STAGES) == 5
    assert corpus_pipeline.run(spark, sf).count() > 0


def test_texts_under_one_id_are_judged_apart(spark):
    rows = [(1, "some text of several words", "en", "s", 1), (1, "some text of several words", "en", "s", 1), (1, "another text", "en", "s", 1), (2, None, "en", "s", 1), (3, "", "en", "s", 1)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    out = corpus_pipeline.STAGES[1][1](spark, df, "").collect()
    assert sorted((r["doc_id"], r["text"]) for r in out) == [(1, "another text"), (1, "some text of several words"), (2, None)]
