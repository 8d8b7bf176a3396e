"""Every stage against a plain version of what it decides."""

import corpus_pipeline
from pyspark.sql import functions as F

from comotion.components import cut
from comotion.llm import lang_id, ngram_join, quality_rules
from comotion.llm.common import table


def test_stages(spark, small):
    docs = table(spark, small, "documents")
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["language_id", "quality_rules", "ngram_jaccard_join", "suffix_array_dedup", "packing"]
    steps = [docs]
    for _, stage in corpus_pipeline.STAGES:
        steps.append(cut(stage(spark, steps[-1], small)))
    ids = lambda df: sorted(r.doc_id for r in df.select("doc_id").collect())
    und = {r.doc_id for r in lang_id.predict(docs, lang_id.train(docs)).filter("lang_pred = 'und'").collect()}
    assert not und & set(ids(steps[1])) and len(ids(steps[1])) >= 0.97 * (docs.count() - len(und))
    assert ids(steps[2]) == ids(quality_rules.judge(steps[1]).filter("kept"))
    assert ids(steps[3]) == ids(ngram_join.link_classes(steps[2]).filter("doc_id = component_id"))
    assert ids(steps[4]) == ids(steps[3]) and steps[4].schema.names == docs.schema.names
    assert steps[4].filter(F.length("text") != F.col("n_chars")).count() == 0
    assert ids(steps[5].filter("start = 0")) == ids(steps[4])
    assert corpus_pipeline.run(spark, small).count() == steps[5].count()


def test_empty(spark, small):
    docs = table(spark, small, "documents").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs = cut(stage(spark, docs, small))
        assert docs.count() == 0


def _words(k, n=80):
    return " ".join(f"s{k}w{j}" for j in range(n))


def test_one_row_of_each_class(spark):
    """Repeated and null doc_ids: one row of a class stays, and a doc_id with two texts loses only the copy."""
    near = _words(3).replace("s3w79", "other")
    rows = [(1, _words(1)), (1, _words(1)), (1, _words(1)), (None, _words(1)), (5, _words(1))]  # one class, three equal rows
    rows += [(None, _words(2)), (None, _words(2))]  # a class of null ids only
    rows += [(7, _words(3)), (None, near), (8, near), (8, _words(4))]  # 8 has a near copy and a text of its own
    rows += [(9, _words(5)), (9, _words(6)), (None, _words(6).replace("s6w0", "x")), (None, _words(7)), (10, ""), (11, None)]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    got = corpus_pipeline.near_duplicates(spark, docs, "")
    assert got.columns == docs.columns
    want = [(1, _words(1)), (None, _words(2)), (7, _words(3)), (8, _words(4)), (9, _words(5)), (9, _words(6)), (None, _words(7)), (10, ""), (11, None)]
    assert sorted(((r.doc_id, r.text) for r in got.collect()), key=repr) == sorted(want, key=repr)
    # the stage after it takes nothing out of the one copy that is left
    after = corpus_pipeline.repeated_passages(spark, cut(got), "")
    assert sorted(((r.doc_id, r.text) for r in after.collect()), key=repr) == sorted(want, key=repr)
