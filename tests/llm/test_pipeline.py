import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from stagewise.llm import exact_dedup, registry, simhash
from stagewise.llm.common import stash, table

from test_operators import similar_components


@pytest.mark.parametrize("name", sorted(registry.ORACLE_SQL))
def test_rows_match_sql(spark, sf, same_rows, name):
    same_rows(registry.QUERIES[name](spark, sf), registry.ORACLE_SQL[name])


def test_stages_take_effect(spark, sf):
    docs = table(spark, sf, "documents")
    one = corpus_pipeline.without_toxic(spark, docs, sf)
    assert one.columns == docs.columns and 0.7 * docs.count() < one.count() <= docs.count()
    two = corpus_pipeline.without_copies(spark, one, sf)
    assert two.columns == docs.columns and exact_dedup.exact_groups(two).where("group_size > 1").count() == 0
    three = corpus_pipeline.without_near_copies(spark, two, sf)
    assert three.columns == docs.columns
    texts = [(r["doc_id"], r["text"]) for r in two.select("doc_id", "text").collect()]
    want = similar_components(texts, 0.8)
    assert sorted(r["doc_id"] for r in three.collect()) == sorted(k for k, c in want if k == c)
    assert three.count() <= simhash.simhash_groups(two).select("component_id").distinct().count()
    four = corpus_pipeline.mixed_sources(spark, three, sf)
    assert four.columns == docs.columns and four.groupBy("doc_id").count().where("count > 2").count() == 0
    assert corpus_pipeline.tokenized(spark, four, sf).count() == four.count()


def test_stages_on_awkward_rows(spark, sf):
    """Nulls, empty and repeated rows and columns of clashing names pass each stage; an empty table stays empty."""
    rows = [(1, None, "a"), (2, "", None), (2, "", None), (None, "some words of a text", "a"), (3, "Some words of a text", "b"), (3, "some words of a text", "b"), (4, "word " * 30_000, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string").withColumns({"__key": F.lit(1), "score": F.lit(2), "k": F.lit(3), "a.b": F.lit(4)})
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stash(stage(spark, docs, sf))
        assert out.columns == docs.columns, name
        assert 0 < out.count() <= docs.count() * (2 if name == "mixing" else 1)
        assert stage(spark, docs.limit(0), sf).count() == 0, name
        docs = out
    assert corpus_pipeline.tokenized(spark, docs, sf).count() == docs.count()
    assert corpus_pipeline.tokenized(spark, docs.limit(0), sf).count() == 0


def test_run(spark, sf):
    assert corpus_pipeline.run(spark, sf).where("n_tokens > 0 and length(decoded_sha256) = 64").count() > 0
