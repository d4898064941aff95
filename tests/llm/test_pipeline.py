import corpus_pipeline
import pytest

from bitempo.llm import simhash, toxicity
from bitempo.llm.common import stash, table


def test_stages_in_order_and_effective(spark):
    sf = "/root/testdata/sf0.01"  # enough labelled toxic texts to learn from
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language", "toxicity", "near_duplicates", "mixing", "packing"]
    docs = before = table(spark, sf, "documents")
    for name, stage in corpus_pipeline.STAGES:
        docs = stash(stage(spark, before, sf), name)
        if name != "packing":
            assert docs.columns == table(spark, sf, "documents").columns
        if name == "language":
            assert docs.count() == before.count()  # every given text has letters
        elif name == "toxicity":
            gone = before.join(docs, "doc_id", "left_anti").join(table(spark, sf, "labels"), "doc_id")
            assert docs.count() < before.count() and gone.where("toxic = 0").count() == 0
        elif name == "near_duplicates":
            prints = [simhash.text_fingerprint(r["text"]) for r in docs.collect()]
            assert len(prints) == len(set(prints)) == len({simhash.text_fingerprint(r["text"]) for r in before.collect()})
        elif name == "packing":
            assert docs.groupBy("doc_id", "piece", "sequence_id", "offset").count().where("count > 1").count() == 0
        before = docs


@pytest.mark.parametrize("rows", [[], [(1, None, None, None, None)], [(1, "...", "en", "s", 3), (2, "abc", None, None, None), (2, "abc", None, None, None)]])
def test_small_tables_pass_through(spark, sf, rows):
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for name, stage in corpus_pipeline.STAGES:
        docs = stash(stage(spark, docs, sf), name)
    assert docs.count() <= 3 * len(rows) and toxicity.THRESHOLD == 0.7
