"""Words in a middle share of many documents link them, however many those are."""

from ripplegraph.plans.scratch import Scratch
from ripplegraph.sources import builders


def test_words_of_more_than_20000_documents_are_kept(spark, tmp_path):
    """20,800 of 52,000 documents are 40 % of them; 20,801 would be more."""
    text = "CASE WHEN id % 5 < 2 THEN concat('alpha beta gamma w', id) ELSE concat('w', id) END AS text"
    spark.range(52_000).selectExpr("id AS doc_id", text).write.parquet(f"{tmp_path}/documents.parquet")
    own, n_words = builders.doc_word_sets(spark, str(tmp_path), Scratch(spark, "test"))
    assert n_words == 3
    assert own.count() == own.where("doc_id % 5 < 2 and array_sort(words) = array(0, 1, 2)").count() == 20_800
