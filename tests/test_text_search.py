"""Search by inverted lists: no row for each pair of question and item, the SQL's rows, also where few items share a bucket."""

import pytest
from oracle import difference

from qacurate.operators import decontam as D
from qacurate.queries import REGISTRY


@pytest.mark.parametrize("name", ["topk_text", "judge_pairs", "decontaminate_text"])
def test_search_makes_no_row_for_each_pair(spark, sf, name):
    df = REGISTRY.queries[name](spark, sf)
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "bucket" not in plan
    assert difference(df, REGISTRY.oracles[name], sf) == ""


def test_only_items_that_share_a_bucket_are_found(spark):
    words = "id string, words array<string>"
    q = spark.createDataFrame([("a", ["apple"]), ("b", []), ("c", ["pear", "apple"])], words)
    m = spark.createDataFrame([(7, ["apple"]), (9, ["stone"]), (3, ["pear"]), (4, ["pear"])], "item_id long, words array<string>")
    found = D.topk_text(q, m).collect()
    assert [(r.id, r.item_id, r["rank"], r.similarity) for r in sorted(found)] == [("a", 7, 1, 1.0), ("c", 3, 1, 0.707107), ("c", 4, 2, 0.707107), ("c", 7, 3, 0.707107)]


def test_more_than_five_thousand_items_are_taken(spark):
    m = spark.range(6000).selectExpr("id as item_id", "array(concat('w', id)) as words")
    q = spark.createDataFrame([("a", ["w5999"])], "id string, words array<string>")
    assert {r.similarity for r in D.topk_text(q, m).collect()} == {1.0}
